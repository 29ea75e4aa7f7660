"""The experiment workloads: parameter sweeps, method comparison, scaling, forecasts.

Walks depend on (graph, seeds, alpha_r, n_w) only, so rows of a sweep that share them share one set of visits.
Full grids are the constants below; `grid` arguments take any subset.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcomm import sources
from localcomm.operators import forecast as fc
from localcomm.operators import graph as gr
from localcomm.operators import mapped
from localcomm.operators import metrics as me
from localcomm.operators import partition as pa
from localcomm.operators import ranking as rk
from localcomm.operators import walks as wa
from localcomm.params import EFFECTIVENESS, Params, derive_params
from localcomm.plans import oracle as sql
from localcomm.plans.stages import staged

ALPHAS = tuple(round(0.1 * i, 1) for i in range(1, 8))
T_S = tuple(0.5 * i for i in range(1, 11))
T_E = tuple(round(0.1 * i, 1) for i in range(1, 10))
PHI_FORECAST = tuple(round(0.1 * i, 1) for i in range(1, 7))
TRIALS = (100, 300, 1000, 3000, 10_000, 30_000, 100_000)
FULL_GRID = tuple([("alpha_r", a) for a in ALPHAS] + [("alpha_n", a) for a in ALPHAS] + [("phi_o", a) for a in ALPHAS] + [("t_s", t) for t in T_S])


def _all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def _scenario(df: DataFrame, i: int) -> DataFrame:
    return df.withColumn("seed", F.lit(i).cast("long") * rk.SCENARIO + F.col("seed"))


def _tag(df: DataFrame, **tags) -> DataFrame:
    return df.select(*[F.lit(v).alias(k) for k, v in tags.items()], *df.columns)


def subgraph_accuracy(w, grid=FULL_GRID, k: int = 10, p: Params = Params(stop="fixed")) -> DataFrame:
    """parameter, value, partition_difference, top20_difference, p: means over seeds, with against without the subgraph.

    The whole grid is one job: each row is a scenario. Rows that differ in the walks alone share the whole graph's answer.
    """
    spark, seeds = w.edges.sparkSession, w.seeds(k)
    m, total = w.combined.agg(F.count(F.lit(1)), 2 * F.sum("w")).first()
    rows = [p.but(**{name: value}) for name, value in grid]
    scenarios, every, deg = [(q, derive_params(m, q)) for q in rows], rk.scenario_seeds(seeds, range(len(rows))), gr.degrees(w.combined, "w")
    if mapped.wanted(spark, p, m) and p.n_w <= pa.FUSED_TRIALS:
        ours, sizes = pa.scenarios_mapped(w.combined, every, w.n, scenarios, total), staged(mapped.relevant_sizes(w.combined, every, w.n, scenarios), "sizes")
    else:
        deg, adj = staged(deg, "deg"), _adjacency(w.combined, p)
        visits = {q.alpha_r: q for q in rows}
        visits = {a: staged(wa.walk_visits(w.combined, seeds, q, adj), "visits") for a, q in visits.items()}
        nodes = staged(_all([_scenario(wa.relevant(visits[q.alpha_r], w.n, q), i) for i, q in enumerate(rows)]), "relevant")
        ours, sizes = pa.scenarios_swept(gr.induced(w.combined, nodes).select("seed", "src", "dst", "w"), nodes, deg, every, scenarios, total), nodes.groupBy("seed").count()
    ranked = list(dict.fromkeys((q.alpha_n, q.phi_o) for q in rows))
    whole = [p.but(alpha_n=a, phi_o=f) for a, f in ranked]
    theirs = pa.whole_swept(w.combined, deg, rk.scenario_seeds(seeds, range(len(whole))), [(q, derive_params(m, q)) for q in whole], total, m)
    of = spark.createDataFrame([(i, ranked.index((q.alpha_n, q.phi_o)), *grid[i][:1], float(grid[i][1])) for i, q in enumerate(rows)], "i long, whole long, parameter string, value double")

    def spread(df: DataFrame) -> DataFrame:
        return df.join(F.broadcast(of), F.expr(f"seed DIV {rk.SCENARIO}") == F.col("whole")).withColumn("seed", F.col("i") * rk.SCENARIO + F.expr(f"seed % {rk.SCENARIO}"))  # a row for each grid row

    mean = lambda df, c, name: df.groupBy(F.expr(f"seed DIV {rk.SCENARIO}").alias("i")).agg(F.avg(c).alias(name))
    diff = mean(me.set_difference_size(ours.members, spread(theirs.members)), "symmetric", "partition_difference")
    top = mean(me.topk_difference(ours.curve, spread(theirs.curve)), "difference", "top20_difference")
    size = mean(sizes, "count", "p")
    return F.broadcast(of).join(diff, "i").join(top, "i").join(size, "i").select("parameter", "value", "partition_difference", "top20_difference", "p")


def rank_times(w, k: int = 10, p: Params = Params(stop="fixed")) -> DataFrame:
    """method, seconds: ranking inside the subgraph and on the whole graph, loading left out."""
    seeds, spark = w.seeds(k), w.edges.sparkSession
    _loaded(w.combined, p)
    rows = [(name, me.timed(lambda: pa.attributed_partition(w.combined, seeds, w.n, p, use_proximity=use).summary)) for name, use in (("subgraph", True), ("whole", False))]  # noqa: B023
    return spark.createDataFrame(rows, "method string, seconds double")


def _loaded(combined: DataFrame, p: Params) -> None:
    """Map a large graph before its methods are timed."""
    if mapped.wanted(combined.sparkSession, p, combined.count()):
        mapped.layout(combined, p.weighted)


def _adjacency(combined: DataFrame, p: Params) -> DataFrame | None:
    """The adjacency for several walks on a graph; None if they read a mapped one."""
    return None if mapped.wanted(combined.sparkSession, p, combined.count()) else staged(gr.adjacency(combined, p.weighted), "adjacency")


def _tenth(w, t: int, p: Params) -> tuple[DataFrame, DataFrame]:
    """Edges and combined graph of a nested part: an edge weighs what it does in the whole, and a mapped part comes from the mapped whole."""
    e, c = staged(gr.edge_fraction(w.edges, t), "tenth"), gr.edge_fraction(w.combined, t)
    if mapped.wanted(e.sparkSession, p, e.count()):
        mapped.kept(c, w.combined, gr.fraction_mask(t))
    else:
        c = staged(c, "tenth-combined")
    mapped.twins(pa.plain_of(e), c)
    return e, c


def trial_insensitivity(w, trials=TRIALS, k: int = 10, p: Params = Params()) -> DataFrame:
    """n_w, p: mean size of the subgraph by number of trials."""
    seeds, adj = w.seeds(k), _adjacency(w.combined, p)
    return _all([_tag(wa.relevant(wa.walk_visits(w.combined, seeds, p.but(n_w=t), adj), w.n, p.but(n_w=t)).groupBy("seed").count().agg(F.avg("count").alias("p")), n_w=t) for t in trials])


def size_independence(w, tenths=range(1, 11), k: int = 3, p: Params = Params()) -> DataFrame:
    """tenth, m, p, m_p: mean size of the subgraph on nested parts of the graph."""
    out = []
    for t in tenths:
        e, c = _tenth(w, t, p)
        s = wa.proximity_subgraph(c, staged(gr.sample_seeds(e, k), "seeds"), w.n, p)
        size = me.subgraph_size(s.sub_nodes, s.sub_edges, w.n).agg(F.avg("p").alias("p"), F.avg("m_p").alias("m_p"))
        out.append(_tag(size, tenth=t, m=e.count()))
    return _all(out)


def effectiveness(w, k: int, p: Params) -> DataFrame:
    """Means of density, nodes and triangles of the attributed and the structural partition, and the density ratio."""
    seeds = w.seeds(k)
    a, b = pa.attributed_partition(w.combined, seeds, w.n, p), pa.structural_partition(w.edges, seeds, w.n, p)
    return me.compare(me.partition_quality(a.members, w.edges), me.partition_quality(b.members, w.edges))


def scalability(w, tenths=range(1, 11), k: int = 3, p: Params = Params(stop="fixed")) -> DataFrame:
    """tenth, m, seconds of both methods on nested parts of the graph, loading left out, and their ratio."""
    rows = []
    for t in tenths:
        e, c = _tenth(w, t, p)
        seeds = staged(gr.sample_seeds(e, k), "seeds")
        _loaded(c, p)
        _loaded(pa.plain_of(e), p)
        ours = me.timed(lambda: pa.attributed_partition(c, seeds, w.n, p).summary)  # noqa: B023
        theirs = me.timed(lambda: pa.structural_partition(e, seeds, w.n, p).summary)  # noqa: B023
        rows.append((t, e.count(), ours, theirs, theirs / ours))
    return w.edges.sparkSession.createDataFrame(rows, "tenth int, m long, attributed_s double, structural_s double, ratio double")


def forecast_sweep(w, name: str, values, k: int = 20, p: Params = Params(t_s=5.0, t_e=0.7, stop="fixed"), removed: float = 0.15, less: DataFrame | None = None) -> DataFrame:
    """parameter, value, gain_v, gain_e, best_v, best_e: gain of the forecast on the graph without `removed` of its edges.

    Each value is a scenario of three jobs: original, graph with less, the same with the forecast. `less`: edges to keep instead.
    Values of t_e, phi_o or another parameter of the ranking; the walks are the same for all.
    """
    seeds, rows = w.seeds(k), [p.but(**{name: float(v)}) for v in values]
    kept = staged(gr.drop_edges(w.edges, removed) if less is None else less, "kept")
    less = staged(sources.Graph(w.nodes, kept).combined(), "removed")
    every = rk.scenario_seeds(seeds, range(len(rows)))
    each = F.explode(F.array(*[F.struct(F.lit(i).cast("long").alias("i"), F.lit(float(q.t_e if q.t_e is not None else 0.7)).alias("t_e")) for i, q in enumerate(rows)]))
    spread = lambda df: df.withColumn("x", each).withColumn("seed", F.col("x.i") * rk.SCENARIO + F.col("seed"))

    def swept(combined: DataFrame, sub: wa.SubgraphSet, edges: DataFrame | None = None) -> pa.PartitionResult:
        m, total = combined.agg(F.count(F.lit(1)), 2 * F.coalesce(F.sum("w"), F.lit(0.0))).first()
        own = spread(sub.sub_edges).select("seed", "src", "dst", "w") if edges is None else edges
        deg = gr.degrees(combined, "w") if edges is None else fc.grown_degrees(edges, combined)
        return pa.scenarios_swept(own, sub.sub_nodes, deg, every, [(q, derive_params(m, q)) for q in rows], total)

    first, second = wa.proximity_subgraph(w.combined, seeds, w.n, p), wa.proximity_subgraph(less, seeds, w.n, p)
    done = spread(fc.complete_edges(second, w.nodes, min(q.t_e if q.t_e is not None else 0.7 for q in rows)))
    done = staged(done.where("NOT is_predicted OR w > x.t_e").select("seed", "src", "dst", "w", "is_predicted"), "completed")
    a, b, c = swept(w.combined, first), swept(less, second), swept(less, second, done)
    inner = lambda e, m: gr.induced(e.select("src", "dst"), m)
    ends = lambda end: c.members.select("seed", F.col("node").alias(end))
    g = me.forecast_gain(a.members, b.members, c.members, inner(w.edges, a.members), inner(kept, b.members), done.select("seed", "src", "dst").join(ends("src"), ["seed", "src"]).join(ends("dst"), ["seed", "dst"]))
    g = g.groupBy(F.expr(f"seed DIV {rk.SCENARIO}").alias("i")).agg(F.avg("gain_v").alias("gain_v"), F.avg("gain_e").alias("gain_e"), F.max("gain_v").alias("best_v"), F.max("gain_e").alias("best_e"))
    told = w.edges.sparkSession.createDataFrame([(i, name, float(v)) for i, v in enumerate(values)], "i long, parameter string, value double")
    return F.broadcast(told).join(g, "i").drop("i")


def parts_before(spark, sf_dir: str, quantile: float = 0.85) -> DataFrame:
    """Edges of `parts` that the orders up to a date give: the graph as it was when so many of its orders were in."""
    o = sources.table(spark, sf_dir, "orders").select("o_orderkey", F.unix_micros(F.col("o_orderdate").cast("timestamp")).alias("t"))
    cut = o.approxQuantile("t", [quantile], 0.001)[0]
    lines = sources.table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'").select("l_partkey", "l_orderkey")
    early = lines.join(o.where(F.col("t") <= cut), F.col("l_orderkey") == F.col("o_orderkey"))
    return gr.project_bipartite(early, "l_partkey", "l_orderkey").select("src", "dst")


def temporal(spark, sf_dir: str, quantile: float = 0.85) -> DataFrame:
    """graph, edges before a cut date and of the whole time: snapshots of the user graph."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    cut = e.select(F.unix_micros(F.col("ts").cast("timestamp")).alias("t")).approxQuantile("t", [quantile], 0.001)[0]
    x = e.select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), F.concat_ws("|", F.date_trunc("hour", "ts").cast("string"), "props").alias("g"))
    whole = gr.project_bipartite(x, "user_id", "g").select("src", "dst")
    before = gr.project_bipartite(x.where(F.col("t") <= cut), "user_id", "g").select("src", "dst")
    late = whole.join(before, ["src", "dst"], "left_anti").withColumn("period", F.lit("after"))
    return before.withColumn("period", F.lit("before")).unionByName(late)


def seed_latency(w, counts=(1, 10, 100, 1000), p: Params = Params(stop="fixed", n_w=2000)) -> DataFrame:
    """seeds, seconds of one batch of partitions."""
    rows = []
    for k in counts:
        seeds = w.seeds(k)
        rows.append((k, me.timed(lambda: pa.attributed_partition(w.combined, seeds, w.n, p).summary)))  # noqa: B023
    return w.edges.sparkSession.createDataFrame(rows, "seeds int, seconds double")


#: The brand whose parts are a graph or a set of members of their own.
BRAND = "Brand#7"
TOY_SETS = {1: "a b c", 2: "0 1 2 3 4 5 6", 4: "0 1 2 3 4 5 6 7 8 9", 3: "7 8 9 x1 x2 x3 x4 x5 x6 x7 x8 x9 x10", 5: "p", 6: "r", 7: "q7", 8: "q8", 9: "q9", 10: "q10"}
TOY_EDGES = [(1, 2), (1, 3), (3, 4), (2, 4), (1, 5), (3, 6), (5, 6), (6, 7), (7, 8), (8, 9), (9, 10), (5, 10)]


def toy(spark):
    """A graph whose members 1..4 have ratios 0.5, 0, 0.477, 0."""
    nodes = spark.createDataFrame([(n, s.split()) for n, s in TOY_SETS.items()], "node long, attrs array<string>")
    return nodes, spark.createDataFrame(TOY_EDGES, "src long, dst long")


def register(query) -> None:
    from localcomm.plans import catalogue as cat

    own = f"SELECT p_partkey AS node FROM part WHERE p_brand = '{BRAND}'"

    @query("toy_ratio_cut", sql.query(sql.combined(), f"members AS ({own})", "ins AS (SELECT m.node, coalesce(sum(b.w), 0) AS deg, coalesce(sum(b.w) FILTER (x.node IS NOT NULL), 0) AS inside FROM members m LEFT JOIN both_b b ON b.src = m.node LEFT JOIN members x ON x.node = b.dst GROUP BY m.node)", select="SELECT node, round((deg - inside) / nullif(inside, 0) + 1e-9, 6) AS ratio FROM ins"))
    def _(s, d):
        """Ratios of a given set of members: the parts of one brand."""
        members = sources.table(s, d, "part").where(F.col("p_brand") == BRAND).select(F.lit(1).cast("long").alias("seed"), F.col("p_partkey").alias("node"))
        # A nudge keeps ratios that end in a five from rounding either way.
        return me.vertex_ratio(members, cat.world(s, d).combined).select("node", F.round(F.col("ratio") + 1e-9, 6).alias("ratio"))

    @query("three_graphs", sql.query(sql.PARTS, f"own AS (SELECT * FROM attrs WHERE node IN ({own})), pairs AS (SELECT a.node AS src, b.node AS dst, {sql.SIM} AS j, EXISTS (SELECT 1 FROM edges e WHERE e.src = a.node AND e.dst = b.node) AS tied FROM own a JOIN own b ON a.node < b.node)", select="SELECT src, dst, round(CASE WHEN j > 0 THEN j ELSE 0.05 END, 6) AS sim, round(CASE WHEN tied THEN 1 ELSE 0 END + CASE WHEN j > 0 THEN j ELSE 0.05 END, 6) AS w FROM pairs WHERE tied OR j > 0.7"))
    def _(s, d):
        """Structure, attribute and combined graph of the parts of one brand; pairs alike by more than 0.7 are tied too."""
        w = cat.world(s, d)
        mine = sources.table(s, d, "part").where(F.col("p_brand") == BRAND).select(F.col("p_partkey").alias("node"))
        nodes = w.nodes.join(mine, "node", "left_semi")
        edges = w.edges.join(mine.withColumnRenamed("node", "src"), "src", "left_semi").join(mine.withColumnRenamed("node", "dst"), "dst", "left_semi").select("src", "dst")
        c = gr.combined_graph(gr.attribute_graph(nodes, edges, t_e=0.7))
        return c.select("src", "dst", F.round("w_a", 6).alias("sim"), F.round("w", 6).alias("w"))

    # Whole grids, seeds and numbers of trials; they take long on large graphs.
    for g in ("parts", "docs"):
        query(f"experiment_accuracy_{g}")(lambda s, d, g=g: subgraph_accuracy(cat.world(s, d, g)))
        query(f"experiment_rank_times_{g}")(lambda s, d, g=g: rank_times(cat.world(s, d, g)))
        query(f"experiment_forecast_t_e_{g}")(lambda s, d, g=g: forecast_sweep(cat.world(s, d, g), "t_e", T_E))
        query(f"experiment_forecast_phi_{g}")(lambda s, d, g=g: forecast_sweep(cat.world(s, d, g), "phi_o", PHI_FORECAST, p=Params(t_s=5.0, t_e=0.6, stop="fixed")))
    query("experiment_trials_parts")(lambda s, d: trial_insensitivity(cat.world(s, d)))
    query("experiment_size_parts")(lambda s, d: size_independence(cat.world(s, d)))
    for g, k in (("parts", 20), ("pages", 20), ("docs", 100)):
        query(f"experiment_effectiveness_{g}")(lambda s, d, g=g, k=k: effectiveness(cat.world(s, d, g), k, EFFECTIVENESS))
    query("experiment_scalability_parts")(lambda s, d: scalability(cat.world(s, d)))
    query("experiment_seed_latency_parts")(lambda s, d: seed_latency(cat.world(s, d), p=Params(stop="fixed")))
    # The forecast on a real snapshot: the graph of the orders up to a date, against that of all orders.
    query("experiment_temporal_parts")(lambda s, d: forecast_sweep(cat.world(s, d), "t_e", T_E, less=parts_before(s, d)))
    for g in ("parts", "pages"):
        query(f"experiment_walk_counts_{g}")(lambda s, d, g=g: wa.visit_histogram(wa.walk_visits(cat.world(s, d, g).combined, cat.world(s, d, g).seeds(1), Params())))
    query("temporal_snapshot_users")(lambda s, d: temporal(s, d))
    query("graph_vectors")(lambda s, d: sources.vectors(s, d).edges)
    query(
        "bipartite_customers_parts", "SELECT DISTINCT o_custkey AS customer, l_partkey AS part FROM orders JOIN lineitem ON l_orderkey = o_orderkey"
    )(lambda s, d: sources.bipartite(s, d))
