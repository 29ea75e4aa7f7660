"""All queries of the engine by name, with their SQL twins where SQL can say them."""

from __future__ import annotations

from collections.abc import Callable
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcomm import sources
from localcomm.functions.sets import jaccard
from localcomm.operators import forecast as fc
from localcomm.operators import graph as gr
from localcomm.operators import mapped
from localcomm.operators import metrics as me
from localcomm.operators import partition as pa
from localcomm.operators import walks as wa
from localcomm.params import FORECAST, Params
from localcomm.plans import oracle as sql
from localcomm.plans.stages import staged

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

#: What the catalogue runs with: a fixed number of rank steps, so that SQL can follow; fewer trials than the production queries at the end.
P = Params(stop="fixed", n_w=2000)
FORE = P.but(t_s=5.0, t_e=0.3)
SEEDS = 5
_made: dict[tuple, tuple] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


class World:
    """A graph's tables, staged once per session and state of the folder, when a query first needs them."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str):
        g = sources.GRAPHS[name](spark, sf_dir)
        self.nodes, self.edges = staged(g.nodes, f"{name}-nodes"), staged(g.edges, f"{name}-edges")
        self.name = name
        self._seeds: dict[int, DataFrame] = {}

    @cached_property
    def combined(self) -> DataFrame:
        c = staged(sources.Graph(self.nodes, self.edges).combined(), f"{self.name}-combined")
        mapped.twins(pa.plain_of(self.edges), c)
        return c

    @cached_property
    def n(self) -> int:
        return self.nodes.count()

    def seeds(self, k: int = SEEDS) -> DataFrame:
        if k not in self._seeds:
            self._seeds[k] = staged(gr.sample_seeds(self.edges, k), "seeds")  # all vertices are looked at for them
        return self._seeds[k]


def _version(spark: SparkSession, sf_dir: str) -> tuple:
    """The tables under a folder as they are now: names, sizes and times of change."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(sf_dir)
    files = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).listStatus(where)
    return (spark.sparkContext.applicationId, sf_dir, *sorted((f.getPath().getName(), f.getLen(), f.getModificationTime()) for f in files))


def forget(graphs: bool = True) -> None:
    """Drop the results that queries share, and the staged graphs if asked, so that the next one pays for what it needs."""
    for key in [k for k in _made if graphs or not k[-1].startswith("world-")]:
        del _made[key]


def world(spark: SparkSession, sf_dir: str, name: str = "parts") -> World:
    return made(spark, sf_dir, f"world-{name}", lambda: World(spark, sf_dir, name))


def made(spark, sf_dir, what: str, build):
    """An intermediate result that several queries share."""
    key = (*_version(spark, sf_dir), what)
    if key not in _made:
        _made[key] = build()
    return _made[key]


def rounded(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in names})


def attributed(spark, d, name="parts", p=P, k=SEEDS) -> pa.PartitionResult:
    w = world(spark, d, name)
    return made(spark, d, f"attributed-{name}-{p}-{k}", lambda: pa.attributed_partition(w.combined, w.seeds(k), w.n, p))


def structural(spark, d, name="parts", p=P, k=SEEDS) -> pa.PartitionResult:
    w = world(spark, d, name)
    return made(spark, d, f"structural-{name}-{p}-{k}", lambda: pa.structural_partition(w.edges, w.seeds(k), w.n, p))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return attributed(spark, sf_dir).summary


# Graph construction -------------------------------------------------------------------------------------------------

for _g in ("parts", "docs", "pages", "users", "customers"):
    query(f"structure_graph_{_g}", sql.query(sql.GRAPHS[_g], select="SELECT src, dst FROM edges"))(lambda s, d, g=_g: world(s, d, g).edges)
for _g in ("parts", "docs"):
    query(f"combined_graph_{_g}", sql.query(sql.combined(_g), select="SELECT src, dst, round(w, 6) AS w, CAST(1 AS DOUBLE) AS w_g, round(sim, 6) AS w_a, true AS is_structural FROM combined"))(
        lambda s, d, g=_g: rounded(world(s, d, g).combined, "w", "w_a")
    )


@query("attribute_graph_parts", sql.query(sql.combined(), select="SELECT src, dst, round(sim, 6) AS sim, true AS is_structural FROM combined"))
def _(s, d):
    w = world(s, d)
    return rounded(gr.attribute_graph(w.nodes, w.edges), "sim")


@query("attribute_graph_global_parts", sql.query(sql.combined(), select=f"SELECT src, dst, round(sim, 6) AS sim, true AS is_structural FROM combined UNION ALL SELECT a.node, b.node, round({sql.SIM}, 6), false FROM attrs a JOIN attrs b ON a.node < b.node WHERE {sql.SIM} > 0.5 AND NOT EXISTS (SELECT 1 FROM edges e WHERE e.src = a.node AND e.dst = b.node)"))
def _(s, d):
    w = world(s, d)
    return rounded(gr.attribute_graph(w.nodes, w.edges, t_e=0.5), "sim")


@query("jaccard_edges_docs", sql.query(sql.combined("docs"), select="SELECT src, dst, round(j, 6) AS sim FROM sims"))
def _(s, d):
    w = world(s, d, "docs")
    return gr.with_sets(w.edges, w.nodes).select("src", "dst", F.round(jaccard(F.col("xa"), F.col("xb")), 6).alias("sim"))


@query("degree_distribution_parts", sql.query(sql.combined(), select="SELECT deg, count(*) AS vertices FROM (SELECT src, count(*) AS deg FROM both_b GROUP BY src) GROUP BY deg"))
def _(s, d):
    return gr.degrees(world(s, d).edges).groupBy("deg").agg(F.count(F.lit(1)).alias("vertices"))


@query("degrees_combined_parts", sql.query(sql.combined(), select="SELECT node, round(deg, 6) AS deg FROM deg_b"))
def _(s, d):
    return rounded(gr.degrees(world(s, d).combined, "w"), "deg")


@query("csr_parts", sql.query(sql.combined(), select="SELECT node, CAST(sum(len(columns)) OVER (ORDER BY node) - len(columns) AS BIGINT) AS row_ptr, CAST(len(columns) AS INTEGER) AS columns FROM (SELECT a.node, coalesce(list(dst) FILTER (dst IS NOT NULL), []) AS columns FROM attrs a LEFT JOIN both_b b ON b.src = a.node GROUP BY a.node)"))
def _(s, d):
    w = world(s, d)
    return gr.to_csr(w.nodes, w.edges).select("node", "row_ptr", F.size("columns").alias("columns"))


@query("edge_removal_parts", sql.query(sql.combined(removed=0.15), select="SELECT src, dst FROM used"))
def _(s, d):
    return gr.drop_edges(world(s, d).edges)


@query("graph_tenths_parts", sql.query(sql.PARTS, select=f"SELECT t AS tenth, count(*) AS m FROM edges, range(1, 11) AS r(t) WHERE {sql.draw_sql('src', 'dst', salt=7)} < t * {sql.PRIME // 10} + CASE WHEN t >= 10 THEN {sql.PRIME} ELSE 0 END GROUP BY t"))
def _(s, d):
    e = world(s, d).edges
    out = None
    for t in range(1, 11):
        one = gr.edge_fraction(e, t).agg(F.count(F.lit(1)).alias("m")).select(F.lit(t).cast("long").alias("tenth"), "m")
        out = one if out is None else out.unionByName(one)
    return out


def _stats_sql(g: str) -> str:
    return f"""(WITH RECURSIVE {sql.GRAPHS[g]}, sym AS (SELECT src, dst FROM edges UNION SELECT dst, src FROM edges),
reach AS (SELECT node, node AS label FROM attrs UNION SELECT s.dst, r.label FROM reach r JOIN sym s ON s.src = r.node WHERE r.label < s.dst),
lab AS (SELECT node, min(label) AS label FROM reach GROUP BY node), deg AS (SELECT a.node, count(s.dst) AS deg FROM attrs a LEFT JOIN sym s ON s.src = a.node GROUP BY a.node)
SELECT '{g}' AS graph, count(*) AS n, CAST(sum(deg) / 2 AS BIGINT) AS m, round(avg(deg), 6) AS mean_deg, max(deg) AS max_deg, CAST(sum(CASE WHEN deg = 0 THEN 1 ELSE 0 END) AS BIGINT) AS isolated,
(SELECT count(DISTINCT label) FROM lab) AS components, (SELECT max(c) FROM (SELECT count(*) AS c FROM lab GROUP BY label)) AS largest FROM deg)"""


def _stats(s, d, *names: str) -> DataFrame:
    out = None
    for g in names:
        one = rounded(gr.network_stats(world(s, d, g).nodes, world(s, d, g).edges), "mean_deg").select(F.lit(g).alias("graph"), "n", "m", "mean_deg", "max_deg", "isolated", "components", "largest")
        out = one if out is None else out.unionByName(one)
    return out


query("network_stats_all", _stats_sql("docs") + " UNION ALL " + _stats_sql("pages"))(lambda s, d: _stats(s, d, "docs", "pages"))
# SQL spreads labels too slowly over graphs of one large component.
query("network_stats_connected")(lambda s, d: _stats(s, d, "parts", "users", "customers"))


@query("validate_parts", sql.query(sql.PARTS, select="SELECT CAST(0 AS BIGINT) AS null_ids, CAST(0 AS BIGINT) AS unordered, CAST(0 AS BIGINT) AS not_positive, CAST(0 AS BIGINT) AS loose_ends"))
def _(s, d):
    return gr.validated(world(s, d).nodes, world(s, d).combined)


@query("validate_broken_parts", sql.query(sql.combined(), "bad AS (SELECT dst AS src, src AS dst, w FROM combined WHERE src % 7 = 0 UNION ALL SELECT src, dst, -w FROM combined WHERE src % 5 = 0 UNION ALL SELECT NULL, dst, w FROM combined WHERE src % 11 = 0)", select="SELECT count(*) FILTER (src IS NULL OR dst IS NULL) AS null_ids, count(*) FILTER (src >= dst) AS unordered, count(*) FILTER (w <= 0) AS not_positive, (SELECT count(*) FROM (SELECT src AS v FROM bad UNION ALL SELECT dst FROM bad) WHERE v IS NULL OR v % 3 = 0) AS loose_ends FROM bad"))
def _(s, d):
    w = world(s, d)
    c = w.combined.select("src", "dst", "w")
    turned = c.where("src % 7 = 0").select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    bad = turned.unionAll(c.where("src % 5 = 0").withColumn("w", -F.col("w"))).unionAll(c.where("src % 11 = 0").withColumn("src", F.lit(None).cast("long")))
    return gr.validated(w.nodes.where("node % 3 <> 0"), bad)


# Walk subgraph ------------------------------------------------------------------------------------------------------

_W = (sql.combined(), sql.seeds(SEEDS), sql.walks(P))


def _sub(s, d, name="parts", p=P, k=SEEDS) -> wa.SubgraphSet:
    w = world(s, d, name)
    return made(s, d, f"sub-{name}-{p}-{k}", lambda: wa.proximity_subgraph(w.combined, w.seeds(k), w.n, p))


@query("walk_visits_parts", sql.query(*_W, select="SELECT seed, node, hits FROM visits"))
def _(s, d):
    return _sub(s, d).visits


@query("walk_visits_relational", sql.query(sql.combined(), sql.seeds(2), sql.walks(P.but(n_w=200, max_hops=4)), select="SELECT seed, node, hits FROM visits"))
def _(s, d):
    w = world(s, d)
    return wa.walk_visits(w.combined, w.seeds(2), P.but(n_w=200, max_hops=4, engine="relational"))


@query("walk_histogram_parts", sql.query(*_W, select="SELECT seed, hits, count(*) AS vertices FROM visits GROUP BY seed, hits"))
def _(s, d):
    return wa.visit_histogram(_sub(s, d).visits)


@query("relevance_rule_parts", sql.query(*_W, select="SELECT seed, node, hits FROM sub_nodes"))
def _(s, d):
    return _sub(s, d).sub_nodes


@query("relevance_count_rule_parts", sql.query(*_W, select="SELECT seed, node, hits FROM visits WHERE hits >= 100 OR node = seed"))
def _(s, d):
    return wa.relevant(_sub(s, d).visits, 1, P.but(rule="count", min_hits=100))


@query("subgraph_parts", sql.query(*_W, select="SELECT seed, src, dst, round(w, 6) AS w FROM sub_edges"))
def _(s, d):
    return rounded(_sub(s, d).sub_edges.select("seed", "src", "dst", "w"), "w")


@query("subgraph_size_parts", sql.query(*_W, select="SELECT s.seed, p, coalesce(m_p, 0) AS m_p, round(p / (SELECT count(*) FROM attrs), 6) AS share FROM (SELECT seed, count(*) AS p FROM sub_nodes GROUP BY seed) s LEFT JOIN (SELECT seed, count(*) AS m_p FROM sub_edges GROUP BY seed) e ON e.seed = s.seed"))
def _(s, d):
    x = _sub(s, d)
    return rounded(me.subgraph_size(x.sub_nodes, x.sub_edges, world(s, d).n), "share")


# Rank, sweep, partition ---------------------------------------------------------------------------------------------

_K = sql.steps_of(P)
_A = (*_W, sql.ranked(P, _K, "sub_edges"))
_CURVE = "SELECT c.seed, c.position, round(cut, 6) AS cut, round(vol, 6) AS vol, round(score, 6) AS score FROM {c} c"


def _curve(df: DataFrame) -> DataFrame:
    return rounded(df.select("seed", "position", "cut", "vol", "score"), "cut", "vol", "score")


@query("seed_rank_parts", sql.query(*_A, select="SELECT seed, node, position, round(rank, 6) AS rank FROM ord"))
def _(s, d):
    return rounded(attributed(s, d).curve.select("seed", "node", "position", "rank"), "rank")


@query("sweep_ratio_parts", sql.query(*_A, select=_CURVE.format(c="curve")))
def _(s, d):
    return _curve(attributed(s, d).curve)


@query("sweep_classic_parts", sql.query(*_W, sql.ranked(P.but(measure="classic"), _K, "sub_edges"), select=_CURVE.format(c="curve")))
def _(s, d):
    return _curve(attributed(s, d, p=P.but(measure="classic")).curve)


@query("attributed_partition_parts", sql.query(*_A, select="SELECT seed, size, round(score, 6) AS score, target_met FROM summary"))
def _(s, d):
    return rounded(attributed(s, d).summary, "score")


@query("attributed_members_parts", sql.query(*_A, select="SELECT seed, node, position FROM members"))
def _(s, d):
    return attributed(s, d).members


@query("attributed_partition_docs", sql.query(sql.combined("docs"), sql.seeds(SEEDS), sql.walks(P), sql.ranked(P, _K, "sub_edges"), select="SELECT seed, size, round(score, 6) AS score, target_met FROM summary"))
def _(s, d):
    return rounded(attributed(s, d, "docs").summary, "score")


@query("attributed_partition_relational", sql.query(sql.combined(), sql.seeds(2), sql.walks(P), sql.ranked(P.but(eps_t=0.5), sql.steps_of(P.but(eps_t=0.5)), "sub_edges"), select="SELECT seed, size, round(score, 6) AS score, target_met FROM summary"))
def _(s, d):
    w, p = world(s, d), P.but(eps_t=0.5, engine="relational")
    sub = _sub(s, d, p=P, k=2)
    total = 2 * w.combined.agg(F.sum("w")).first()[0]
    from localcomm.params import derive_params

    r = pa.ranked_and_swept(sub.sub_edges.select("seed", "src", "dst", "w"), sub.sub_nodes, gr.degrees(w.combined, "w"), w.seeds(2), p, derive_params(w.combined.count(), p), total)
    return rounded(r.summary, "score")


_FULL = (sql.combined(), sql.seeds(2), "whole AS (SELECT seed, src, dst, w, false AS predicted FROM combined, seeds)", sql.ranked(P, _K, "whole"))


def _without(s, d):
    w = world(s, d)
    return made(s, d, "without", lambda: pa.attributed_partition(w.combined, w.seeds(2), w.n, P, use_proximity=False))


@query("attributed_partition_full_graph", sql.query(*_FULL, select="SELECT seed, size, round(score, 6) AS score, target_met FROM summary"))
def _(s, d):
    return rounded(_without(s, d).summary, "score")


@query("attributed_rank_parts", sql.query(*_FULL, select="SELECT seed, node, position, round(rank, 6) AS rank FROM ord WHERE position <= 20"))
def _(s, d):
    w = world(s, d)
    return rounded(pa.attributed_rank(w.combined, w.seeds(2), P).select("seed", "node", "position", "rank"), "rank")


@query("rank_top20_difference", sql.query(sql.combined(), sql.seeds(2), sql.walks(P), sql.ranked(P, _K, "sub_edges"), "whole AS (SELECT seed, src, dst, w, false AS predicted FROM combined, seeds)", sql.ranked(P, _K, "whole", name="f"), select="SELECT a.seed, count(*) FILTER (b.node IS NULL) AS difference FROM ord a LEFT JOIN (SELECT * FROM ordf WHERE position <= 20) b ON b.seed = a.seed AND b.node = a.node WHERE a.position <= 20 GROUP BY a.seed"))
def _(s, d):
    return me.topk_difference(attributed(s, d, k=2).curve, _without(s, d).curve)


@query("partition_difference_parts", sql.query(sql.combined(), sql.seeds(2), sql.walks(P), sql.ranked(P, _K, "sub_edges"), "whole AS (SELECT seed, src, dst, w, false AS predicted FROM combined, seeds)", sql.ranked(P, _K, "whole", name="f"), select="SELECT coalesce(a.seed, b.seed) AS seed, count(*) FILTER (a.node IS NULL OR b.node IS NULL) AS symmetric, count(*) FILTER (b.node IS NULL) AS only_a, count(*) FILTER (a.node IS NULL) AS only_b FROM members a FULL JOIN membersf b ON b.seed = a.seed AND b.node = a.node GROUP BY 1"))
def _(s, d):
    return me.set_difference_size(attributed(s, d, k=2).members, _without(s, d).members)


_B1 = (sql.PARTS, sql.seeds(SEEDS), sql.plain(), sql.ranked(P.but(measure="classic"), _K, "gsub", "gdeg"))


@query("structural_partition_parts", sql.query(*_B1, select="SELECT seed, size, round(score, 6) AS score, target_met FROM summary"))
def _(s, d):
    return rounded(structural(s, d).summary, "score")


@query("structural_partition_strict", sql.query(*_B1, select="SELECT seed, CASE WHEN target_met THEN size ELSE 0 END AS size, round(score, 6) AS score, target_met FROM summary"))
def _(s, d):
    return rounded(structural(s, d, p=P.but(select="target")).summary, "score")


@query("truncated_walk_partition")
def _(s, d):
    w = world(s, d)
    return rounded(pa.truncated_walk_partition(w.edges, w.seeds(2), w.n, P).summary, "score")


@query("push_rank_parts")
def _(s, d):
    from localcomm.operators.ranking import push_rank

    w = world(s, d)
    return rounded(push_rank(gr.plain_graph(w.edges), w.seeds(2), eps=1e-3), "rank", "residual")


# Measures -----------------------------------------------------------------------------------------------------------


@query("partition_quality_parts", sql.query(*_A, sql.quality("members"), select="SELECT seed, nodes, edges, round(density, 6) AS density, triangles_x3, triangles FROM quality"))
def _(s, d):
    return rounded(me.partition_quality(attributed(s, d).members, world(s, d).edges), "density")


@query("structural_quality_parts", sql.query(*_B1, sql.quality("members"), select="SELECT seed, nodes, edges, round(density, 6) AS density, triangles_x3, triangles FROM quality"))
def _(s, d):
    return rounded(me.partition_quality(structural(s, d).members, world(s, d).edges), "density")


_IN = "ins AS (SELECT m.seed, m.node, sum(b.w) AS deg, coalesce(sum(b.w) FILTER (x.node IS NOT NULL), 0) AS inside FROM members m JOIN both_b b ON b.src = m.node LEFT JOIN members x ON x.seed = m.seed AND x.node = b.dst GROUP BY m.seed, m.node)"


@query("ratio_conductance_parts", sql.query(*_A, _IN, select="SELECT seed, round(CASE WHEN bool_and(inside > 0) THEN sum(CASE WHEN inside > 0 THEN (deg - inside) / inside END) END, 6) AS cut, round(sum(deg), 6) AS vol, round(CASE WHEN bool_and(inside > 0) THEN sum(CASE WHEN inside > 0 THEN (deg - inside) / inside END) END / sum(deg), 6) AS score FROM ins GROUP BY seed"))
def _(s, d):
    return rounded(me.ratio_conductance(attributed(s, d).members, world(s, d).combined), "cut", "vol", "score")


@query("classic_conductance_parts", sql.query(*_A, _IN, select="SELECT seed, round(sum(deg - inside), 6) AS cut, round(sum(deg), 6) AS vol, round(sum(deg - inside) / least(sum(deg), (SELECT sum(deg) FROM deg_b) - sum(deg)), 6) AS score FROM ins GROUP BY seed"))
def _(s, d):
    return rounded(me.classic_conductance(attributed(s, d).members, world(s, d).combined), "cut", "vol", "score")


@query("vertex_ratio_parts", sql.query(*_A, _IN, select="SELECT seed, node, round((deg - inside) / nullif(inside, 0) + 1e-9, 6) AS ratio, CASE WHEN inside = 0 THEN 'orphan' WHEN deg - inside < inside THEN 'inside' WHEN deg - inside > inside THEN 'outside' ELSE 'equal' END AS side FROM ins"))
def _(s, d):
    # A nudge keeps ratios that end in a five from rounding either way.
    return me.vertex_ratio(attributed(s, d).members, world(s, d).combined).withColumn("ratio", F.round(F.col("ratio") + 1e-9, 6))


@query("ratio_components_parts")
def _(s, d):
    return rounded(me.ratio_components(attributed(s, d).members, world(s, d).combined), "ext_g", "ext_a", "int_g", "int_a")


@query("compare_methods_parts")
def _(s, d):
    e = world(s, d).edges
    return me.compare(me.partition_quality(attributed(s, d).members, e), me.partition_quality(structural(s, d).members, e))


@query("cost_model_parts")
def _(s, d):
    w, x = world(s, d), _sub(s, d)
    size = me.subgraph_size(x.sub_nodes, x.sub_edges, w.n)
    grown = fc.complete_edges(x, w.nodes, 0.3).groupBy("seed").agg(F.count(F.lit(1)).alias("m_e"))
    seen = x.visits.groupBy("seed").agg(F.count(F.lit(1)).alias("visited"), F.sum("hits").alias("visits"))
    swept = attributed(s, d).curve.groupBy("seed").agg(F.count(F.lit(1)).alias("swept"))
    counts = me.cost_model(F.lit(w.n), F.lit(w.edges.count()), F.col("p"), F.col("m_p"), F.col("m_e"), F.lit(P.n_w))
    # Beside what the complexities say: vertices and visits the walks made, and prefixes swept.
    return size.join(grown, "seed", "left").na.fill(0, ["m_e"]).join(seen, "seed").join(swept, "seed").select("seed", "p", "m_p", "m_e", "visited", "visits", "swept", *[c.alias(k) for k, c in counts.items()])


@query("volume_parts", sql.query(*_A, select="SELECT m.seed, round(sum(d.deg), 6) AS vol FROM members m JOIN deg_b d ON d.node = m.node GROUP BY m.seed"))
def _(s, d):
    return rounded(gr.volume(attributed(s, d).members, gr.degrees(world(s, d).combined, "w")), "vol")


@query("graph_snapshot_parts", "WITH member AS (SELECT DISTINCT l_orderkey AS g, l_partkey AS m, o_orderdate AS ts FROM lineitem JOIN orders ON o_orderkey = l_orderkey WHERE l_returnflag = 'R') SELECT DISTINCT a.m AS src, b.m AS dst FROM member a JOIN member b ON a.g = b.g AND a.m < b.m WHERE a.ts <= TIMESTAMP '1998-04-25 00:00:00'")
def _(s, d):
    lines = sources.table(s, d, "lineitem").where("l_returnflag = 'R'").select("l_partkey", "l_orderkey")
    dated = lines.join(sources.table(s, d, "orders").select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    pairs = dated.select("l_orderkey", F.col("l_partkey").alias("src"), F.col("o_orderdate").alias("ts")).join(lines.select("l_orderkey", F.col("l_partkey").alias("dst")), "l_orderkey")
    return gr.snapshot(pairs, F.to_timestamp_ntz(F.lit("1998-04-25 00:00:00")))


# Completion and forecast --------------------------------------------------------------------------------------------

_F = (sql.combined(), sql.seeds(SEEDS), sql.walks(FORE), sql.completion(0.3))
for _s in ("pairs", "prefix"):

    @query(f"complete_edges_{_s}", sql.query(*_F, select="SELECT seed, src, dst, round(w, 6) AS w, predicted AS is_predicted FROM done"))
    def _(s, d, how=_s):
        return rounded(fc.complete_edges(_sub(s, d, p=FORE), world(s, d).nodes, 0.3, how), "w")


@query("minhash_pairs")
def _(s, d):
    return rounded(fc.similar_pairs(world(s, d).nodes, 0.7, "minhash"), "sim")


@query("similar_pairs_prefix", sql.query(sql.PARTS, select=f"SELECT a.node AS src, b.node AS dst, round({sql.SIM}, 6) AS sim FROM attrs a JOIN attrs b ON a.node < b.node WHERE {sql.SIM} > 0.5"))
def _(s, d):
    return rounded(fc.similar_pairs(world(s, d).nodes, 0.5), "sim")


def _forecast(s, d, name="parts", p=FORE):
    w = world(s, d, name)
    return made(s, d, f"forecast-{name}-{p}", lambda: fc.forecast_community(w.combined, w.nodes, w.seeds(), w.n, p))


@query("forecast_partition_parts", sql.query(*_F, sql.ranked(FORE, _K, "done"), select="SELECT seed, size, round(score, 6) AS score, target_met FROM summary"))
def _(s, d):
    return rounded(_forecast(s, d).summary, "score")


@query("predicted_links_parts", sql.query(*_F, select="SELECT * FROM (SELECT seed, src, dst, round(w, 6) AS w, row_number() OVER (PARTITION BY seed ORDER BY w DESC, src, dst) AS place FROM new_edges) WHERE place <= 20"))
def _(s, d):
    return rounded(fc.predicted_links(_forecast(s, d)), "w")


def _gain(name: str, t_e: float = 0.6, removed: float = 0.15):
    """Original, 85% graph, 85% graph with forecast, on the same seeds."""

    def run(s, d):
        w, p = world(s, d, name), P.but(t_s=5.0, t_e=t_e)
        seeds = w.seeds()
        less = staged(sources.Graph(w.nodes, gr.drop_edges(w.edges, removed)).combined(), "removed")
        a, b = pa.attributed_partition(w.combined, seeds, w.n, p), pa.attributed_partition(less, seeds, w.n, p)
        c = fc.forecast_community(less, w.nodes, seeds, w.n, p)
        inner = lambda e, m: gr.induced(e.select("src", "dst"), m)
        f = c.sub_edges.select("seed", "src", "dst").join(c.members.select("seed", F.col("node").alias("src")), ["seed", "src"]).join(c.members.select("seed", F.col("node").alias("dst")), ["seed", "dst"])
        return me.forecast_gain(a.members, b.members, c.members, inner(w.edges, a.members), inner(less, b.members), f)

    return run


query("forecast_gain_parts")(_gain("parts"))
query("forecast_gain_docs")(_gain("docs"))


@query("cold_start_parts", sql.query(sql.combined(), select="SELECT src AS seed, count(*) AS deg FROM both_b GROUP BY src HAVING count(*) <= 2"))
def _(s, d):
    return fc.cold_start_nodes(world(s, d).edges)


@query("ego_network_pages", sql.query(sql.PAGES, sql.seeds(SEEDS), "sym AS (SELECT src, dst FROM edges UNION SELECT dst, src FROM edges)", select="SELECT seed, node, CAST(min(hop) AS INTEGER) AS hop FROM (SELECT seed, seed AS node, 0 AS hop FROM seeds UNION ALL SELECT seed, dst, 1 FROM seeds JOIN sym ON src = seed UNION ALL SELECT seed, b.dst, 2 FROM seeds JOIN sym a ON a.src = seed JOIN sym b ON b.src = a.dst) GROUP BY seed, node"))
def _(s, d):
    w = world(s, d, "pages")
    return fc.ego_network(w.edges, w.seeds(), 2)


# Production parameters: 10,000 trials and all hops, too slow for SQL ----------------------------------------------------


@query("walk_visits_production")
def _(s, d):
    return _sub(s, d, p=Params()).visits


@query("walk_visits_relational_production")
def _(s, d):
    w = world(s, d)
    return wa.walk_visits(w.combined, w.seeds(), Params(engine="relational"))


for _g in ("parts", "docs"):
    query(f"attributed_partition_production_{_g}")(lambda s, d, g=_g: rounded(attributed(s, d, g, Params()).summary, "score"))
    query(f"structural_partition_production_{_g}")(lambda s, d, g=_g: rounded(structural(s, d, g, Params()).summary, "score"))
    query(f"forecast_partition_production_{_g}")(lambda s, d, g=_g: rounded(_forecast(s, d, g, FORECAST).summary, "score"))

from localcomm.plans import experiments, surroundings  # noqa: E402

experiments.register(query)
surroundings.register(query)
