"""Queries around the methods: scans, joins, windows, reports, functions, on the given tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from localcomm.functions.sets import register_sql
from localcomm.operators import graph as gr
from localcomm.params import Params, derive_params
from localcomm.plans import oracle as sql


def _t(s, d, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


def register(query) -> None:
    from localcomm.plans import catalogue as cat

    def add(name: str, oracle: str | None, f) -> None:
        query(name, oracle)(f)

    edges = lambda s, d: cat.world(s, d).edges
    pe = lambda select: sql.query(sql.PARTS, select=select)

    add("scan_filter_returns", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_returnflag = 'R'", lambda s, d: _t(s, d, "lineitem").where("l_returnflag = 'R'").select("l_orderkey", "l_partkey"))
    add("semi_join_touched_parts", pe("SELECT p_partkey, p_brand FROM part WHERE p_partkey IN (SELECT src FROM edges UNION SELECT dst FROM edges)"), lambda s, d: _t(s, d, "part").select("p_partkey", "p_brand").join(gr.both_ways(edges(s, d)).select(F.col("src").alias("p_partkey")), "p_partkey", "left_semi"))
    add("anti_join_isolated_parts", pe("SELECT p_partkey, p_brand FROM part WHERE p_partkey NOT IN (SELECT src FROM edges UNION SELECT dst FROM edges)"), lambda s, d: _t(s, d, "part").select("p_partkey", "p_brand").join(gr.both_ways(edges(s, d)).select(F.col("src").alias("p_partkey")), "p_partkey", "left_anti"))

    def full_outer(s, d):
        a, b = cat.attributed(s, d).members, cat.structural(s, d).members
        return a.select("seed", "node", F.col("position").alias("ours")).join(b.select("seed", "node", F.col("position").alias("theirs")), ["seed", "node"], "full_outer")

    add("full_outer_partitions", None, full_outer)
    add(
        "broadcast_region_attrs",
        "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
        # nation has 25 rows and region 5, by definition of the schema
        lambda s, d: _t(s, d, "customer").join(F.broadcast(_t(s, d, "nation").join(F.broadcast(_t(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name"),
    )

    def range_pick(s, d):
        from localcomm.functions.sets import draw
        from localcomm.operators.graph import adjacency

        adj = adjacency(cat.world(s, d).combined)
        asked = adj.select("src").distinct().withColumn("u", draw("src", salt=3))
        return asked.join(adj, "src").where("u * total div 2147483647 >= lo AND u * total div 2147483647 < hi").select("src", "dst")

    add(
        "range_pick_edges",
        sql.query(sql.combined(), "w1 AS (SELECT src, dst, greatest(1, CAST(round(w * 1000) AS BIGINT)) AS wi FROM both_b)", "adj AS (SELECT src, dst, CAST(sum(wi) OVER (PARTITION BY src ORDER BY dst) AS BIGINT) AS hi, wi, CAST(sum(wi) OVER (PARTITION BY src) AS BIGINT) AS total FROM w1)", select=f"SELECT a.src, a.dst FROM adj a JOIN (SELECT DISTINCT src, {sql.draw_sql('src', salt=3)} AS u FROM adj) k ON k.src = a.src AND k.u * a.total // {sql.PRIME} >= a.hi - a.wi AND k.u * a.total // {sql.PRIME} < a.hi"),
        range_pick,
    )
    e = "events"
    add(
        "interval_pairs_events",
        "SELECT a.event_id AS first_event, b.event_id AS second_event FROM events a JOIN events b ON a.props = b.props AND a.user_id < b.user_id AND abs(epoch(a.ts) - epoch(b.ts)) <= 60",
        lambda s, d: _interval(_t(s, d, e)),
    )
    add(
        "interval_pairs_events_ten_minutes",
        "SELECT a.event_id AS first_event, b.event_id AS second_event FROM events a JOIN events b ON a.props = b.props AND a.user_id < b.user_id AND abs(epoch(a.ts) - epoch(b.ts)) <= 600",
        lambda s, d: _interval(_t(s, d, e), 600),
    )
    add(
        "asof_events",
        "SELECT event_id, (SELECT max(p.ts) FROM events p WHERE p.user_id = x.user_id AND p.event_type = 'purchase' AND p.ts <= x.ts) AS last_purchase FROM events x WHERE event_type = 'error'",
        lambda s, d: _asof(_t(s, d, e)),
    )
    add("distinct_agg_users", "SELECT user_id, count(DISTINCT props) AS n_props, count(DISTINCT event_type) AS n_types FROM events GROUP BY user_id", lambda s, d: _t(s, d, e).groupBy("user_id").agg(F.count_distinct("props").alias("n_props"), F.count_distinct("event_type").alias("n_types")))
    add("approx_distinct_users", None, lambda s, d: _t(s, d, e).groupBy("user_id").agg(F.approx_count_distinct("props", 0.02).alias("n_props")))
    rep = sql.query(sql.combined(), "rep AS (SELECT p_brand AS brand, p_size // 10 AS bucket, sim FROM combined JOIN part ON p_partkey = src)", select="SELECT brand, CAST(bucket AS BIGINT) AS bucket, count(*) AS edges, round(avg(sim), 6) AS mean_sim FROM rep GROUP BY {g}")

    def report(s, d, how):
        base = cat.world(s, d).combined.join(_t(s, d, "part"), F.col("src") == F.col("p_partkey")).select(F.col("p_brand").alias("brand"), F.floor(F.col("p_size") / 10).cast("long").alias("bucket"), "w_a")
        agg = [F.count(F.lit(1)).alias("edges"), F.round(F.avg("w_a"), 6).alias("mean_sim")]
        if how == "sets":
            return base.groupingSets([["brand"], ["bucket"], []], "brand", "bucket").agg(*agg)
        return getattr(base, how)("brand", "bucket").agg(*agg)

    add("grouping_sets_report", rep.format(g="GROUPING SETS ((brand), (bucket), ())"), lambda s, d: report(s, d, "sets"))
    add("cube_report", rep.format(g="CUBE (brand, bucket)"), lambda s, d: report(s, d, "cube"))
    add("rollup_report", rep.format(g="ROLLUP (brand, bucket)"), lambda s, d: report(s, d, "rollup"))
    kinds = ["click", "view", "purchase", "error", "signup"]
    add("pivot_event_types", "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{k}') AS {k}" for k in kinds) + " FROM events GROUP BY user_id", lambda s, d: _t(s, d, e).groupBy("user_id").pivot("event_type", kinds).agg(F.count(F.lit(1))).na.fill(0))
    dg = "dg AS (SELECT p_brand AS brand, src AS node, count(*) AS deg FROM both_b JOIN part ON p_partkey = src GROUP BY ALL)"

    def ranks(s, d):
        w = Window.partitionBy("brand").orderBy(F.desc("deg"), "node")
        v = Window.partitionBy("brand").orderBy(F.desc("deg"))
        x = gr.degrees(edges(s, d)).join(_t(s, d, "part"), F.col("node") == F.col("p_partkey")).select(F.col("p_brand").alias("brand"), "node", "deg")
        return x.select("brand", "node", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(v).cast("long").alias("rk"), F.dense_rank().over(v).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("quarter"), F.round(F.percent_rank().over(v), 6).alias("pr"))

    add("rank_windows_parts", sql.query(sql.combined(), dg, select="SELECT brand, node, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER v, 6) AS pr FROM dg WINDOW w AS (PARTITION BY brand ORDER BY deg DESC, node), v AS (PARTITION BY brand ORDER BY deg DESC)"), ranks)
    add(
        "running_volume",
        sql.query(sql.combined(), dg, select="SELECT brand, node, CAST(sum(deg) OVER (PARTITION BY brand ORDER BY deg DESC, node ROWS UNBOUNDED PRECEDING) AS BIGINT) AS vol FROM dg"),
        lambda s, d: gr.degrees(edges(s, d)).join(_t(s, d, "part"), F.col("node") == F.col("p_partkey")).select(F.col("p_brand").alias("brand"), "node", F.sum("deg").over(Window.partitionBy("p_brand").orderBy(F.desc("deg"), "node").rowsBetween(Window.unboundedPreceding, Window.currentRow)).alias("vol")),
    )
    w_u = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")  # noqa: E731  (windows need a session)
    add(
        "lag_lead_events",
        "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
        lambda s, d: _t(s, d, e).select("event_id", F.lag("event_id").over(w_u()).alias("before"), F.lead("event_id").over(w_u()).alias("after")),
    )
    add(
        "range_frame_events",
        "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM events",
        lambda s, d: _t(s, d, e).select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy(F.unix_timestamp(F.col("ts").cast("timestamp"))).rangeBetween(-3600, 0)).alias("last_hour")),
    )
    add("topk_degree", sql.query(sql.combined(), dg, select="SELECT node, deg FROM dg ORDER BY deg DESC, node LIMIT 20"), lambda s, d: gr.degrees(edges(s, d)).orderBy(F.desc("deg"), "node").limit(20))
    add("topk_per_seed", sql.query(*cat._A, select="SELECT seed, CAST(position AS INTEGER) AS position, node FROM ord WHERE position <= 20"), lambda s, d: cat.attributed(s, d).curve.where("position <= 20").select("seed", "position", "node"))

    def set_ops(s, d):
        a, b = (x.select("seed", "node") for x in (cat.attributed(s, d).members, cat.structural(s, d).members))
        return a.union(b).distinct().withColumn("op", F.lit("union")).unionByName(a.intersect(b).withColumn("op", F.lit("both"))).unionByName(a.exceptAll(b).withColumn("op", F.lit("ours")))

    add("set_ops_members", None, set_ops)
    add(
        "text_functions_docs",
        "SELECT doc_id, md5(lower(trim(text, ' '))) AS h, len(string_split(text, chr(10))) AS lines, CAST(length(text) AS BIGINT) AS chars FROM documents",
        lambda s, d: _t(s, d, "documents").select("doc_id", F.md5(F.lower(F.trim("text"))).alias("h"), F.size(F.split("text", "\n")).cast("long").alias("lines"), F.length("text").cast("long").alias("chars")),
    )
    add(
        "date_functions_events",
        "SELECT date_trunc('day', ts)::TIMESTAMP AS day, count(*) AS events, CAST(max(hour(ts)) AS INTEGER) AS last_hour FROM events GROUP BY 1",
        lambda s, d: _t(s, d, e).groupBy(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day")).agg(F.count(F.lit(1)).alias("events"), F.max(F.hour("ts")).alias("last_hour")),
    )
    add(
        "array_functions_sets",
        sql.query(sql.combined(), select="SELECT src, dst, len(list_intersect(a.x, b.x)) AS shared, len(list_distinct(a.x || b.x)) AS either, len(list_filter(a.x, lambda v: len(v) > 4)) AS long FROM edges JOIN attrs a ON a.node = src JOIN attrs b ON b.node = dst"),
        lambda s, d: gr.with_sets(edges(s, d), cat.world(s, d).nodes).select("src", "dst", F.size(F.array_intersect("xa", "xb")).cast("long").alias("shared"), F.size(F.array_union("xa", "xb")).cast("long").alias("either"), F.size(F.filter("xa", lambda v: F.length(v) > 4)).cast("long").alias("long")),
    )
    add(
        "map_functions_weights",
        sql.query(sql.combined(), select="SELECT src AS node, count(*) AS n, CAST(count(*) FILTER (w > 1.1) AS BIGINT) AS strong FROM both_b GROUP BY src"),
        lambda s, d: gr.both_ways(cat.world(s, d).combined).groupBy(F.col("src").alias("node")).agg(F.map_from_entries(F.collect_list(F.struct("dst", "w"))).alias("m")).select("node", F.size(F.map_keys("m")).cast("long").alias("n"), F.size(F.map_filter("m", lambda k, v: v > 1.1)).cast("long").alias("strong")),
    )
    add(
        "json_props_sets",
        "SELECT user_id, list_sort(list_distinct(list(CAST(json_extract_string(props, '$.k') AS INTEGER)))) AS ks FROM events GROUP BY user_id",
        lambda s, d: _t(s, d, e).groupBy("user_id").agg(F.array_sort(F.collect_set(F.get_json_object("props", "$.k").cast("int"))).alias("ks")),
    )

    def math_params(s, d):
        """What follows from the sizes of graphs that have an edge for each order with a line of a return flag."""
        sizes = _t(s, d, "lineitem").groupBy(F.col("l_returnflag").alias("flag")).agg(F.countDistinct("l_orderkey").alias("m"))

        def job(frames):
            for f in frames:
                for flag, m in zip(f["flag"], f["m"].tolist(), strict=True):
                    got = [(phi, derive_params(m, Params(phi_o=phi))) for phi in (0.05, 0.2)]
                    yield pd.DataFrame({"flag": flag, "m": m, "phi": [phi for phi, _ in got], "l": [x.l for _, x in got], "t_last": [x.t_last for _, x in got], "b": [round(x.b, 6) for _, x in got]})

        return sizes.mapInPandas(job, "flag string, m long, phi double, l int, t_last long, b double")

    add("math_params", "SELECT flag, CAST(m AS BIGINT) AS m, CAST(phi AS DOUBLE) AS phi, CAST(ceil(log2(m)) AS INTEGER) AS l, CAST((ceil(log2(m)) + 1) * ceil(2 / (phi * phi) * ln(200 * (ceil(log2(m)) + 2) * sqrt(m))) AS BIGINT) AS t_last, round((1 + log2(m)) / 2, 6) AS b FROM (SELECT l_returnflag AS flag, count(DISTINCT l_orderkey) AS m FROM lineitem GROUP BY l_returnflag) AS a, (VALUES (0.05::DOUBLE), (0.2::DOUBLE)) AS b(phi)", math_params)

    def udf(s, d):
        register_sql(s)
        return gr.with_sets(edges(s, d), cat.world(s, d).nodes).select("src", "dst", F.round(F.expr("jaccard_sets(xa, xb)"), 6).alias("sim"))

    add("udf_sql_jaccard", sql.query(sql.combined(), select="SELECT src, dst, round(j, 6) AS sim FROM sims"), udf)
    add("udaf_curve_median", sql.query(*cat._A, select="SELECT CAST(position AS INTEGER) AS position, round(median(score), 6) AS median_score FROM curve GROUP BY position"), lambda s, d: cat.attributed(s, d).curve.groupBy("position").agg(F.round(F.percentile("score", 0.5), 6).alias("median_score")))
    add(
        "length_filtered_pairs",
        sql.query(sql.PAGES, select="SELECT a.node AS src, b.node AS dst FROM attrs a JOIN attrs b ON a.node < b.node AND 10 * len(b.x) >= 8 * len(a.x) AND 10 * len(a.x) >= 8 * len(b.x)"),
        lambda s, d: _banded(cat.world(s, d, "pages").nodes),
    )

    def csv_json(s, d):
        from localcomm import sources
        from localcomm.plans.stages import shared_root

        g, root = edges(s, d), f"{shared_root(s)}/roundtrip-{s.sparkContext.applicationId}"
        for fmt in ("csv", "json"):
            sources.write_table(g, f"{root}-{fmt}", fmt)
        return sources.read_edges(s, f"{root}-csv", "csv").intersect(sources.read_edges(s, f"{root}-json", "json"))

    add("csv_json_roundtrip", pe("SELECT src, dst FROM edges"), csv_json)

    def udtf(s, d):
        from pyspark.sql.functions import udtf as make

        @make(returnType="seed bigint, position int, vol double")
        class SweepRows:
            def eval(self, seed: int, vols):
                for i, v in enumerate(vols, 1):
                    yield seed, i, float(v)

        s.udtf.register("sweep_rows", SweepRows)
        c = cat.attributed(s, d).curve.groupBy("seed").agg(F.transform(F.array_sort(F.collect_list(F.struct("position", "vol"))), lambda x: F.round(x["vol"], 6)).alias("vols"))
        c.createOrReplaceTempView("swept")
        return s.sql("SELECT r.seed, r.position, r.vol FROM swept, LATERAL sweep_rows(swept.seed, swept.vols) r")

    add("udtf_sweep_rows", sql.query(*cat._A, select="SELECT seed, CAST(position AS INTEGER) AS position, round(vol, 6) AS vol FROM curve"), udtf)
    from localcomm.streaming import events as st

    for name, oracle, f in st.queries():
        add(name, oracle, f)


def _interval(ev: DataFrame, seconds: int = 60) -> DataFrame:
    """Pairs of users with the same props within a bound: a bucket of the time makes the join an equality."""
    x = ev.select("event_id", "user_id", "props", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    width = seconds * 1_000_000
    a = x.select(F.col("event_id").alias("first_event"), F.col("user_id").alias("ua"), "props", F.col("t").alias("ta"), F.explode(F.array(*[F.floor(F.col("t") / width) + i for i in (-1, 0, 1)])).alias("b"))
    b = x.select(F.col("event_id").alias("second_event"), F.col("user_id").alias("ub"), "props", F.col("t").alias("tb"), F.floor(F.col("t") / width).alias("b"))
    return a.join(b, ["props", "b"]).where((F.col("ua") < F.col("ub")) & (F.abs(F.col("ta") - F.col("tb")) <= width)).select("first_event", "second_event")


def _asof(ev: DataFrame) -> DataFrame:
    """The last purchase at or before each error of the same user, by one window over both kinds."""
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    x = ev.where("event_type IN ('purchase', 'error')").withColumn("last_purchase", F.max(F.when(F.col("event_type") == "purchase", F.col("ts"))).over(w))
    return x.where("event_type = 'error'").select("event_id", "last_purchase")


def _banded(nodes: DataFrame) -> DataFrame:
    """All pairs of sets whose sizes are within four fifths of each other: one side lists the sizes that it can meet."""
    x = nodes.select("node", F.size("attrs").cast("long").alias("size"))
    a = x.select(F.col("node").alias("src"), F.explode(F.sequence(F.expr("(8 * size + 9) DIV 10"), F.expr("10 * size DIV 8"))).alias("size"))
    return a.join(x.select(F.col("node").alias("dst"), "size"), "size").where("src < dst").select("src", "dst")
