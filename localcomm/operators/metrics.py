"""Measures of partitions: density, triangles, differences, conductances, costs."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcomm.operators.graph import both_ways, induced


def partition_quality(members: DataFrame, edges: DataFrame) -> DataFrame:
    """seed, nodes, edges, density, triangles_x3, triangles; density is null below two nodes.

    A triangle of ordered ends a < b < c is met once, as two edges from its smallest end closed by the third.
    """
    from localcomm.plans.stages import staged

    # Members are few and known as such once staged; then the graph is read once, and its inner edges several times.
    members = staged(members.select("seed", "node"), "quality-members")
    inner = staged(induced(edges.select("src", "dst"), members).select("seed", "src", "dst"), "inner-edges")
    size = members.groupBy("seed").agg(F.count(F.lit(1)).alias("nodes"))
    m = inner.groupBy("seed").agg(F.count(F.lit(1)).alias("edges"))
    wedge = inner.select("seed", "src", F.col("dst").alias("b")).join(inner.select("seed", "src", F.col("dst").alias("c")), ["seed", "src"]).where("b < c")
    closed = wedge.join(inner.select("seed", F.col("src").alias("b"), F.col("dst").alias("c")), ["seed", "b", "c"]).groupBy("seed").agg(F.count(F.lit(1)).alias("triangles"))
    out = size.join(m, "seed", "left").join(closed, "seed", "left").na.fill(0, ["edges", "triangles"])
    n = F.col("nodes")
    return out.select("seed", "nodes", "edges", F.when(n > 1, 2 * F.col("edges") / (n * (n - 1))).alias("density"), (3 * F.col("triangles")).alias("triangles_x3"), "triangles")


def set_difference_size(a: DataFrame, b: DataFrame) -> DataFrame:
    """seed, symmetric, only_a, only_b of two member sets."""
    both = a.select("seed", "node", F.lit(1).alias("in_a")).join(b.select("seed", "node", F.lit(1).alias("in_b")), ["seed", "node"], "full_outer")
    only_a, only_b = F.sum(F.col("in_b").isNull().cast("long")), F.sum(F.col("in_a").isNull().cast("long"))
    return both.groupBy("seed").agg((only_a + only_b).alias("symmetric"), only_a.alias("only_a"), only_b.alias("only_b"))


def topk_difference(a: DataFrame, b: DataFrame, k: int = 20) -> DataFrame:
    """seed, difference: how many of the first k vertices of one order the other's first k lack; columns seed, position, node."""
    x, y = (d.where(F.col("position") <= k).select("seed", "node") for d in (a, b))
    return x.join(y.withColumn("hit", F.lit(1)), ["seed", "node"], "left").groupBy("seed").agg((F.count(F.lit(1)) - F.count("hit")).alias("difference"))


def forecast_gain(original: DataFrame, removed: DataFrame, forecast: DataFrame, edges_original: DataFrame, edges_removed: DataFrame, edges_forecast: DataFrame) -> DataFrame:
    """seed, gain_v, gain_e: by how much the forecast comes nearer the original partition than the one without it.

    Edge tables have seed, src, dst inside the partitions.
    """
    v1, v2 = set_difference_size(original, removed), set_difference_size(original, forecast)
    edge = lambda e: e.select("seed", F.struct("src", "dst").alias("node"))
    e1, e2 = set_difference_size(edge(edges_original), edge(edges_removed)), set_difference_size(edge(edges_original), edge(edges_forecast))
    pick = lambda d, n: d.select("seed", F.col("symmetric").alias(n))
    out = pick(v1, "dv_removed").join(pick(v2, "dv_forecast"), "seed").join(pick(e1, "de_removed"), "seed", "left").join(pick(e2, "de_forecast"), "seed", "left").na.fill(0)
    return out.select("seed", "dv_removed", "dv_forecast", (F.col("dv_removed") - F.col("dv_forecast")).alias("gain_v"), (F.col("de_removed") - F.col("de_forecast")).alias("gain_e"))


def conductance_parts(members: DataFrame, weighted: DataFrame) -> DataFrame:
    """seed, node, deg, inside: each member's weight in all and within its set; edges have w."""
    e = both_ways(weighted.select("src", "dst", "w"))
    own = e.join(members.select("seed", F.col("node").alias("src")), "src")
    tagged = own.join(members.select("seed", F.col("node").alias("dst"), F.lit(1).alias("hit")), ["seed", "dst"], "left")
    deg = tagged.groupBy("seed", F.col("src").alias("node")).agg(F.sum("w").alias("deg"), F.sum(F.when(F.col("hit") == 1, F.col("w")).otherwise(0.0)).alias("inside"))
    return members.select("seed", "node").join(deg, ["seed", "node"], "left").na.fill(0.0, ["deg", "inside"])


def classic_conductance(members: DataFrame, weighted: DataFrame) -> DataFrame:
    """seed, cut, vol, score: weight that leaves over the smaller volume."""
    total = 2 * (weighted.agg(F.sum("w")).first()[0] or 0.0)
    c = conductance_parts(members, weighted).groupBy("seed").agg(F.sum(F.col("deg") - F.col("inside")).alias("cut"), F.sum("deg").alias("vol"))
    least = F.least(F.col("vol"), F.lit(total) - F.col("vol"))
    return c.select("seed", "cut", "vol", F.when(least > 1e-12, F.col("cut") / least).alias("score"))


def vertex_ratio(members: DataFrame, combined: DataFrame) -> DataFrame:
    """seed, node, ratio, side: leaving over staying weight of each member; below 1 it is tied more to its set."""
    r = F.when(F.col("inside") > 0, (F.col("deg") - F.col("inside")) / F.col("inside"))
    side = F.when(r.isNull(), "orphan").when(r < 1, "inside").when(r > 1, "outside").otherwise("equal")
    return conductance_parts(members, combined).select("seed", "node", r.alias("ratio"), side.alias("side"))


def ratio_conductance(members: DataFrame, combined: DataFrame) -> DataFrame:
    """seed, cut, vol, score of the ratio measure; null if a member has nothing inside."""
    parts = conductance_parts(members, combined)
    whole = F.sum((F.col("inside") <= 0).cast("long")) == 0
    cut = F.when(whole, F.sum(F.when(F.col("inside") > 0, (F.col("deg") - F.col("inside")) / F.col("inside"))))
    c = parts.groupBy("seed").agg(cut.alias("cut"), F.sum("deg").alias("vol"))
    return c.select("seed", "cut", "vol", F.when(F.col("vol") > 0, F.col("cut") / F.col("vol")).alias("score"))


def ratio_components(members: DataFrame, combined: DataFrame) -> DataFrame:
    """seed, node, ext_g, ext_a, int_g, int_a: the ratio's weights split into structure and similarity."""
    g = conductance_parts(members, combined.select("src", "dst", F.col("w_g").alias("w"))).select("seed", "node", (F.col("deg") - F.col("inside")).alias("ext_g"), F.col("inside").alias("int_g"))
    a = conductance_parts(members, combined.select("src", "dst", F.col("w_a").alias("w"))).select("seed", "node", (F.col("deg") - F.col("inside")).alias("ext_a"), F.col("inside").alias("int_a"))
    return g.join(a, ["seed", "node"]).select("seed", "node", "ext_g", "ext_a", "int_g", "int_a")


def subgraph_size(sub_nodes: DataFrame, sub_edges: DataFrame, n: int) -> DataFrame:
    """seed, p, m_p, share: vertices and edges of the subgraph, and its share of the graph."""
    p = sub_nodes.groupBy("seed").agg(F.count(F.lit(1)).alias("p"))
    m = sub_edges.groupBy("seed").agg(F.count(F.lit(1)).alias("m_p"))
    return p.join(m, "seed", "left").na.fill(0, ["m_p"]).withColumn("share", F.col("p") / n)


def compare(ours: DataFrame, theirs: DataFrame) -> DataFrame:
    """Mean density, nodes and triangles of two methods and the ratio of their densities: one row."""
    a = ours.agg(F.avg("density").alias("density_a"), F.avg("nodes").alias("nodes_a"), F.avg("triangles_x3").alias("triangles_a"), F.lit(1).alias("one"))
    b = theirs.agg(F.avg("density").alias("density_b"), F.avg("nodes").alias("nodes_b"), F.avg("triangles_x3").alias("triangles_b"), F.lit(1).alias("one"))
    return a.join(b, "one").drop("one").withColumn("density_ratio", F.col("density_a") / F.col("density_b"))


def cost_model(n, m, p, m_p, m_e, n_w) -> dict:
    """Operation counts of the three methods as their complexities state them, of the sweep done here, and cells of the graph's forms; of numbers or columns."""
    return {"subgraph": n + m_p + n_w, "partition": p * p + p * m_p + n + n_w, "forecast": p * p + p * m_e + n + n_w, "event_sweep": m_p + p, "csr_cells": space_cells(n, m)["csr"], "adjacency_cells": space_cells(n, m)["adjacency"]}


def space_cells(n, m) -> dict:
    return {"csr": 2 * m + n + 1, "adjacency": n + m}


def timed(run: Callable[[], DataFrame]) -> float:
    """Seconds to plan and make all rows of a DataFrame, written nowhere."""
    began = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began
