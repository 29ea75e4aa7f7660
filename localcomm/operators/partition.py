"""Partitions end to end: the attributed one, its ablations, and the structure-only baselines."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcomm.operators import mapped, ranking
from localcomm.operators.graph import adjacency, both_ways, degrees, plain_graph
from localcomm.operators.walks import Csr, proximity_subgraph, relevant_mask, walked
from localcomm.params import Derived, Params, derive_params
from localcomm.plans.stages import staged


@dataclass
class PartitionResult:
    members: DataFrame
    summary: DataFrame
    curve: DataFrame
    sub_nodes: DataFrame | None
    sub_edges: DataFrame | None


#: Trials up to which one task walks them all for a seed.
FUSED_TRIALS = 200_000


def _chosen(curve: DataFrame, seeds: DataFrame, p: Params, sub_nodes: DataFrame | None, sub_edges: DataFrame) -> PartitionResult:
    curve = staged(curve, "curve")
    members, summary = ranking.choose_partition(curve, seeds, p)
    return PartitionResult(members, summary, curve, sub_nodes, sub_edges)


def ranked_and_swept(sub_edges: DataFrame, sub_nodes: DataFrame, deg: DataFrame, seeds: DataFrame, p: Params, d: Derived, total: float) -> PartitionResult:
    """Rank, order, sweep and choose on given subgraphs; one task per seed while the largest is small, joins beyond.

    Both ways stop, truncate and cut alike. `deg` may have a seed column, if degrees differ by seed.
    """
    sub_edges = staged(sub_edges, "ranked-edges")
    local = p.engine == "local"
    if p.engine == "auto":
        largest = sub_edges.groupBy("seed").count().agg(F.max("count")).first()[0] or 0
        local = largest <= ranking.LOCAL_MOST
    if local:
        curve = ranking.curves(sub_edges, deg, [(p, d)], total)
    else:
        curve = ranking.sweep_curve(staged(ranking.rank_order(ranking.seed_rank(sub_edges, seeds, p, d), p.n_s), "order"), sub_edges, deg, p, total)
    return _chosen(curve, seeds, p, sub_nodes, sub_edges)


def scenarios_swept(sub_edges: DataFrame, sub_nodes: DataFrame, deg: DataFrame, seeds: DataFrame, scenarios: ranking.Scenarios, total: float) -> PartitionResult:
    """The same for a grid of parameters in one job: seeds go by `ranking.scenario_seeds`; `target_met` is that of the first."""
    sub_edges = staged(sub_edges, "ranked-edges")
    return _chosen(ranking.curves(sub_edges, deg, scenarios, total), seeds, scenarios[0][0], sub_nodes, sub_edges)


def scenarios_mapped(combined: DataFrame, seeds: DataFrame, n: int, scenarios: ranking.Scenarios, total: float) -> PartitionResult:
    """The same with the walks, on a graph that is mapped (checked by the caller)."""
    return _chosen(mapped.fused_curves(combined, seeds, n, scenarios, total), seeds, scenarios[0][0], None, None)


def whole_swept(edges: DataFrame, deg: DataFrame, seeds: DataFrame, scenarios: ranking.Scenarios, total: float, m: int) -> PartitionResult:
    """Rank, order, sweep and choose on one whole graph of m edges for all seeds; the graph is never copied for each.

    Up to `mapped.MAP_FROM` edges it is sent to all tasks; beyond, they map it from the shared folder. Without a local path
    to that folder it is sent up to `ranking.SEND_MOST` edges, and beyond ranks are joined with one table of transitions.
    """
    p, d = scenarios[0]
    if mapped.wanted(edges.sparkSession, p, m):
        return _chosen(mapped.whole_curves(edges, seeds, scenarios, total), seeds, p, None, edges.select("src", "dst", "w"))
    edges = edges.select("src", "dst", "w")
    if p.engine == "local" or (p.engine == "auto" and m <= ranking.SEND_MOST):
        return _chosen(ranking.whole_curves(edges, deg, seeds, scenarios, total), seeds, p, None, edges)
    found = None
    for i, (q, e) in enumerate(scenarios):
        mine = seeds.where(F.expr(f"seed DIV {ranking.SCENARIO}") == i).select(F.pmod("seed", F.lit(ranking.SCENARIO)).alias("seed"))
        order = staged(ranking.rank_order(ranking.seed_rank(edges, mine, q, e), q.n_s), "order")
        one = ranking.sweep_curve(order, edges, deg, q, total).withColumn("seed", F.col("seed") + F.lit(i * ranking.SCENARIO))
        found = one if found is None else found.unionByName(one)
    return _chosen(found, seeds, p, None, edges)


def fused_curves(combined: DataFrame, deg: DataFrame, seeds: DataFrame, n: int, p: Params, d: Derived, total: float) -> DataFrame:
    """CURVE rows of every seed: walks, relevance, subgraph, rank and sweep in one task, on a graph sent to all tasks (checked by the caller)."""
    adj = adjacency(combined, p.weighted).select("src", "dst", "hi")
    ends = both_ways(combined.select("src", "dst", "w")).join(deg.select(F.col("node").alias("src"), "deg"), "src")
    table = ends.join(adj, ["src", "dst"]).select("src", "dst", "w", "deg", "hi").toArrow()
    sent = combined.sparkSession.sparkContext.broadcast(SentGraph(table))

    def job(frames):
        for f in frames:
            for seed in f["seed"].tolist():
                yield sent.value.partition(seed, n, p, d, total)

    return mapped.spread(seeds.select(F.col("seed").cast("long").alias("seed")).where("seed IS NOT NULL").distinct()).mapInPandas(job, ranking.CURVE).replace(float("nan"), None)


class SentGraph:
    """A whole graph in one task: rows for walkers, weights and degrees for the subgraph."""

    def __init__(self, table):
        self.csr = Csr(table)
        order = np.lexsort((np.asarray(table["hi"]), np.asarray(table["src"])))
        self.w, self.deg = (np.asarray(table[c])[order] for c in ("w", "deg"))
        self.first = np.append(0, self.csr.end[:-1]) if len(self.csr.end) else self.csr.end

    def partition(self, seed: int, n: int, p: Params, d: Derived, total: float):
        node, hits = walked(self.csr, seed, np.arange(p.n_w, dtype=np.int64), p)
        node = node[relevant_mask(node, hits, seed, n, p)]
        at = np.searchsorted(self.csr.nodes, node)
        at, node = (x[(at < len(self.csr.nodes)) & (self.csr.nodes[np.minimum(at, len(self.csr.nodes) - 1)] == node)] for x in (at, node)) if len(self.csr.nodes) else (at[:0], node[:0])
        size = self.csr.end[at] - self.first[at]
        rows = np.repeat(self.first[at] - (np.cumsum(size) - size), size) + np.arange(size.sum())
        src, dst = np.repeat(node, size), self.csr.dst[rows]
        both = np.isin(dst, node)
        rows = rows[both]
        return ranking.Compact(src[both], dst[both], self.w[rows], self.deg[rows]).curve(seed, seed, p, d, total)


def attributed_partition(combined: DataFrame, seeds: DataFrame, n: int, p: Params = Params(), use_proximity: bool = True) -> PartitionResult:
    """The partition around each seed of a combined graph of n vertices.

    Without the walk subgraph the whole graph is ranked (`sub_nodes` is None then). Isolated seeds are alone.
    On a graph that can be sent to all tasks a seed walks, ranks and sweeps in one task, which keeps its subgraph to itself:
    `sub_nodes` and `sub_edges` are None; `proximity_subgraph` gives them.
    """
    m, total = combined.agg(F.count(F.lit(1)), 2 * F.coalesce(F.sum("w"), F.lit(0.0))).first()
    d, deg = derive_params(m, p), degrees(combined, "w")
    if use_proximity and mapped.wanted(combined.sparkSession, p, m) and p.n_w <= FUSED_TRIALS:
        return _chosen(mapped.fused_curves(combined, seeds, n, [(p, d)], total), seeds, p, None, None)
    if use_proximity and p.engine == "auto" and m <= ranking.SEND_MOST and p.n_w <= FUSED_TRIALS:
        return _chosen(fused_curves(combined, deg, seeds, n, p, d, total), seeds, p, None, None)
    if use_proximity:
        sub = proximity_subgraph(combined, seeds, n, p)
        return ranked_and_swept(sub.sub_edges.select("seed", "src", "dst", "w"), sub.sub_nodes, deg, seeds, p, d, total)
    return whole_swept(combined, deg, seeds, [(p, d)], total, m)


def structural_partition(edges: DataFrame, seeds: DataFrame, n: int, p: Params = Params()) -> PartitionResult:
    """The structure-only baseline: all weights 1, no walk subgraph, classic sweep; `select` as in Params."""
    return attributed_partition(plain_of(edges), seeds, n, p.but(measure="classic"), use_proximity=False)


def plain_of(edges: DataFrame) -> DataFrame:
    """`plain_graph`, one for each table of edges, so that a mapped one is written once."""
    if "_plain" not in edges.__dict__:
        edges.__dict__["_plain"] = plain_graph(edges)
    return edges.__dict__["_plain"]


def truncated_walk_partition(edges: DataFrame, seeds: DataFrame, n: int, p: Params = Params(), t_cap: int | None = None) -> PartitionResult:
    """The older baseline: lazy walk without restart, truncated in every step, classic sweep.

    It takes all t_last steps of the bound unless `t_cap` is given; without a restart nothing contracts earlier.
    """
    m = edges.count()
    d = derive_params(m, p)
    d = Derived(d.l, d.t_last, d.b, d.eps, d.t_last if t_cap is None else min(d.t_last, t_cap))
    g = plain_of(edges)
    return whole_swept(g, degrees(g, "w"), seeds, [(p.but(alpha_n=0.0, measure="classic", stop="fixed", truncate="feedback"), d)], 2.0 * m, m)


def attributed_rank(combined: DataFrame, seeds: DataFrame, p: Params = Params(), top: int = 20) -> DataFrame:
    """seed, position, node, rank, share: the top vertices by rank on the attributed graph, without any sweep."""
    m = combined.count()
    d = derive_params(m, p)
    if mapped.wanted(combined.sparkSession, p, m):
        return mapped.whole_curves(combined, seeds, [(p.but(n_s=top), d)], 1.0).select("seed", "position", "node", "rank", "share")
    if p.engine == "local" or (p.engine == "auto" and m <= ranking.SEND_MOST):
        c = ranking.whole_curves(combined, degrees(combined, "w"), seeds, [(p.but(n_s=top), d)], 1.0)
        return c.select("seed", "position", "node", "rank", "share")
    return ranking.rank_order(ranking.seed_rank(combined.select("src", "dst", "w"), seeds, p, d), top)
