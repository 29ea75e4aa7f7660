"""The walk subgraph: random walks with restart, the relevance cut, the induced subgraph, for many seeds at once.

A trial walks until its restart coin falls (or for a fixed number of steps with jumps back to the seed); a vertex
counts once a trial, the seed in each. All draws follow from (seed, walk, hop), so results don't depend on
partitions or retries. Two engines give the same rows: `local` sends the adjacency to all tasks, behind a check
of its size, and moves thousands of walkers at once in numpy; `relational` joins walkers with the adjacency hop by hop.
Beyond `mapped.MAP_FROM` edges the walkers of `auto` read a graph mapped from the shared folder, by the same draws.

Cases: a seed without neighbours visits itself only; repeated seeds are walked once; null seeds are dropped.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcomm.functions.sets import PRIME, draw
from localcomm.operators import mapped
from localcomm.operators.graph import adjacency, chunked, induced
from localcomm.params import Params
from localcomm.plans.stages import staged

#: Edges (both directions) up to which the adjacency is sent to all tasks: 32 bytes each.
SEND_MOST = 4_000_000
WALKS_A_TASK = 10_000


def draw_numpy(keys: list, salt: int) -> np.ndarray:
    """`draw` for arrays."""
    x = np.int64(salt % PRIME)
    for k in keys:
        x = drawn_on(x, k)
    return x


def drawn_on(x: np.ndarray, key) -> np.ndarray:
    """The draw of some keys and one more, from the draw without it."""
    x = _rest(x * np.int64(48271) + np.asarray(key, np.int64) % PRIME)
    for c in (12345, 67891, 424243):
        x = _rest(x * (x + np.int64(65537)) + np.int64(c))
    return x


def _rest(x: np.ndarray) -> np.ndarray:
    """x % PRIME of x >= 0: 2^31 leaves 1, so high bits count like low ones."""
    x = (x & PRIME) + (x >> 31)
    x = (x & PRIME) + (x >> 31)
    return x - PRIME * (x >= PRIME)


class Csr:
    """Sorted vertices, row offsets, neighbours and the running whole-number weights over all rows."""

    def __init__(self, table):
        src, dst, hi = (np.asarray(table[c]) for c in ("src", "dst", "hi"))
        order = np.lexsort((hi, src))
        src, self.dst, hi = src[order], dst[order], hi[order]
        self.nodes, first = np.unique(src, return_index=True)
        self.end = np.append(first[1:], len(src))
        self.total = hi[self.end - 1] if len(src) else hi
        self.base = np.cumsum(self.total) - self.total
        self.run = hi + np.repeat(self.base, self.end - first)

    def moves(self, at: np.ndarray, u: np.ndarray) -> np.ndarray:
        """The next vertex of walkers at `at` by draws u; -1 without neighbours."""
        if not len(self.nodes):
            return np.full(len(at), -1)
        i = np.minimum(np.searchsorted(self.nodes, at), len(self.nodes) - 1)
        ok = self.nodes[i] == at
        pick = np.searchsorted(self.run, self.base[i] + u * self.total[i] // PRIME, side="right")
        return np.where(ok, self.dst[np.minimum(pick, len(self.dst) - 1)], -1)


def walked(csr, seed: int, walks: np.ndarray, p: Params, start: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Vertices visited by the trials of one seed, with the number of trials that visit each.

    `start` is what the graph calls the seed, if it isn't its id; visited vertices go by the graph's names.
    """
    coin, start = int(p.alpha_r * PRIME), seed if start is None else start
    at, who = np.full(len(walks), start, np.int64), walks
    # Draws go by seed, walk and hop: what seed and walk give is the same for all hops.
    drawn = drawn_on(draw_numpy([seed], p.salt), walks)
    seen_walk, seen_node = [walks], [at]
    for hop in range(p.max_hops):
        stop = drawn_on(drawn, 2 * hop) < coin
        if p.walk_mode == "until_restart":
            who, at, drawn = who[~stop], at[~stop], drawn[~stop]
            at = csr.moves(at, drawn_on(drawn, 2 * hop + 1))
            live = at >= 0
            if not live.all():
                who, at, drawn = who[live], at[live], drawn[live]
        else:
            to = csr.moves(at, drawn_on(drawn, 2 * hop + 1))
            at = np.where(stop | (to < 0), start, to)
        if not len(who):
            break
        seen_walk.append(who)
        seen_node.append(at)
    return _counted(np.concatenate(seen_walk), np.concatenate(seen_node))


def _counted(w: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vertices and the number of walks that visit each, of pairs of walk and vertex that may repeat."""
    if not len(n):
        return np.unique(n, return_counts=True)
    low, first = int(n.min()), int(w.min())
    span = int(n.max()) - low + 1
    if (int(w.max()) - first + 1) * span < 1 << 62:  # a pair is one number
        both = np.sort((w - first) * span + (n - low))
        both = both[np.append(True, both[1:] != both[:-1])]
        return np.unique(both % span + low, return_counts=True)
    order = np.lexsort((n, w))
    w, n = w[order], n[order]
    return np.unique(n[np.append(True, (w[1:] != w[:-1]) | (n[1:] != n[:-1]))], return_counts=True)


def walk_visits(combined: DataFrame, seeds: DataFrame, p: Params = Params(), adj: DataFrame | None = None) -> DataFrame:
    """seed, node, hits: trials of n_w that visit the node. `adj`: the graph's `adjacency`, if a caller has it already."""
    if p.engine == "auto" and mapped.wanted(combined.sparkSession, p, combined.count()):
        seeds = seeds.select(F.col("seed").cast("long").alias("seed")).where("seed IS NOT NULL").distinct()
        return mapped.visits(combined, seeds, p, WALKS_A_TASK)
    adj = staged(adjacency(combined, p.weighted), "adjacency") if adj is None else adj
    seeds = seeds.select(F.col("seed").cast("long").alias("seed")).where("seed IS NOT NULL").distinct()
    local = p.engine == "local" or (p.engine == "auto" and adj.limit(SEND_MOST + 1).count() <= SEND_MOST)
    return _local_visits(adj, seeds, p) if local else _relational_visits(adj, seeds, p)


def _local_visits(adj: DataFrame, seeds: DataFrame, p: Params) -> DataFrame:
    sent = adj.sparkSession.sparkContext.broadcast(Csr(adj.select("src", "dst", "hi").toArrow()))  # at most SEND_MOST rows
    tasks = -(-p.n_w // WALKS_A_TASK)
    chunks = seeds.select("seed", F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("chunk"))

    def job(frames):
        for f in frames:
            for seed, chunk in zip(f["seed"].tolist(), f["chunk"].tolist(), strict=True):
                walks = np.arange(chunk * WALKS_A_TASK, min(p.n_w, (chunk + 1) * WALKS_A_TASK), dtype=np.int64)
                node, hits = walked(sent.value, seed, walks, p)
                yield pd.DataFrame({"seed": seed, "node": node, "hits": hits})

    return mapped.spread(chunks, "seed", "chunk").mapInPandas(job, "seed long, node long, hits long").groupBy("seed", "node").agg(F.sum("hits").alias("hits"))


def _relational_visits(adj: DataFrame, seeds: DataFrame, p: Params) -> DataFrame:
    near = staged(chunked(adj), "chunks").withColumnRenamed("src", "node")
    walkers = seeds.select("seed", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(p.n_w - 1).cast("long"))).alias("walk"))
    live = walkers.withColumn("node", F.col("seed"))
    seen, coin = [live], int(p.alpha_r * PRIME)
    for hop in range(p.max_hops):
        stop = draw("seed", "walk", 2 * hop, salt=p.salt) < coin
        pick = draw("seed", "walk", 2 * hop + 1, salt=p.salt)
        asked = live.where(~stop) if p.walk_mode == "until_restart" else live.withColumn("stop", stop)
        asked = asked.withColumn("u", pick)
        # First the chunk of a vertex's neighbours, then the one inside it.
        step = asked.join(near, "node", "inner").withColumn("at", F.expr("u * total div 2147483647")).where("at >= lo AND at < hi")
        step = step.withColumn("to", F.expr("element_at(filter(nbrs, x -> x.hi > at), 1).dst"))
        if p.walk_mode == "until_restart":
            live = step.select("seed", "walk", F.col("to").alias("node"))
        else:
            live = step.select("seed", "walk", F.when(F.col("stop"), F.col("seed")).otherwise(F.col("to")).alias("node"))
        if hop % 8 == 7:
            live = staged(live, "walkers")
            if live.isEmpty():
                break
        seen.append(live)
    out = seen[0]
    for s in seen[1:]:
        out = out.unionByName(s)
    return out.distinct().groupBy("seed", "node").agg(F.count(F.lit(1)).alias("hits"))


def relevant(visits: DataFrame, n: int, p: Params = Params()) -> DataFrame:
    """seed, node, hits of the vertices above the cut; the seed always stays.

    Mean and deviation are over all n vertices; those never visited enter as zeros, without a row.
    """
    if p.rule == "count":
        return visits.where((F.col("hits") >= p.min_hits) | (F.col("node") == F.col("seed")))
    h = F.col("hits").cast("double")
    cut = visits.groupBy("seed").agg((F.sum(h) / n).alias("mu"), (F.sum(h * h) / n).alias("sq"))
    cut = cut.select("seed", (F.col("mu") + F.sqrt(F.greatest(F.col("sq") - F.col("mu") * F.col("mu"), F.lit(0.0))) / p.t_s).alias("cut"))
    return visits.join(cut, "seed").where((F.col("hits") > F.col("cut")) | (F.col("node") == F.col("seed"))).select("seed", "node", "hits")


def relevant_mask(node: np.ndarray, hits: np.ndarray, seed: int, n: int, p: Params) -> np.ndarray:
    """`relevant` for the visits of one seed."""
    if p.rule == "count":
        return (hits >= p.min_hits) | (node == seed)
    h = hits.astype(np.float64)
    mu, sq = h.sum() / n, (h * h).sum() / n
    return (h > mu + np.sqrt(max(sq - mu * mu, 0.0)) / p.t_s) | (node == seed)


@dataclass
class SubgraphSet:
    sub_nodes: DataFrame
    sub_edges: DataFrame
    visits: DataFrame


def proximity_subgraph(combined: DataFrame, seeds: DataFrame, n: int, p: Params = Params()) -> SubgraphSet:
    """The subgraph that walks from each seed find relevant, for a graph of n vertices."""
    visits = staged(walk_visits(combined, seeds, p), "visits")
    nodes = staged(relevant(visits, n, p), "relevant")
    return SubgraphSet(nodes, staged(induced(combined, nodes), "subgraph"), visits)


def visit_histogram(visits: DataFrame) -> DataFrame:
    """seed, hits, vertices: how many vertices were visited so often; never visited ones are left out."""
    return visits.groupBy("seed", "hits").agg(F.count(F.lit(1)).alias("vertices"))
