"""Edge completion by attribute similarity, and the forecast of a community's growth.

Pairs are found per seed inside its subgraph, or on the whole graph: by comparing all pairs, by an exact prefix join
(rarest members first, several to a key, by sizes, full check), or by min-hash bands with a full check, which miss some pairs.
"""

from __future__ import annotations

import itertools
import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from localcomm.functions.sets import canonical, jaccard
from localcomm.operators.graph import both_ways, degrees
from localcomm.operators.partition import PartitionResult, ranked_and_swept
from localcomm.operators.walks import SubgraphSet, proximity_subgraph
from localcomm.params import Params, derive_params
from localcomm.plans.stages import staged


def similar_pairs(nodes: DataFrame, t_e: float, strategy: str = "prefix", key: tuple[str, ...] = ()) -> DataFrame:
    """src < dst with sim > t_e, within equal key columns; nodes have node and attrs.

    `prefix` and `minhash` compare distinct sets; the nodes that hold a set come in behind, and pairs of equal sets have similarity 1.
    """
    n = nodes.select(*key, "node", canonical(F.col("attrs")).alias("x")).where(F.size("x") > 0)
    if strategy == "pairs":
        a = n.select(*key, F.col("node").alias("src"), F.col("x").alias("xa"))
        b = n.select(*key, F.col("node").alias("dst"), F.col("x").alias("xb"))
        met = a.join(b, list(key)) if key else a.crossJoin(b)
        return met.where("src < dst").withColumn("sim", jaccard(F.col("xa"), F.col("xb"))).where(F.col("sim") > t_e).select(*key, "src", "dst", "sim")
    if strategy not in ("prefix", "minhash"):
        raise ValueError(strategy)
    # A set goes by the smallest node that holds it, within its key.
    held = staged(n.withColumn("set", F.min("node").over(Window.partitionBy(*key, "x"))), "sets")
    sets = staged(held.where("node = set").select(*key, "node", "x").distinct(), "distinct-sets")
    near = _prefix_pairs(sets, t_e, key) if strategy == "prefix" else _minhash_pairs(sets, t_e, key)
    a, b = (sets.select(*key, F.col("node").alias(end), F.col("x").alias(x)) for end, x in (("src", "xa"), ("dst", "xb")))
    sim = near.join(a, [*key, "src"]).join(b, [*key, "dst"]).withColumn("sim", jaccard(F.col("xa"), F.col("xb"))).where(F.col("sim") > t_e).select(*key, "src", "dst", "sim")
    own = held.select(*key, "node", "set").distinct()
    ends = lambda of, end: own.select(*key, F.col("set").alias(of), F.col("node").alias(end))
    apart = sim.withColumnsRenamed({"src": "sa", "dst": "sb"}).join(ends("sa", "i"), [*key, "sa"]).join(ends("sb", "j"), [*key, "sb"])
    found = apart.select(*key, F.least("i", "j").alias("src"), F.greatest("i", "j").alias("dst"), "sim").where("src < dst")
    if t_e >= 1:
        return found
    same = ends("set", "src").join(ends("set", "dst"), [*key, "set"]).where("src < dst").select(*key, "src", "dst", F.lit(1.0).alias("sim"))
    return found.unionByName(same)


#: Keys that a set may give for one size of partner; the number of members in a key follows from it.
KEYS = 32


def prefix_keys(x: list[int], other: int, t_e: float) -> tuple[int, list[tuple[int, ...]]]:
    """What a set of member ranks (ascending, rarest first) is found by from sets of another size: members of a key, and the keys.

    Sets of sizes a and b with similarity t or more share at least o = t / (1 + t) * (a + b) members, so their prefixes of
    a - o + l and b - o + l members share l of them: a key is any l members of the prefix. Both ends take the same l.
    """
    size = len(x)
    need = max(1, math.ceil(t_e / (1 + t_e) * (size + other) - 1e-9))
    large = max(size, other)
    take = 1
    while take < need and math.comb(large - need + take + 1, take + 1) <= KEYS:
        take += 1
    return take, list(itertools.combinations(x[: size - need + take], take))


def _prefix_pairs(n: DataFrame, t_e: float, key: tuple[str, ...]) -> DataFrame:
    """Candidates: pairs of distinct sets that share a key of their rarest members; exact for sim >= t_e."""
    members = n.select(*key, "node", F.size("x").alias("size"), F.explode("x").alias("member")).withColumn("member", F.coalesce("member", F.lit("\0")))
    df = members.groupBy(*key, "member").agg(F.count(F.lit(1)).alias("df"))
    ranked = members.join(df, [*key, "member"]).groupBy(*key, "node", "size").agg(F.array_sort(F.collect_list(F.struct("df", "member"))).alias("m"))
    ranked = ranked.select(*key, "node", "size", F.transform("m", lambda t: F.xxhash64(t["member"])).alias("m"))
    # Sizes that a set meets: those that occur in its key and lie in the band.
    sizes = ranked.select(*key, F.col("size").alias("other")).distinct()
    band = (F.col("other") >= t_e * F.col("size") - 1e-9) & (F.col("size") >= t_e * F.col("other") - 1e-9)
    asked = (ranked.join(sizes, list(key)) if key else ranked.crossJoin(F.broadcast(sizes))).where(band)  # one row for each size
    names = list(key)
    kinds = ", ".join(f"{c} {n.schema[c].dataType.simpleString()}" for c in names)
    schema = f"{kinds + ', ' if names else ''}node long, size int, other int, member long"

    def job(frames):
        for f in frames:
            row, member = [], []
            for i, (m, other) in enumerate(zip(f["m"].tolist(), f["other"].tolist(), strict=True)):
                _, keys = prefix_keys([int(v) for v in m], other, t_e)
                row += [i] * len(keys)
                member += [hash(k) for k in keys]  # of whole numbers: the same in every process
            out = f[[*names, "node", "size", "other"]].iloc[row].reset_index(drop=True)
            yield out.assign(member=np.array(member, np.int64))

    kept = asked.select(*names, "node", "size", "other", "m").mapInPandas(job, schema)
    a = kept.where("size <= other").select(*names, "member", F.col("node").alias("i"), "size", "other")
    b = kept.where("size >= other").select(*names, "member", F.col("node").alias("j"), F.col("other").alias("size"), F.col("size").alias("other"))
    met = a.join(b, [*names, "member", "size", "other"]).where("i < j OR (i > j AND size < other)")
    return met.select(*names, F.least("i", "j").alias("src"), F.greatest("i", "j").alias("dst")).distinct()


#: Of the pairs at the threshold, those that min-hash bands may miss.
MISS = 1e-3


def bands(t_e: float) -> tuple[int, int]:
    """(rows, bands): the most rows a band for which 64 bands miss at most MISS of the pairs of similarity t_e."""
    most = lambda r: math.ceil(math.log(MISS) / math.log1p(-(t_e**r)))
    rows = max([r for r in range(1, 7) if 0 < t_e < 1 and most(r) <= 64], default=1)
    return rows, min(64, most(rows)) if 0 < t_e < 1 else 64


def _minhash_pairs(n: DataFrame, t_e: float, key: tuple[str, ...]) -> DataFrame:
    """Candidates: pairs of distinct sets that agree in all min-hashes of a band."""
    rows, count = bands(t_e)
    v = n.select(*key, "node", F.transform("x", lambda t: F.xxhash64(t)).alias("m"))

    def job(frames):
        for f in frames:
            size = f["m"].map(len).to_numpy()
            first, members = np.cumsum(size) - size, np.concatenate(f["m"].tolist()).astype(np.int64).view(np.uint64)
            found = np.zeros((len(f), count), np.uint64)
            for i in range(rows * count):
                low = np.minimum.reduceat(_mixed(members, 2 * i + 1), first)
                found[:, i // rows] = _mixed(found[:, i // rows] ^ low, 2 * (i // rows))
            yield f[[*key, "node"]].assign(band=list(found.view(np.int64)))

    kinds = "".join(f"{c} {n.schema[c].dataType.simpleString()}, " for c in key)
    kept = v.mapInPandas(job, f"{kinds}node long, band array<long>").select(*key, "node", F.explode(F.array_distinct("band")).alias("band"))
    a, b = (kept.select(*key, "band", F.col("node").alias(end)) for end in ("src", "dst"))
    return a.join(b, [*key, "band"]).where("src < dst").select(*key, "src", "dst").distinct()


def _mixed(x: np.ndarray, salt: int) -> np.ndarray:
    """64-bit hashes spread anew for each salt."""
    with np.errstate(over="ignore"):
        x = x + np.uint64((salt + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def complete_edges(sub: SubgraphSet, nodes: DataFrame, t_e: float = 0.7, strategy: str = "pairs") -> DataFrame:
    """seed, src, dst, w, is_predicted: the subgraph's edges, and its non-adjacent pairs more similar than t_e with their similarity as weight."""
    sets = sub.sub_nodes.select("seed", "node").join(nodes.select("node", "attrs"), "node")
    own = sub.sub_edges.select("seed", "src", "dst", "w")
    new = similar_pairs(sets, t_e, strategy, ("seed",)).join(own, ["seed", "src", "dst"], "left_anti")
    return own.withColumn("is_predicted", F.lit(False)).unionByName(new.select("seed", "src", "dst", F.col("sim").alias("w"), F.lit(True).alias("is_predicted")))


def forecast_community(combined: DataFrame, nodes: DataFrame, seeds: DataFrame, n: int, p: Params, strategy: str = "pairs", rewalk: bool = False) -> PartitionResult:
    """The partition that the completed subgraph gives; `sub_edges` of the result tells predicted edges apart.

    With `rewalk` a second subgraph is drawn inside the completed first one before ranking.
    """
    m, total = combined.agg(F.count(F.lit(1)), 2 * F.coalesce(F.sum("w"), F.lit(0.0))).first()
    d = derive_params(m, p)
    sub = proximity_subgraph(combined, seeds, n, p)
    done = staged(complete_edges(sub, nodes, p.t_e if p.t_e is not None else 0.7, strategy), "completed")
    if rewalk:
        done = rewalked(done, seeds, n, p)
    return ranked_and_swept(done, sub.sub_nodes, grown_degrees(done, combined), seeds, p, d, total)


def rewalked(done: DataFrame, seeds: DataFrame, n: int, p: Params) -> DataFrame:
    """The completed subgraphs cut by walks once more, inside each.

    All seeds walk in one job: a vertex goes by the place of its seed among them and its own id, so subgraphs don't touch.
    """
    from localcomm.operators.walks import relevant, walk_visits

    place = staged(seeds.select("seed").distinct().withColumn("k", F.row_number().over(Window.orderBy("seed")).cast("long")), "places")  # the caller's seeds, one row each
    span = 1 << 40
    mine = done.join(F.broadcast(place), "seed") if place.count() <= 100_000 else done.join(place, "seed")
    apart = mine.select((F.col("k") * span + F.col("src")).alias("src"), (F.col("k") * span + F.col("dst")).alias("dst"), "w")
    visits = walk_visits(apart, place.select((F.col("k") * span + F.col("seed")).alias("seed")), p)
    kept = relevant(visits, n, p).select(F.expr(f"seed % {span}").alias("seed"), F.expr(f"node % {span}").alias("node"))
    kept = staged(kept, "rewalked")
    inside = done.join(kept.select("seed", F.col("node").alias("src")), ["seed", "src"], "left_semi").join(kept.select("seed", F.col("node").alias("dst")), ["seed", "dst"], "left_semi")
    return staged(inside.select("seed", "src", "dst", "w", "is_predicted"), "completed")


def grown_degrees(done: DataFrame, combined: DataFrame) -> DataFrame:
    """seed, node, deg: degrees in the whole graph and the weight that a seed's predicted edges add, which differs by seed."""
    ends = both_ways(done.select("src", "dst", "seed", F.when(F.col("is_predicted"), F.col("w")).otherwise(0.0).alias("w")))
    more = ends.groupBy("seed", F.col("src").alias("node")).agg(F.sum("w").alias("more"))
    return more.join(degrees(combined, "w"), "node", "left").select("seed", "node", (F.coalesce("deg", F.lit(0.0)) + F.col("more")).alias("deg"))


def predicted_links(result: PartitionResult, top: int = 20) -> DataFrame:
    """seed, src, dst, w: the most similar predicted links of each seed."""
    w = Window.partitionBy("seed").orderBy(F.desc("w"), "src", "dst")
    return result.sub_edges.where("is_predicted").withColumn("place", F.row_number().over(w)).where(F.col("place") <= top).select("seed", "src", "dst", "w", "place")


def ego_network(edges: DataFrame, seeds: DataFrame, hops: int = 1) -> DataFrame:
    """seed, node, hop: vertices within some hops, with the smallest number of hops."""
    e = both_ways(edges.select("src", "dst"))
    out = seeds.select("seed", F.col("seed").alias("node"), F.lit(0).alias("hop"))
    edge = out
    for h in range(1, hops + 1):
        edge = edge.join(e.withColumnRenamed("src", "node"), "node").select("seed", F.col("dst").alias("node"), F.lit(h).alias("hop")).distinct()
        out = out.unionByName(edge)
    return out.groupBy("seed", "node").agg(F.min("hop").alias("hop"))


def cold_start_nodes(edges: DataFrame, most: int = 2) -> DataFrame:
    """seed, deg: vertices with at least one and at most `most` neighbours."""
    return degrees(edges).where(F.col("deg") <= most).select(F.col("node").alias("seed"), "deg")
