"""Lazy personalised rank, its ordering, and the sweep, as joins and windows or per seed in one task.

The rank of a step is (1 - alpha) times half its own value and half what neighbours send by weight, plus alpha on the seed.
Truncation drops rank below eps times the degree, inside the loop (`feedback`) or from the result (`output`).
Ties in the order go to the smaller node. The sweep gives every prefix of the order its cut, volume and score:

- ratio: the sum over members of weight that leaves over weight that stays, over the volume; a prefix with a member
  that has nothing inside has no score. Prefixes from half the graph's volume on have none either.
- classic: leaving weight over the smaller of the volumes inside and outside.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from localcomm.operators.graph import both_ways
from localcomm.params import Derived, Params
from localcomm.plans.stages import staged

CURVE = "seed long, position int, node long, rank double, share double, cut double, vol double, orphans int, score double"
#: Edges of one seed up to which a task ranks and sweeps it by itself.
LOCAL_MOST = 500_000
#: Edges of a whole graph up to which it is sent to all tasks: both ways, some 40 bytes each.
SEND_MOST = 1_000_000
DIGITS = 12


def ranked(arriving, deg: np.ndarray, seed: int, p: Params, d: Derived) -> tuple[np.ndarray, int]:
    """Rank of all vertices and the steps it took; `arriving` gives what each vertex gets from its neighbours' ranks.

    A step follows from the ranks before it alone. So where ranks come back to those of an earlier step, all later ones
    repeat, and of the steps that are left only those beyond whole rounds are taken.

    Without a restart a step takes means of shares (rank over degree), so once the walk has filled its component and nothing
    is truncated, no later share leaves the span of the shares there are. When that span is one value to DIGITS, all later
    orders are this one, and the rank is what the walk tends to: the mass by degree.
    """
    q = np.zeros(len(deg))
    if p.stop != "mass":
        q[seed] = 1.0
    steps, mark, marked = 0, q, 0
    while steps < d.steps:
        steps += 1
        new = (1 - p.alpha_n) * 0.5 * (q + arriving(q))
        new[seed] += p.alpha_n
        if p.stop == "fixed" and not p.alpha_n and steps % SETTLED_EVERY == 0 and (even := settled(q, new, deg, d)) is not None:
            q, steps = even, d.steps
            break
        if p.truncate == "feedback":
            new[new <= d.eps * deg] = 0.0
        if np.array_equal(new, q):  # a fixed point: all further steps give the same
            break
        change = abs(new.sum() - q.sum()) if p.stop == "mass" else np.abs(new - q).sum()
        q = new
        if p.stop != "fixed" and change < p.eps_t:
            break
        if p.stop == "fixed" and np.array_equal(q, mark):
            steps += (d.steps - steps) // (steps - marked) * (steps - marked)
        if steps >= 2 * marked:
            mark, marked = q, steps
    if p.truncate == "output":
        q = np.where(q > d.eps * deg, q, 0.0)
    return q, steps


#: Steps after which a walk without a restart is looked at anew.
SETTLED_EVERY = 16


def settled(q: np.ndarray, new: np.ndarray, deg: np.ndarray, d: Derived) -> np.ndarray | None:
    """The rank a walk without a restart tends to, if all shares to come are alike to DIGITS; `new` follows q, not truncated yet."""
    on = q > 0
    if not np.array_equal(on, new > 0):
        return None
    share = new[on] / deg[on]
    low, high = share.min(), share.max()
    if low <= d.eps or np.round(low, DIGITS) != np.round(high, DIGITS):
        return None
    return np.where(on, deg * (new.sum() / deg[on].sum()), 0.0)


def rank_vector(src, dst, w, n: int, seed: int, p: Params, d: Derived) -> tuple[np.ndarray, np.ndarray, int]:
    """Rank and degree of n vertices; edges come both ways by position."""
    deg = np.bincount(src, weights=w, minlength=n)
    share = w / deg[src]
    q, steps = ranked(lambda q: np.bincount(dst, weights=q[src] * share, minlength=n), deg, seed, p, d)
    return q, deg, steps


def no_curve() -> pd.DataFrame:
    return pd.DataFrame(columns=[c.split()[0] for c in CURVE.split(", ")])


class Compact:
    """A graph's edges both ways by position of their ends, with the full degrees of the vertices."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, w: np.ndarray, deg: np.ndarray):
        self.nodes, self.src = np.unique(src, return_inverse=True)
        self.dst, self.w = np.searchsorted(self.nodes, dst), w
        self.full = np.zeros(len(self.nodes))
        self.full[self.src] = deg

    def curve(self, key: int, seed: int, p: Params, d: Derived, total: float) -> pd.DataFrame:
        """Order and sweep of one seed; `key` is what the rows call it."""
        nodes, src, dst, w, full = self.nodes, self.src, self.dst, self.w, self.full
        at = int(np.searchsorted(nodes, seed))
        if at >= len(nodes) or nodes[at] != seed:
            return no_curve()
        q, deg, _ = rank_vector(src, dst, w, len(nodes), at, p, d)
        if p.cut_scope == "subgraph":
            full, total = deg, deg.sum()
        share = np.round(q / deg, DIGITS)
        order = np.lexsort((nodes, -share))
        order = order[q[order] > 0][: p.n_s]
        return swept(key, nodes, q, share, full, order, src, dst, w, p, total)


def swept(key: int, nodes, q, share, full, order, src, dst, w, p: Params, total: float) -> pd.DataFrame:
    """CURVE rows of an order of positions; ranks and full degrees by position, edges both ways."""
    place = np.full(len(nodes), len(nodes) + 1)
    place[order] = np.arange(len(order))
    # An edge counts inside for both its ends from the step at which the later end enters.
    use = (place[src] < len(order)) & (place[dst] < len(order))
    step = np.maximum(place[src[use]], place[dst[use]])
    by = np.argsort(step, kind="stable")
    s_src, s_w, s_step = src[use][by], w[use][by], step[by]
    bounds = np.searchsorted(s_step, np.arange(len(order) + 1))
    inside, ratio = np.zeros(len(nodes)), np.zeros(len(nodes))
    cut, vol, orphans, score, weight_in = [], [], [], [], 0.0
    v = r = 0.0
    none = 0
    for j, node in enumerate(order):
        none += 1
        v += full[node]
        lo, hi = bounds[j], bounds[j + 1]
        touched = np.unique(s_src[lo:hi])
        was = inside[touched] > 0
        np.add.at(inside, s_src[lo:hi], s_w[lo:hi])
        now = full[touched] / inside[touched] - 1
        r += float((now - ratio[touched]).sum())
        ratio[touched] = now
        none -= int((~was).sum())
        weight_in += float(s_w[lo:hi].sum())
        if p.measure == "ratio":
            cut.append(r if not none else np.nan)
            score.append(r / v if not none and 2 * v < total else np.nan)
        else:
            c, least = v - weight_in, min(v, total - v)
            cut.append(c)
            score.append(c / least if least > 1e-12 else np.nan)
        vol.append(v)
        orphans.append(none)
    return pd.DataFrame({"seed": key, "position": np.arange(1, len(order) + 1, dtype=np.int32), "node": nodes[order], "rank": q[order], "share": share[order], "cut": cut, "vol": vol, "orphans": np.array(orphans, np.int32), "score": score})


#: A seed of the i-th of several scenarios goes by i * 2^40 + seed, so that a grid of parameters is one job.
SCENARIO = 1 << 40
Scenarios = list[tuple[Params, Derived]]


def scenario_seeds(seeds: DataFrame, numbers) -> DataFrame:
    """The seeds of each scenario number; vertices must be below 2^40."""
    return seeds.select(F.explode(F.array(*[F.lit(i).cast("long") * SCENARIO + F.col("seed") for i in numbers])).alias("seed"))


def _by(df: DataFrame) -> list[str]:
    return ["seed"] if "seed" in df.columns else []


def curves(sub_edges: DataFrame, deg: DataFrame, scenarios: Scenarios, total: float) -> DataFrame:
    """CURVE rows of every seed, ranked and swept in one task each; `deg` may differ by seed."""
    rows = both_ways(sub_edges.select("src", "dst", "seed", "w")).join(deg.select(*_by(deg), F.col("node").alias("src"), "deg"), [*_by(deg), "src"])

    def job(key, f: pd.DataFrame) -> pd.DataFrame:
        p, d = scenarios[int(key[0]) // SCENARIO]
        return Compact(*(f[c].to_numpy() for c in ("src", "dst", "w", "deg"))).curve(int(key[0]), int(key[0]) % SCENARIO, p, d, total)

    return rows.groupBy("seed").applyInPandas(job, CURVE).replace(float("nan"), None)


def whole_curves(edges: DataFrame, deg: DataFrame, seeds: DataFrame, scenarios: Scenarios, total: float) -> DataFrame:
    """CURVE rows of every seed on one whole graph, sent to all tasks: at most SEND_MOST edges, which callers check."""
    table = both_ways(edges.select("src", "dst", "w")).join(deg.select(F.col("node").alias("src"), "deg"), "src").select("src", "dst", "w", "deg").toArrow()
    sent = edges.sparkSession.sparkContext.broadcast(Compact(*(np.asarray(table[c]) for c in ("src", "dst", "w", "deg"))))

    def job(frames):
        for f in frames:
            for key in f["seed"].tolist():
                yield sent.value.curve(key, key % SCENARIO, *scenarios[key // SCENARIO], total)

    return seeds.select("seed").distinct().repartition("seed").mapInPandas(job, CURVE).replace(float("nan"), None)


def seed_rank(edges: DataFrame, seeds: DataFrame, p: Params, d: Derived, checkpoint_every: int = 4) -> DataFrame:
    """seed, node, rank, deg by joins, one shuffle a step, on each seed's edges or, without a seed column, one graph for all.

    Stops as `rank_vector` does, seed by seed: a sum of each row's rank and the one before gives a seed's change, and seeds
    that have come to rest leave the loop.
    """
    by = _by(edges)
    e = staged(both_ways(edges.select("src", "dst", *by, "w")), "rank-edges")
    deg = staged(e.groupBy(*by, F.col("src").alias("node")).agg(F.sum("w").alias("deg")), "rank-degrees")
    t = staged(e.join(deg.withColumnRenamed("node", "src"), [*by, "src"]).select(*by, F.col("src").alias("node"), "dst", (F.col("w") / F.col("deg")).alias("p")), "transitions")
    start = seeds.select("seed", F.col("seed").alias("node")).distinct()
    q, done = start.withColumn("rank", F.lit(1.0 if p.stop != "mass" else 0.0)), None
    half, rank = (1 - p.alpha_n) * 0.5, F.col("rank")
    for step in range(1, d.steps + 1):
        moved = q.join(t, [*by, "node"]).select("seed", F.col("dst").alias("node"), (rank * F.col("p") * half).alias("rank"), F.lit(0.0).alias("before"))
        kept = q.select("seed", "node", (rank * half).alias("rank"), rank.alias("before"))
        back = start.join(q.select("seed"), "seed", "left_semi").select("seed", "node", F.lit(p.alpha_n).alias("rank"), F.lit(0.0).alias("before"))
        new = moved.unionByName(kept).unionByName(back).groupBy("seed", "node").agg(F.sum("rank").alias("rank"), F.sum("before").alias("before"))
        if p.truncate == "feedback":
            new = new.join(deg, [*by, "node"], "left").withColumn("rank", F.when(rank > d.eps * F.coalesce("deg", F.lit(0.0)), rank).otherwise(0.0)).drop("deg")
        if p.stop == "fixed":
            q = new.where("rank > 0").drop("before")
            q = staged(q, "rank") if step % checkpoint_every == 0 else q
            continue
        new = staged(new, "rank")
        change = F.abs(F.sum("rank") - F.sum("before")) if p.stop == "mass" else F.sum(F.abs(rank - F.col("before")))
        rest = new.groupBy("seed").agg(change.alias("change")).where(F.col("change") < p.eps_t).select("seed")
        new = new.where("rank > 0").drop("before")
        over = new.join(rest, "seed", "left_semi")
        done = over if done is None else done.unionByName(over)
        q = new.join(rest, "seed", "left_anti")
        if q.isEmpty():
            break
    out = (q if done is None else q.unionByName(done)).join(deg, [*by, "node"])
    return out.where(rank > d.eps * F.col("deg")) if p.truncate == "output" else out


def rank_order(ranks: DataFrame, n_s: int) -> DataFrame:
    """seed, position, node, rank, share: the first n_s vertices by rank over degree."""
    share = F.round(F.col("rank") / F.col("deg"), DIGITS)
    w = Window.partitionBy("seed").orderBy(F.desc("share"), "node")
    return ranks.where("rank > 0").withColumn("share", share).withColumn("position", F.row_number().over(w)).where(F.col("position") <= n_s).select("seed", "position", "node", "rank", "share")


def sweep_curve(order: DataFrame, edges: DataFrame, deg: DataFrame, p: Params, total: float) -> DataFrame:
    """CURVE rows from an order by windows: running sums over the steps at which inside weight and ratios change.

    Edges and degrees may differ by seed; with `cut_scope` subgraph the degrees and volumes are those of the edges given.
    """
    pos = order.select("seed", "node", "position")
    by = _by(edges)
    e = both_ways(edges.select("src", "dst", *by, "w"))
    volume = F.lit(total)
    if p.cut_scope == "subgraph":
        deg = e.groupBy(*by, F.col("src").alias("node")).agg(F.sum("w").alias("deg"))
        sums = deg.groupBy(*by).agg(F.sum("deg").alias("total"))
        deg, volume = (deg.join(sums, by) if by else deg.crossJoin(F.broadcast(sums))), F.col("total")  # without seeds the sum is one row
    own = [*_by(deg), "node"]
    inner = e.join(pos.select("seed", F.col("node").alias("src"), F.col("position").alias("pa")), [*by, "src"]).join(pos.select("seed", F.col("node").alias("dst"), F.col("position").alias("pb")), ["seed", "dst"])
    gains = inner.select("seed", F.col("src").alias("node"), F.greatest("pa", "pb").alias("step"), "w").groupBy("seed", "node", "step").agg(F.sum("w").alias("w"))
    up = Window.partitionBy("seed", "node").orderBy("step").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    g = gains.join(deg, own).withColumn("after", F.sum("w").over(up)).withColumn("before", F.col("after") - F.col("w"))
    first = F.row_number().over(Window.partitionBy("seed", "node").orderBy("step")) == 1
    ratio = lambda x: F.col("deg") / F.col(x) - 1
    g = g.withColumn("d", F.when(first, ratio("after")).otherwise(ratio("after") - ratio("before"))).withColumn("joined", F.when(first, 1).otherwise(0))
    steps = g.groupBy("seed", F.col("step").alias("position")).agg(F.sum("d").alias("d"), F.sum("joined").alias("joined"), F.sum("w").alias("w"))
    run = Window.partitionBy("seed").orderBy("position").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    c = order.join(deg, own).join(steps, ["seed", "position"], "left")
    zero = lambda x: F.sum(F.coalesce(x, F.lit(0))).over(run)
    c = c.withColumn("vol", F.sum("deg").over(run)).withColumn("r", zero("d")).withColumn("orphans", (F.col("position") - zero("joined")).cast("int")).withColumn("win", zero("w"))
    if p.measure == "ratio":
        cut = F.when(F.col("orphans") == 0, F.col("r"))
        score = F.when((F.col("orphans") == 0) & (2 * F.col("vol") < volume), F.col("r") / F.col("vol"))
    else:
        cut = F.col("vol") - F.col("win")
        least = F.least(F.col("vol"), volume - F.col("vol"))
        score = F.when(least > 1e-12, cut / least)
    return c.select("seed", "position", "node", "rank", "share", cut.alias("cut"), "vol", "orphans", score.alias("score"))


def choose_partition(curve: DataFrame, seeds: DataFrame, p: Params) -> tuple[DataFrame, DataFrame]:
    """(members, summary): the prefix of the lowest score, shortest on ties; the seed alone if none has a score.

    `target` keeps nothing of a seed whose best score doesn't lie below phi_o.
    """
    score = F.round("score", 10)
    best = curve.where("score IS NOT NULL").groupBy("seed").agg(F.min(F.struct(score.alias("score"), F.col("position").alias("size"))).alias("b"))
    s = seeds.select("seed").distinct().join(best, "seed", "left").select("seed", F.coalesce(F.col("b.size"), F.lit(1)).alias("size"), F.col("b.score").alias("score"), F.coalesce(F.col("b.score") < p.phi_o, F.lit(False)).alias("target_met"))
    if p.select == "target":
        s = s.withColumn("size", F.when(F.col("target_met"), F.col("size")).otherwise(F.lit(0)))
    members = s.join(curve.select("seed", "position", "node"), "seed", "left").where("position <= size").select("seed", "node", "position")
    alone = s.where("size = 1").join(members.select("seed"), "seed", "left_anti").select("seed", F.col("seed").alias("node"), F.lit(1).alias("position"))
    return members.unionByName(alone), s


def push_rank(edges: DataFrame, seeds: DataFrame, alpha: float = 0.2, eps: float = 1e-4, rounds: int = 1000) -> DataFrame:
    """seed, node, rank, residual by residual pushes: all vertices whose residual exceeds eps times the degree push at once.

    A push takes alpha of a residual off the sum of all, so the rounds end; if not within `rounds`, that is an error.
    """
    e = staged(both_ways(edges.select("src", "dst", "w")), "push-edges")
    deg = staged(e.groupBy(F.col("src").alias("node")).agg(F.sum("w").alias("deg")), "push-degrees")
    state = seeds.select("seed", F.col("seed").alias("node"), F.lit(0.0).alias("rank"), F.lit(1.0).alias("residual"))
    for _ in range(rounds):
        s = state.join(deg, "node", "left").withColumn("hot", F.coalesce(F.col("residual") > eps * F.col("deg"), F.lit(False)))
        s = staged(s, "push")
        if s.where("hot").isEmpty():
            return s.select("seed", "node", "rank", "residual")
        r = F.col("residual")
        stay = s.select("seed", "node", F.when(F.col("hot"), F.col("rank") + alpha * r).otherwise(F.col("rank")).alias("rank"), F.when(F.col("hot"), (1 - alpha) * 0.5 * r).otherwise(r).alias("residual"))
        out = s.where("hot").join(e.withColumnRenamed("src", "node"), "node").select("seed", F.col("dst").alias("node"), F.lit(0.0).alias("rank"), ((1 - alpha) * 0.5 * r * F.col("w") / F.col("deg")).alias("residual"))
        state = stay.unionByName(out).groupBy("seed", "node").agg(F.sum("rank").alias("rank"), F.sum("residual").alias("residual"))
    raise RuntimeError(f"residuals above eps times the degree are left after {rounds} rounds")
