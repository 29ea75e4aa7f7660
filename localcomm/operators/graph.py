"""Structure, attribute and combined graphs as edge tables.

Edges are canonical rows (src < dst); `both_ways` gives the symmetric view. Nulls: pairs with a null end are dropped,
null attribute sets are empty. Extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from localcomm.functions.sets import PRIME, canonical, draw, jaccard


def structure_graph(pairs: DataFrame, src: str = "src", dst: str = "dst", directed: bool = False) -> DataFrame:
    """Undirected edges of a pair table: no loops, no repeats; `directed` pairs lose their direction the same way."""
    a, b = F.col(src).cast("long"), F.col(dst).cast("long")
    return pairs.where(a != b).select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")).distinct()


#: Members of a group that meet in one key.
PART = 1000


def project_bipartite(members: DataFrame, member: str, group: str, min_support: int = 1, max_group: int | None = None) -> DataFrame:
    """Members that share a group, with the number of groups shared.

    `max_group` leaves out groups beyond a size, whose pairs grow with its square; None keeps all.
    """
    from localcomm.plans.stages import staged

    m = staged(members.select(F.col(member).cast("long").alias("m"), F.col(group).alias("g")).where("m IS NOT NULL AND g IS NOT NULL").distinct(), "memberships")
    size = m.groupBy("g").agg(F.count(F.lit(1)).alias("size")).where("size > 1")
    if max_group is not None:
        size = size.where(F.col("size") <= max_group)
    # A large group meets in parts, so that its pairs are made by many tasks: one side lists all parts, the other lies in one.
    counts = size.agg(F.sum("size"), F.sum(F.col("size") * (F.col("size") - 1) / 2), F.max("size")).first()
    if counts[0] and counts[1] > DENSE * counts[0]:
        return _projected_classes(m.join(size.select("g"), "g"), min_support, int(counts[1]))
    found = _met(m, size) if (counts[2] or 0) > LISTED or max_group is not None else _met_in_lists(m)
    return found.where(F.col("support") >= min_support)


#: Pairs to a membership from which members of the same groups are looked for first.
DENSE = 8
#: Members up to which every group is a list whose pairs are made in place.
LISTED = 100
#: Pairs that a task makes from classes.
PAIRS_A_TASK = 2_000_000


def _met(m: DataFrame, size: DataFrame) -> DataFrame:
    """src < dst, support of members m in groups g of a known size."""
    own = m.join(size.select("g", F.ceil(F.col("size") / PART).alias("parts")), "g")
    left = own.select("g", F.col("m").alias("src"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part"))
    right = own.select("g", F.col("m").alias("dst"), F.pmod(F.xxhash64("m"), F.col("parts")).alias("part"))
    pairs = left.join(right, ["g", "part"]).where("src < dst")
    return pairs.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("support"))


def _met_in_lists(m: DataFrame) -> DataFrame:
    """The same for small groups (checked by the caller): a list for each, without a join."""
    lists = m.groupBy("g").agg(F.array_sort(F.collect_list("m")).alias("ms")).where(F.size("ms") > 1)
    left = lists.select("ms", F.posexplode("ms").alias("i", "src"))
    pairs = left.select("src", F.explode(F.slice("ms", F.col("i") + 2, F.size("ms"))).alias("dst"))
    return pairs.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("support"))


def _projected_classes(own: DataFrame, min_support: int, pairs: int) -> DataFrame:
    """The projection where groups are large: members of the very same groups are one class, classes meet, and pairs of their members follow."""
    from localcomm.plans.stages import staged

    by = own.groupBy("m").agg(F.array_sort(F.collect_list("g")).alias("gs"))
    held = staged(by.withColumn("c", F.min("m").over(Window.partitionBy("gs"))).select("m", "c", F.size("gs").cast("long").alias("groups")), "classes")
    firsts = staged(own.join(held.where("m = c").select("m"), "m", "left_semi"), "class-groups")
    met = _met(firsts, firsts.groupBy("g").agg(F.count(F.lit(1)).alias("size")))
    tasks = max(1, min(2000, -(-pairs // PAIRS_A_TASK)))
    met = staged(met.where(F.col("support") >= min_support), "class-pairs").repartition(tasks, "src", "dst")  # a row here is many there
    side = lambda c, x: held.select(F.col("c").alias(c), F.col("m").alias(x))
    across = met.join(side("src", "a"), "src").join(side("dst", "b"), "dst").select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), "support")
    within = held.where(F.col("groups") >= min_support).select("c", F.col("m").alias("src"), F.col("groups").alias("support")).join(held.select("c", F.col("m").alias("dst")), "c").where("src < dst").select("src", "dst", "support")
    return across.unionByName(within)


def both_ways(edges: DataFrame) -> DataFrame:
    """Each edge from either end, all other columns kept."""
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    return edges.select("src", "dst", *rest).union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *rest))


def with_sets(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """Pairs with the attribute sets xa and xb of their ends; a node without a row has the empty set."""
    n = nodes.select("node", canonical(F.col("attrs")).alias("x"))
    none = F.array().cast("array<string>")
    out = pairs.join(n.select(F.col("node").alias("src"), F.col("x").alias("xa")), "src", "left").join(n.select(F.col("node").alias("dst"), F.col("x").alias("xb")), "dst", "left")
    return out.withColumn("xa", F.coalesce("xa", none)).withColumn("xb", F.coalesce("xb", none))


#: Members of all sets from which edges travel without them.
SETS_FROM = 200_000


def _similar(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """src, dst, sim of edges. Large tables of sets lie in the shared folder and are mapped; small ones, or those of another file system, are joined."""
    from localcomm.operators import mapped, overlap
    from localcomm.plans.stages import staged

    e = edges.select("src", "dst")
    if mapped.local_path(edges.sparkSession) is not None and all(t == "bigint" for _, t in e.dtypes):
        n = staged(nodes.select(F.col("node").cast("long").alias("node"), canonical(F.col("attrs")).alias("attrs")), "sets")
        if (n.agg(F.sum(F.size("attrs"))).first()[0] or 0) >= SETS_FROM:
            where = overlap.written(n.where("node IS NOT NULL AND size(attrs) > 0").withColumnRenamed("attrs", "x"))
            if where is not None:
                return overlap.similarities(e.where("src IS NOT NULL AND dst IS NOT NULL"), where)
        nodes = n
    return with_sets(e, nodes).withColumn("sim", jaccard(F.col("xa"), F.col("xb"))).select("src", "dst", "sim")


def attribute_graph(nodes: DataFrame, edges: DataFrame, floor: float = 0.05, t_e: float | None = None, strategy: str = "prefix") -> DataFrame:
    """src, dst, sim, is_structural: similarity of every edge, floored where it is 0, and with t_e also of every other pair above it."""
    out = _similar(edges, nodes).select("src", "dst", F.when(F.col("sim") > 0, F.col("sim")).otherwise(F.lit(floor)).alias("sim"), F.lit(True).alias("is_structural"))
    if t_e is not None:
        from localcomm.operators.forecast import similar_pairs

        new = similar_pairs(nodes, t_e, strategy).join(edges.select("src", "dst"), ["src", "dst"], "left_anti")
        out = out.unionByName(new.select("src", "dst", "sim", F.lit(False).alias("is_structural")))
    return out


def combined_graph(attr_edges: DataFrame) -> DataFrame:
    """src, dst, w, w_g, w_a, is_structural: similarity, plus 1 on structural edges."""
    w_g = F.when(F.col("is_structural"), 1.0).otherwise(0.0)
    return attr_edges.select("src", "dst", (w_g + F.col("sim")).alias("w"), w_g.alias("w_g"), F.col("sim").alias("w_a"), "is_structural")


def plain_graph(edges: DataFrame) -> DataFrame:
    """A structure graph in the combined graph's form, all weights 1."""
    return edges.select("src", "dst", F.lit(1.0).alias("w"), F.lit(1.0).alias("w_g"), F.lit(0.0).alias("w_a"), F.lit(True).alias("is_structural"))


def degrees(edges: DataFrame, weight: str | None = None, key: tuple[str, ...] = ()) -> DataFrame:
    """node, deg (count, or sum of a weight), by further keys."""
    ends = both_ways(edges)
    deg = F.sum(weight) if weight else F.count(F.lit(1))
    return ends.groupBy(*key, F.col("src").alias("node")).agg(deg.alias("deg"))


def volume(members: DataFrame, deg: DataFrame) -> DataFrame:
    """seed, vol: degree sum of each member set (columns seed, node)."""
    return members.join(deg, "node", "left").groupBy("seed").agg(F.coalesce(F.sum("deg"), F.lit(0)).cast("double").alias("vol"))


def induced(edges: DataFrame, sub_nodes: DataFrame) -> DataFrame:
    """Edges with both ends in the node set of a seed; all edge columns and the seed."""
    s = sub_nodes.select("seed", "node")
    return edges.join(s.select("seed", F.col("node").alias("src")), "src").join(s.select("seed", F.col("node").alias("dst")), ["seed", "dst"])


UNIT = 1000


def unit_weight(weighted: bool = True):
    """A weight w in whole thousandths, at least 1."""
    return F.greatest(F.lit(1), F.round(F.col("w") * UNIT)).cast("long") if weighted else F.lit(1).cast("long")


def adjacency(combined: DataFrame, weighted: bool = True) -> DataFrame:
    """src, dst, lo, hi, total: each neighbour's share [lo, hi) of the whole-number weight of a vertex.

    Weights are rounded to thousandths, at least 1; totals stay below 2^32, which draws need, up to two million neighbours
    of weight 2 each.
    """
    e = both_ways(combined.select("src", "dst", unit_weight(weighted).alias("wi")))
    up = Window.partitionBy("src").orderBy("dst").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return e.select("src", "dst", (F.sum("wi").over(up) - F.col("wi")).alias("lo"), F.sum("wi").over(up).alias("hi"), F.sum("wi").over(Window.partitionBy("src")).alias("total"))


def chunked(adj: DataFrame, size: int = 256) -> DataFrame:
    """src, lo, hi, total, nbrs: rows of `adjacency` in arrays of at most `size` neighbours (hi, dst), so that a hub's are few."""
    place = F.row_number().over(Window.partitionBy("src").orderBy("dst"))
    rows = adj.withColumn("chunk", F.floor((place - 1) / size)).groupBy("src", "chunk")
    return rows.agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.max("total").alias("total"), F.array_sort(F.collect_list(F.struct("hi", "dst"))).alias("nbrs")).drop("chunk")


def to_csr(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """node, row_ptr, columns: compressed rows as a table, one row a vertex, isolated ones included.

    Offsets are running sums over ranges of nodes: a window inside each range, and the ranges' own sums before it.
    """
    rows = both_ways(edges.select("src", "dst")).groupBy(F.col("src").alias("node")).agg(F.array_sort(F.collect_list("dst")).alias("columns"))
    full = nodes.select("node").join(rows, "node", "left").withColumn("columns", F.coalesce("columns", F.array().cast("array<bigint>")))
    part = full.withColumn("part", F.floor(F.col("node") / 4096))
    sums = part.groupBy("part").agg(F.sum(F.size("columns")).alias("s"))
    before = sums.select("part", (F.sum("s").over(Window.orderBy("part")) - F.col("s")).alias("before"))  # one row per 4096 nodes
    run = Window.partitionBy("part").orderBy("node")
    return part.join(before, "part").select("node", (F.col("before") + F.sum(F.size("columns")).over(run) - F.size("columns")).alias("row_ptr"), "columns")


def drop_edges(edges: DataFrame, fraction: float = 0.15, salt: int = 42) -> DataFrame:
    """Edges without a reproducible random fraction of them."""
    return edges.where(draw("src", "dst", salt=salt) >= int(fraction * PRIME))


def edge_fraction(edges: DataFrame, i: int, of: int = 10, salt: int = 7) -> DataFrame:
    """The i-th of `of` nested parts: each part holds the ones before it."""
    return edges.where(draw("src", "dst", salt=salt) < i * (PRIME // of) + (PRIME if i >= of else 0))


def fraction_mask(i: int, of: int = 10, salt: int = 7):
    """`edge_fraction` for arrays of src and dst."""

    def kept(src: np.ndarray, dst: np.ndarray) -> np.ndarray:
        from localcomm.operators.walks import draw_numpy

        return draw_numpy([src, dst], salt) < i * (PRIME // of) + (PRIME if i >= of else 0)

    return kept


def sample_seeds(edges: DataFrame, k: int, salt: int = 42) -> DataFrame:
    """k vertices of degree 1 or more, in the order of a draw."""
    nodes = edges.select(F.col("src").alias("seed")).union(edges.select("dst")).distinct()
    return nodes.orderBy(draw("seed", salt=salt), "seed").limit(k)


#: Edges (or stars that stand for them) up to which one task finds the components.
LABEL_ROWS = 10_000_000
#: Edges that a task takes in before it turns them into stars.
STAR_ROWS = 2_000_000


def stars(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All vertices of some edges but the smallest of each component, and that smallest vertex."""
    ids, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    a, b = at[: len(src)], at[len(src) :]
    label = np.arange(len(ids))
    while len(a):
        a, b = label[a], label[b]
        apart = a != b
        a, b = a[apart], b[apart]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while not np.array_equal(label, far := label[label]):
            label = far
    moved = label != np.arange(len(ids))
    return ids[moved], ids[label[moved]]


def _starred(edges: DataFrame) -> DataFrame:
    """Edges turned into stars, partition by partition: fewer edges of the same components."""

    def job(batches):
        import pyarrow as pa

        held, new, many = [np.zeros(0, np.int64)] * 2, [], 0
        fold = lambda: stars(*(np.concatenate([held[i], *[x[i] for x in new]]) for i in (0, 1)))
        for batch in batches:
            new.append([batch.column(c).to_numpy(zero_copy_only=False) for c in ("src", "dst")])
            many += batch.num_rows
            if many > max(STAR_ROWS, len(held[0])):
                held, new, many = fold(), [], 0
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in fold()], ["src", "dst"])

    return edges.mapInArrow(job, "src long, dst long")


def component_labels(nodes: DataFrame, edges: DataFrame, rounds: int = 40) -> DataFrame:
    """node, label (smallest node of its component).

    Tasks turn their edges into stars, in fewer and fewer partitions while that makes them fewer. Up to LABEL_ROWS one task
    ends it; beyond, labels spread over what is left.
    """
    from localcomm.plans.stages import staged

    e = staged(_starred(edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).where("src IS NOT NULL AND dst IS NOT NULL")), "stars")
    left = e.count()
    while left > LABEL_ROWS:
        e = staged(_starred(e.repartition(max(1, -(-left // LABEL_ROWS)), "dst")), "stars")
        before, left = left, e.count()
        if left > 0.7 * before:
            return _spread_labels(nodes, e, rounds)
    found = _starred(e.repartition(1)).select(F.col("src").alias("node"), F.col("dst").alias("label"))
    return nodes.select("node").join(found, "node", "left").select("node", F.coalesce("label", "node").alias("label"))


def _spread_labels(nodes: DataFrame, edges: DataFrame, rounds: int = 40) -> DataFrame:
    """node, label (smallest node of its component) by label spreading with jumps; stops when nothing changes."""
    from localcomm.plans.stages import staged

    e = staged(both_ways(edges.select("src", "dst")), "cc-edges")
    cur = staged(nodes.select("node", F.col("node").alias("label")), "cc")
    for _ in range(rounds):
        near = e.join(cur.select(F.col("node").alias("dst"), "label"), "dst").groupBy(F.col("src").alias("node")).agg(F.min("label").alias("low"))
        step = cur.join(near, "node", "left").select("node", F.least("label", F.coalesce("low", "label")).alias("label"), F.col("label").alias("old"))
        jump = step.select(F.col("node").alias("label"), F.col("label").alias("far"))
        nxt = staged(step.join(jump, "label", "left").select("node", F.least("label", F.coalesce("far", "label")).alias("label"), "old"), "cc")
        changed = not nxt.where("label <> old").isEmpty()
        cur = nxt.select("node", "label")
        if not changed:
            return cur
    raise RuntimeError("component labels didn't settle")


def network_stats(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """n, m, mean_deg, max_deg, isolated, components, largest: one row."""
    deg = nodes.select("node").join(degrees(edges), "node", "left").withColumn("deg", F.coalesce("deg", F.lit(0)))
    labels = component_labels(nodes, edges).groupBy("label").agg(F.count(F.lit(1)).alias("size"))
    a = deg.agg(F.count(F.lit(1)).alias("n"), (F.sum("deg") / 2).cast("long").alias("m"), F.avg("deg").alias("mean_deg"), F.max("deg").alias("max_deg"), F.sum((F.col("deg") == 0).cast("long")).alias("isolated"))
    b = labels.agg(F.count(F.lit(1)).alias("components"), F.max("size").alias("largest"))
    return a.withColumn("one", F.lit(1)).join(b.withColumn("one", F.lit(1)), "one").drop("one")


def snapshot(edges_ts: DataFrame, until) -> DataFrame:
    """Edges seen up to a moment (column ts): the graph as it was."""
    return structure_graph(edges_ts.where(F.col("ts") <= F.lit(until)))


def validated(nodes: DataFrame, combined: DataFrame) -> DataFrame:
    """Counts of rows that break the model: null ids, wrong order, weights of 0 or less, ends without a node."""
    n = nodes.select("node")
    bad = combined.agg(
        F.sum((F.col("src").isNull() | F.col("dst").isNull()).cast("long")).alias("null_ids"), F.sum((F.col("src") >= F.col("dst")).cast("long")).alias("unordered"), F.sum((F.col("w") <= 0).cast("long")).alias("not_positive")
    )
    loose = both_ways(combined.select("src", "dst")).join(n.withColumnRenamed("node", "src"), "src", "left_anti").agg(F.count(F.lit(1)).alias("loose_ends"))
    return bad.withColumn("one", F.lit(1)).join(loose.withColumn("one", F.lit(1)), "one").drop("one")
