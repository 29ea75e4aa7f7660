"""Nearest neighbours by several shifted Hilbert curves, with an exact completion by block bounds.

Each curve projects the vectors on a few random directions, shifts and quantises them, and orders them by Hilbert
key; Spark range-partitions (curve, key, id) and a task slides a window over its sorted rows, scoring each query
against its neighbours. The merged and reranked answers of all curves give each query a k-th best score.

The completion then makes the answer exact: the rows in order of the first curve form blocks with a centre and
radius, queries form such blocks too, and only pairs of blocks whose bound reaches the smallest k-th best score
are scored. On clustered vectors this prunes most pairs; on vectors without structure it prunes few, and the work is
that of the query set against all rows in blocks.

Scores add products in order of the components in double precision, so equal vectors tie exactly; ties go to the
smaller id.

Cases: null ids, null, zero and non-finite vectors and those holding nulls take no part; vectors of several lengths are
searched length by length; repeated ids are rows of their own: each asks for itself, and the others may answer it; a table of
fewer than k + 1 rows gives all; an empty one gives none.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from localcomm.llm.common import staged


@dataclass(frozen=True)
class CurveParams:
    k: int = 20
    curves: int = 8
    directions: int = 8
    bits: int = 6
    window: int = 256
    query_every: int = 20
    query_block: int = 512
    row_block: int = 4096
    complete: bool = True
    seed: int = 11


def hilbert_keys(cells: np.ndarray, bits: int) -> np.ndarray:
    """Keys along the Hilbert curve of rows of whole-number cells, by the public transpose method, for all rows at once."""
    x = [cells[:, i].astype(np.uint64) for i in range(cells.shape[1])]
    one = np.uint64(1)
    for b in range(bits - 1, 0, -1):
        q, low = np.uint64(1 << b), np.uint64((1 << b) - 1)
        for i in range(len(x)):
            flip = (x[i] & q) != 0
            swap = np.where(flip, np.uint64(0), (x[0] ^ x[i]) & low)
            x[0] = np.where(flip, x[0] ^ low, x[0] ^ swap)
            if i:
                x[i] = x[i] ^ swap
    for i in range(1, len(x)):
        x[i] = x[i] ^ x[i - 1]
    t = np.zeros(len(cells), np.uint64)
    for b in range(bits - 1, 0, -1):
        t = np.where((x[-1] & np.uint64(1 << b)) != 0, t ^ np.uint64((1 << b) - 1), t)
    key = np.zeros(len(cells), np.uint64)
    for b in range(bits - 1, -1, -1):
        for v in x:
            key = (key << one) | (((v ^ t) >> np.uint64(b)) & one)
    return key.astype(np.int64)


class Curve:
    """One projection with its shift; cells come from a smooth squash of the projected values, so no range is needed."""

    def __init__(self, dim: int, number: int, scale: float, params: CurveParams):
        rng = np.random.default_rng((params.seed, number))
        self.axes = np.linalg.qr(rng.normal(size=(dim, dim)))[0][:, : min(params.directions, dim)]
        self.shift = rng.uniform(0, 0.5, self.axes.shape[1])
        self.scale, self.bits = max(scale, 1e-300), params.bits

    def keys(self, x: np.ndarray) -> np.ndarray:
        y = (x @ self.axes) / self.scale
        unit = (0.5 * (1 + np.tanh(0.8 * y)) + self.shift) / 1.5
        return hilbert_keys(np.minimum((unit * (1 << self.bits)).astype(np.int64), (1 << self.bits) - 1), self.bits)


def vectors(table: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """row, vec_id and vector (array<double>) of the rows that take part; `row` tells apart rows that repeat an id."""
    v = F.col("vector")
    rows = table.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("vector")).where(
        F.col("vec_id").isNotNull() & v.isNotNull() & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists(v, lambda x: x != 0)
    )
    return staged(rows.withColumn("row", F.monotonically_increasing_id()), "vectors")


def _matrix(batch: pa.RecordBatch, name: str = "vector") -> np.ndarray:
    lists = batch.column(name)
    return np.asarray(lists.flatten()).reshape(len(lists), -1)


def exact_scores(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Inner products of one vector with rows, summed component by component."""
    s = np.zeros(len(x))
    for j in range(len(q)):
        s += q[j] * x[:, j]
    return s


class Rows:
    """Vectors with their ids and rows."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, rows: np.ndarray):
        self.x, self.ids, self.rows = x, ids, rows

    @staticmethod
    def of(batch: pa.RecordBatch) -> "Rows":
        return Rows(_matrix(batch), np.asarray(batch.column("vec_id")), np.asarray(batch.column("row")))

    def __getitem__(self, at) -> "Rows":
        return Rows(self.x[at], self.ids[at], self.rows[at])

    def __add__(self, more: "Rows") -> "Rows":
        return Rows(np.concatenate([self.x, more.x]), np.concatenate([self.ids, more.ids]), np.concatenate([self.rows, more.rows]))

    def __len__(self) -> int:
        return len(self.ids)


def nearest(q: np.ndarray, own: int, rough: np.ndarray, near: Rows, k: int, least: float = -np.inf) -> tuple[Rows, np.ndarray]:
    """The k best rows by exact score and id, from rough scores (the query's own row left out, those below `least` too)."""
    rough = np.where(near.rows == own, -np.inf, rough)
    slack = 1e-9 * max(1.0, float(np.abs(q).sum()) * float(np.abs(near.x).max(initial=0)))
    floor = max(least - slack, np.partition(rough, len(rough) - k)[len(rough) - k] - slack if len(rough) > k else -np.inf)
    some = near[np.flatnonzero((rough >= floor) & (rough > -np.inf))]
    s = exact_scores(q, some.x)
    order = np.lexsort((some.rows, some.ids, -s))[:k]
    return some[order], s[order]


FOUND = "query_row long, query_id long, row long, vec_id long, score double"


def _found(got: list[tuple[int, int, Rows, np.ndarray]]) -> pa.RecordBatch:
    each = [len(s) for *_, s in got]
    repeated = lambda i: pa.array(np.repeat(np.array([g[i] for g in got], np.int64), each))
    return pa.RecordBatch.from_arrays([repeated(0), repeated(1), pa.array(np.concatenate([g[2].rows for g in got])), pa.array(np.concatenate([g[2].ids for g in got])), pa.array(np.concatenate([g[3] for g in got]))], [x.split()[0] for x in FOUND.split(", ")])


def keyed(rows: DataFrame, dim: int, scale: float, curves: range, params: CurveParams) -> DataFrame:
    """curve, key, vec_id, row, vector: one row per curve."""

    def job(batches):
        made = [Curve(dim, c, scale, params) for c in curves]
        for batch in batches:
            for lo in range(0, batch.num_rows, 4096):
                part = batch.slice(lo, 4096)
                x = _matrix(part)
                for c, curve in zip(curves, made, strict=True):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), c, np.int32)), pa.array(curve.keys(x)), part.column("vec_id"), part.column("row"), part.column("vector")], ["curve", "key", "vec_id", "row", "vector"])

    return rows.mapInArrow(job, "curve int, key long, vec_id long, row long, vector array<double>")


def windows(ordered: DataFrame, params: CurveParams) -> DataFrame:
    """Each query's best among its neighbours on each curve; rows come sorted by (curve, key, vec_id)."""
    w, step = params.window, params.query_every

    def scored(rows, lo, hi):
        """Answers of the queries at places lo..hi of a stretch of one curve."""
        out, at = [], lo + np.flatnonzero(rows.ids[lo:hi] % step == 0)
        for g in range(0, len(at), 32):
            some = at[g : g + 32]
            a, b = max(0, some[0] - w), min(len(rows), some[-1] + w + 1)
            rough = rows.x[some] @ rows.x[a:b].T
            for r, i in enumerate(some):
                l, h = max(a, i - w), min(b, i + w + 1)
                out.append((int(rows.rows[i]), int(rows.ids[i]), *nearest(rows.x[i], rows.rows[i], rough[r, l - a : h - a], rows[l:h], params.k)))
        return out

    def job(batches):
        # A stretch holds the last rows that are still a neighbour of later ones.
        curve, rows, done = None, None, 0
        for batch in batches:
            cs = np.asarray(batch.column("curve"))
            bounds = [0, *(np.flatnonzero(np.diff(cs)) + 1).tolist(), len(cs)]
            for s, e in zip(bounds, bounds[1:], strict=False):
                if e == s:
                    continue
                new = Rows.of(batch.slice(s, e - s))
                if curve is not None and curve != cs[s]:
                    if out := scored(rows, done, len(rows)):
                        yield _found(out)
                    curve = None
                if curve is None:
                    curve, rows, done = cs[s], new, 0
                else:
                    rows = rows + new
                ready = len(rows) - w
                if ready > done:
                    if out := scored(rows, done, ready):
                        yield _found(out)
                    cut = max(0, ready - w)
                    rows, done = rows[cut:], ready - cut
        if curve is not None and (out := scored(rows, done, len(rows))):
            yield _found(out)

    return ordered.mapInArrow(job, FOUND)


def merged(found: DataFrame, k: int) -> DataFrame:
    """FOUND columns and rank: the k best of what several searches found for each query row."""
    order = Window.partitionBy("query_row").orderBy(F.desc("score"), "vec_id", "row")
    return found.dropDuplicates(["query_row", "row"]).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


BLOCK = "block long, n int, centre array<double>, radius double, least double, ids array<long>, rows array<long>, least_each array<double>, vectors array<double>"


def blocks(ordered: DataFrame, size: int) -> DataFrame:
    """Blocks of neighbouring rows with centre and radius; `least` is the smallest score that could still matter."""
    from pyspark import TaskContext

    def job(batches):
        at, held, number = TaskContext.get().partitionId() << 32, None, 0

        def batch_of(part, least):
            centre = part.x.mean(0)
            radius = float(np.sqrt(((part.x - centre) ** 2).sum(1)).max()) * (1 + 1e-9) + 1e-12
            lists = [pa.ListArray.from_arrays(pa.array([0, len(v)], pa.int32()), pa.array(v)) for v in (part.ids, part.rows, least, part.x.ravel())]
            return pa.RecordBatch.from_arrays([pa.array([at + number]), pa.array([len(part)], pa.int32()), pa.array([centre.tolist()], pa.list_(pa.float64())), pa.array([radius]), pa.array([float(least.min())]), *lists], [x.split()[0] for x in BLOCK.split(", ")])

        for batch in batches:
            new = Rows.of(batch), np.asarray(batch.column("least"))
            held = new if held is None else (held[0] + new[0], np.concatenate([held[1], new[1]]))
            while len(held[0]) >= size:
                yield batch_of(held[0][:size], held[1][:size])
                held, number = (held[0][size:], held[1][size:]), number + 1
        if held is not None and len(held[0]):
            yield batch_of(*held)

    return ordered.mapInArrow(job, BLOCK)


def completed(first_curve: DataFrame, found: DataFrame, params: CurveParams) -> DataFrame:
    """What the windows may have missed: answers from every pair of blocks whose bound reaches the k-th best."""
    kth = found.groupBy("query_row").agg(F.max("rank").alias("n"), F.min("score").alias("least"))
    kth = kth.select(F.col("query_row").alias("row"), F.when(F.col("n") >= params.k, F.col("least")).otherwise(F.lit(float("-inf"))).alias("least"))
    asked = first_curve.where(F.pmod("vec_id", F.lit(params.query_every)) == 0).join(kth, "row", "left").withColumn("least", F.coalesce("least", F.lit(float("-inf"))))
    order = ["curve", "key", "vec_id", "row"]
    by_row = staged(blocks(first_curve.withColumn("least", F.lit(0.0)), params.row_block), "row-blocks")
    by_query = staged(blocks(asked.repartitionByRange(*order).sortWithinPartitions(*order), params.query_block), "query-blocks")
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)
    norm = lambda a: F.sqrt(dot(a, a))
    # Summaries of blocks only: each query block lists all row blocks by number, then the bound decides.
    heads = by_row.select(F.col("block").alias("r"), F.col("centre").alias("rc"), F.col("radius").alias("rr"), F.monotonically_increasing_id().alias("i")).withColumn("slot", F.pmod("i", F.lit(16)))
    asks = by_query.select(F.col("block").alias("q"), F.col("centre").alias("qc"), F.col("radius").alias("qr"), "least").withColumn("slot", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(15).cast("long"))))
    bound = dot(F.col("qc"), F.col("rc")) + norm(F.col("qc")) * F.col("rr") + norm(F.col("rc")) * F.col("qr") + F.col("qr") * F.col("rr")
    pairs = asks.join(heads, "slot").where(bound * F.lit(1 + 1e-9) + F.lit(1e-9) >= F.col("least")).select("q", "r")
    # Query blocks are the smaller ones: they travel to the row blocks, which are dealt once.
    asked = pairs.join(by_query.select(F.col("block").alias("q"), "ids", "rows", "least_each", "vectors"), "q")
    wide = asked.join(by_row.select(F.col("block").alias("r"), "centre", "radius", F.col("ids").alias("row_ids"), F.col("rows").alias("row_rows"), F.col("vectors").alias("row_vectors")), "r")

    def job(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                get = lambda c: np.asarray(batch.column(c).slice(i, 1).flatten())  # noqa: B023, E731
                ids, rows, least, centre = get("ids"), get("rows"), get("least_each"), get("centre")
                q, near = get("vectors").reshape(len(ids), -1), Rows(get("row_vectors").reshape(-1, len(centre)), get("row_ids"), get("row_rows"))
                radius = batch.column("radius")[i].as_py()
                may = np.flatnonzero(q @ centre + np.sqrt((q**2).sum(1)) * radius + 1e-9 >= least)
                out = []
                for g in range(0, len(may), 64):
                    some = may[g : g + 64]
                    rough = q[some] @ near.x.T
                    for a, r in zip(some, rough, strict=True):
                        got, s = nearest(q[a], rows[a], r, near, params.k, least[a])
                        if len(got):
                            out.append((int(rows[a]), int(ids[a]), got, s))
                if out:
                    yield _found(out)

    return wide.mapInArrow(job, FOUND)


def searched(table: DataFrame, params: CurveParams = CurveParams(), id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score of the k nearest rows of every query (ids divisible by `query_every`)."""
    rows = vectors(table, id_col, vec_col)
    sizes = rows.groupBy(F.size("vector").alias("dim")).agg(F.avg(F.aggregate("vector", F.lit(0.0), lambda s, v: s + v * v)).alias("square")).orderBy("dim").collect()  # one row a length
    out = table.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    for size in sizes:
        one = rows if len(sizes) == 1 else rows.where(F.size("vector") == size["dim"])
        out = out.unionByName(_searched(one, size["dim"], float(np.sqrt(size["square"] / size["dim"])), params).select(out.columns))
    return out


def _searched(rows: DataFrame, dim: int, scale: float, params: CurveParams) -> DataFrame:
    order = ["curve", "key", "vec_id", "row"]
    sort = lambda d: d.repartitionByRange(*order).sortWithinPartitions(*order)
    found = merged(windows(sort(keyed(rows, dim, scale, range(params.curves), params)), params), params.k)
    if not params.complete:
        return found
    found = staged(found, "curve-answers")
    more = completed(sort(keyed(rows, dim, scale, range(1), params)), found, params)
    return merged(found.drop("rank").unionByName(more), params.k)


def op5_curves(spark: SparkSession, sf_dir: str) -> DataFrame:
    return searched(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
