"""Similarity of attribute sets along edges, with the sets in files of the shared folder that tasks map.

Members go by whole numbers; those of a single vertex count in its size only. An edge travels as its two ends, so nothing of
the sets is shuffled or sent with it.
"""

from __future__ import annotations

import os
import uuid

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcomm.operators import mapped
from localcomm.plans.stages import staged

#: Places of the table in which a task marks the members of some vertices.
MARKS = 16_000_000
#: Members of a part that a task sorts and writes.
PART_MEMBERS = 2_000_000
_KINDS = {"node": np.int64, "size": np.int64, "end": np.int64, "member": np.int32}


def written(sets: DataFrame) -> tuple[str, int, int] | None:
    """Folder, vertices and distinct shared members of sets (node long, x canonical); None if a vertex has two rows."""
    spark = sets.sparkSession
    members = sets.select("node", F.size("x").cast("long").alias("size"), F.explode("x").alias("member"))
    # Null is a member like any other; no other text begins with a space here.
    members = staged(members.withColumn("member", F.coalesce(F.concat(F.lit(" "), "member"), F.lit(""))), "members")
    shared = members.groupBy("member").agg(F.count(F.lit(1)).alias("held")).where("held > 1").select("member", F.monotonically_increasing_id().alias("id"))
    shared = staged(shared, "shared-members")
    # Ids count up in each partition; a row for each partition tells where its ids begin.
    part = F.shiftright("id", 33)
    held = sorted(shared.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n")).collect())
    begun = np.cumsum([0] + [r["n"] for r in held]).tolist()
    if begun[-1] >= 1 << 31:
        raise ValueError(f"{begun[-1]} distinct members")
    numbers = spark.createDataFrame([(r["part"], b) for r, b in zip(held, begun, strict=False)], "part long, begun long")
    dense = shared.withColumn("part", part).join(F.broadcast(numbers), "part").select("member", (F.col("begun") + F.expr("id & 8589934591")).cast("int").alias("id"))
    # A member held by one vertex leaves a row without a number, for the size.
    rows = staged(members.join(dense, "member", "left").groupBy("node", "size").agg(F.collect_list("id").alias("ids")), "numbered-sets")
    n, total = rows.agg(F.count(F.lit(1)), F.sum(F.size("ids"))).first()
    if rows.select("node").distinct().count() < n or sets.count() > n:
        return None
    folder = mapped.new_folder(spark, "sets")

    def write(batches):
        import pyarrow as pa

        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        node, size = t["node"].to_numpy(), t["size"].to_numpy()
        order = np.argsort(node)
        ids = t["ids"].combine_chunks().take(pa.array(order))
        os.makedirs(folder, exist_ok=True)
        name, count = uuid.uuid4().hex, ids.value_lengths().to_numpy()
        for key, values in (("node", node[order]), ("size", size[order]), ("end", np.cumsum(count)), ("member", ids.flatten().to_numpy())):
            values.astype(_KINDS[key]).tofile(f"{folder}/{name}.{key}")
        yield mapped.told(name, int(node[order][0]), len(node), int(count.sum()))

    parts = max(1, -(-(total or 0) // PART_MEMBERS))
    told = rows.repartitionByRange(parts, "node").mapInArrow(write, mapped.HELD).collect()  # a row for each part
    mapped.gathered(spark, folder, told, _KINDS, {"member"})
    return folder, n, begun[-1]


class Sets:
    """Mapped sets in one task."""

    def __init__(self, folder: str, n: int, members: int):
        read = lambda key: np.asarray(np.memmap(f"{folder}/{key}", _KINDS[key], "r")) if os.path.getsize(f"{folder}/{key}") else np.zeros(0, _KINDS[key])
        self.members = max(1, members)
        self.node, self.size, self.end, self.member = (read(key) for key in _KINDS)
        self.first = np.append(0, self.end[:-1]) if n else self.end

    def at(self, ids: np.ndarray) -> np.ndarray:
        """Places of vertices; -1 without a set."""
        if not len(self.node):
            return np.full(len(ids), -1)
        i = np.minimum(np.searchsorted(self.node, ids), len(self.node) - 1)
        return np.where(self.node[i] == ids, i, -1)

    def _members(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        first = self.first[at]
        size = self.end[at] - first
        return self.member[np.repeat(first - (np.cumsum(size) - size), size) + np.arange(size.sum())], size

    def similar(self, src: np.ndarray, dst: np.ndarray) -> np.ndarray:
        """`jaccard` of the sets of each pair; a vertex without a row has the empty set."""
        a, b = self.at(src), self.at(dst)
        out, some = np.zeros(len(a)), np.flatnonzero((a >= 0) & (b >= 0))
        some = some[np.argsort(a[some], kind="stable")]
        a, b = a[some], b[some]
        own, run = np.unique(a, return_inverse=True)
        step = max(1, MARKS // self.members)
        marks, shared = np.zeros(min(step, max(1, len(own))) * self.members, bool), np.zeros(len(a), np.int64)
        for low in range(0, len(own), step):
            lo, hi = np.searchsorted(run, (low, low + step))
            mine, size = self._members(own[low : low + step])
            on = np.repeat(np.arange(len(size)) * self.members, size) + mine
            marks[on] = True
            asked, size = self._members(b[lo:hi])
            met = np.append(0, np.cumsum(marks[np.repeat((run[lo:hi] - low) * self.members, size) + asked]))
            ends = np.cumsum(size)
            shared[lo:hi] = met[ends] - met[ends - size]
            marks[on] = False
        out[some] = shared / (self.size[a] + self.size[b] - shared)
        return out


_open: dict[tuple[str, int, int], Sets] = {}


def opened(where: tuple[str, int, int]) -> Sets:
    """Sets, mapped once in a worker; the ones before are let go."""
    if where not in _open:
        _open.clear()
        _open[where] = Sets(*where)
    return _open[where]


def similarities(edges: DataFrame, where: tuple[str, int, int]) -> DataFrame:
    """src, dst, sim of edges without null ends."""

    def job(batches):
        import pyarrow as pa

        for batch in batches:
            src, dst = (batch.column(c).to_numpy() for c in ("src", "dst"))
            yield pa.RecordBatch.from_arrays([batch.column("src"), batch.column("dst"), pa.array(opened(where).similar(src, dst))], ["src", "dst", "sim"])

    return edges.select("src", "dst").mapInArrow(job, "src long, dst long, sim double")
