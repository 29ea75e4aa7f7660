"""Similarity join of word n-gram sets by Jaccard, exact, with set-relation skipping; components of its links.

Sets with equal members form one class; the join works on classes, each represented by one document.

1. Families. Min-hashes name, for each class, the anchor with which it most likely agrees. The classes of one anchor meet in
   groups of bounded size, together with the anchor: a set travels once for each group, one that agrees with the anchor takes
   over the component of the anchor, and the others are compared with all of the group.
2. Prefix index. Any two similar sets share a member among the first few in a common order. Members that one text
   alone holds come first and need no index row; members that more texts hold come later. How many texts
   hold a member is counted exactly over the stretch of the hash range in which prefixes lie.
3. Block skipping. Index lists are cut into blocks by set size. The place of a member in a set bounds the sizes of the
   sets that it can still be similar to, so a row visits only the blocks that its place leaves open, and a row too far
   behind isn't listed as the smaller set at all. Lists don't pair classes of one component or one group.
4. Derived answers. A class that a family linked has a near set whose overlap with it is known. The pairs left are mapped to
   the pairs of these near sets, each compared in full once; their overlap, up to what a set has beyond its near set or
   lacks of it, decides most pairs. Pairs that it leaves open, and that aren't in one component by then, are compared in full.

A full comparison of pairs groups them by the class that occurs in most of them (in bounded parts) and sends each set once a group.
Member hashes have 64 bits, of which comparisons use 48. Filters that say how often a member is held, and which rows are to
be read, are bit arrays of at most 16 MB: a false yes of theirs costs time only, as all tasks share them.

Cases: null, empty and blank texts have no members, link with nothing and are components of their own; texts of
fewer than n words have one member; repeated rows fall in one class; a null doc_id counts as a row but never names
a component unless all its members are null; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import contextlib
import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from localcomm.llm.common import Scratch, flat, mixed, run_hashes, slices, texts, tidy

CHUNK = 1 << 18
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Rows up to which a table of classes is sent to all tasks (some 60 bytes each); beyond, it is joined.
SEND_MOST = 200_000
#: Classes, and members of all its sets together, that meet in one group.
GROUP_MOST, GROUP_MEMBERS = 1024, 1 << 21
#: Rows of an Arrow batch of texts, and of sets that are compared.
SCANNED, COMPARED = 1000, 500
#: Times a family follows its anchor to that one's own.
HOPS = 3
#: Parts up to which all parts of a family meet.
PARTS_MOST = 32
#: A member that more texts than these hold moves one level back in the common order each.
LEVELS = (32, 256, 2048, 16384)


@dataclass(frozen=True)
class JoinParams:
    words: int = 4
    percent: int = 85
    hashes: int = 8
    agree: int = 2  # equal min-hashes that bring a class into the family of an anchor
    group: int = GROUP_MOST
    levels: tuple[int, ...] = LEVELS
    counted: float = 1.35  # the counted stretch of the hash range, in shares of the prefix
    small: int = 64  # sets of at most so many members are counted whole

    @property
    def limit(self) -> np.uint64:
        return np.uint64(int(min(0.999, self.counted * (1 - self.percent / 100)) * 2**64))


def shingle_sets(b: np.ndarray, offs: np.ndarray, words: int) -> list[np.ndarray]:
    """The sorted distinct member hashes of each text."""
    n, size = len(offs) - 1, len(b)
    empty = np.zeros(0, np.uint64)
    if not size:
        return [empty] * n
    blank = _BLANK[b]
    edge = np.ones(size, bool)
    edge[1:] = blank[1:] != blank[:-1]
    edge[offs[:-1][offs[:-1] < size]] = True
    starts = np.flatnonzero(edge)
    h = run_hashes(_LOWER[b], starts, np.diff(np.append(starts, size)))
    token = ~blank[starts]
    h, starts = h[token], starts[token]
    ends = np.searchsorted(starts, offs)
    mult = [np.uint64((0x9E3779B97F4A7C15 * (2 * k + 3) + 2 * k) & 0xFFFFFFFFFFFFFFFF | 1) for k in range(words)]
    with np.errstate(over="ignore"):
        long = max(0, len(h) - words + 1)
        s = np.full(long, np.uint64(words))
        for k in range(words):
            s = s + mixed(h[k : k + long] + np.uint64(k)) * mult[k]
        s = mixed(s)
        out = []
        for r in range(n):
            i, j = ends[r], ends[r + 1]
            if j - i >= words:
                out.append(np.unique(s[i : j - words + 1]))
            elif j > i:
                few = np.uint64(j - i)
                for k in range(j - i):
                    few = few + mixed(h[i + k : i + k + 1] + np.uint64(k))[0] * mult[k]
                out.append(mixed(np.array([few], np.uint64)))
            else:
                out.append(empty)
    return out


def _sets_of(batch, words):
    """(row in the batch, member hashes) of all rows."""
    buf, offs = flat(batch.column("text"))
    for i, j in slices(offs, CHUNK):
        for r, s in enumerate(shingle_sets(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i], words), i):
            yield r, s


def _digest(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


def summaries(documents: DataFrame, p: JoinParams) -> DataFrame:
    """doc_id, n, digest (of the set) and min-hashes of every row."""
    salts = mixed(np.arange(1, p.hashes + 1, dtype=np.uint64) * np.uint64(0x632BE59BD9B4E019))

    def least(sets: list[np.ndarray]) -> list[pa.Array]:
        """The min-hashes of some sets that aren't empty, one array a salt."""
        values, starts = np.concatenate(sets), np.cumsum([0, *[len(x) for x in sets[:-1]]])
        with np.errstate(over="ignore"):
            return [np.minimum.reduceat((values ^ salt) * np.uint64(0x9FB21C651E98DF25), starts).view(np.int64) for salt in salts]

    def job(batches):
        for batch in batches:
            n, digests, mins, held, size = [], [], [], [], 0
            for _, s in _sets_of(batch, p.words):
                n.append(len(s))
                digests.append(_digest(s))
                if len(s):
                    held.append(s)
                    size += len(s)
                if size > 1 << 18:
                    mins.append(least(held))
                    held, size = [], 0
            if held:
                mins.append(least(held))
            values = np.concatenate([np.stack(m, 1).ravel() for m in mins]) if mins else np.zeros(0, np.int64)
            ends = np.cumsum([0, *[p.hashes * (k > 0) for k in n]])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(digests, pa.binary()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(values))], ["doc_id", "n", "digest", "mins"])

    return texts(documents, binary=True).mapInArrow(tidy(job), "doc_id long, n long, digest binary, mins array<long>")


class BitFilter:
    """Membership of 64-bit values by three bits each in an array of bounded size; no false denial."""

    def __init__(self, log_bits: int):
        self.log = log_bits
        self.bits = np.zeros(1 << (log_bits - 3), np.uint8)

    def _places(self, h: np.ndarray):
        shift = np.uint64(64 - self.log)
        with np.errstate(over="ignore"):
            for m in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9):
                yield ((h * np.uint64(m)) >> shift).astype(np.int64)

    def add(self, h: np.ndarray) -> None:
        for at in self._places(h):
            np.bitwise_or.at(self.bits, at >> 3, (1 << (at & 7)).astype(np.uint8))

    def has(self, h: np.ndarray) -> np.ndarray:
        ok = np.ones(len(h), bool)
        for at in self._places(h):
            ok &= (self.bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 > 0
        return ok


def bit_filter(values: DataFrame, least_log: int = 16, most_log: int = 27) -> BitFilter:
    """A filter of one column of longs: arrays of at most 16 tasks, 16 MB at most each, joined on the driver one by one."""
    count = values.count()
    log = min(most_log, max(least_log, int(16 * max(count, 1)).bit_length()))

    def job(batches):
        mine = BitFilter(log)
        for batch in batches:
            mine.add(np.asarray(batch.column(0)).view(np.uint64))
        yield pa.RecordBatch.from_arrays([pa.array([mine.bits.tobytes()], pa.binary())], ["bits"])

    out = BitFilter(log)
    if count:
        for row in values.coalesce(16).mapInArrow(tidy(job), "bits binary").toLocalIterator():
            out.bits |= np.frombuffer(row["bits"], np.uint8)
    return out


class Chosen:
    """One row for each class that is asked for: rows whose doc_id is its representative's. Null ids are always read."""

    def __init__(self, reps: DataFrame):
        self.ids = bit_filter(reps.select("rep").where("rep IS NOT NULL"))

    def rows(self, batch) -> pa.RecordBatch:
        ids = batch.column("doc_id")
        return batch.filter(pa.array(ids.is_null().to_numpy(zero_copy_only=False) | self.ids.has(np.asarray(ids.fill_null(0)).view(np.uint64))))


def _once(chosen: Chosen, batches, words: int, seen_most: int = 100_000):
    """(set, digest) of chosen rows, a set that a task meets again left out."""
    seen: set[bytes] = set()
    for batch in batches:
        for _, s in _sets_of(chosen.rows(batch), words):
            if len(s):
                d = _digest(s)
                if d not in seen:
                    if len(seen) > seen_most:
                        seen.clear()
                    seen.add(d)
                    yield s, d


def _sent_if_few(df: DataFrame) -> DataFrame:
    """Sent to all tasks while it is small by count, else left to a shuffled join."""
    return F.broadcast(df) if df.limit(SEND_MOST + 1).count() <= SEND_MOST else df


@contextlib.contextmanager
def _batches_of(spark: SparkSession, rows: int):
    """Arrow batches of fewer rows while wide rows are compared."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def _packed(s: np.ndarray) -> bytes:
    """The upper 48 bits of each hash, six bytes each."""
    return (s >> np.uint64(16)).view(np.uint8).reshape(-1, 8)[:, :6].tobytes()


def _unpacked(b: np.ndarray) -> np.ndarray:
    wide = np.zeros((len(b) // 6, 8), np.uint8)
    wide[:, :6] = b.reshape(-1, 6)
    return wide.reshape(-1).view(np.uint64)


def fetched(documents: DataFrame, ends: DataFrame, routes: DataFrame, p: JoinParams) -> DataFrame:
    """The rows of `routes` (column digest) with the members of their classes; `ends` has digest and rep of all of them."""
    sent = documents.sparkSession.sparkContext.broadcast(Chosen(ends))

    def table(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, pa.binary()) for c in zip(*rows, strict=True)], ["digest", "members"])

    def job(batches):
        rows, size = [], 0
        for s, d in _once(sent.value, batches, p.words):
            rows.append((d, _packed(s)))
            size += len(rows[-1][1])
            if size > 1 << 22:
                yield table(rows)
                rows, size = [], 0
        if rows:
            yield table(rows)

    return texts(documents, binary=True).mapInArrow(tidy(job), "digest binary, members binary").join(_sent_if_few(routes), "digest")


def _grouped(batches, keys: list[str], rest: list[str]):
    """(key, rows of `rest` with unpacked members) of each group of sorted rows; a class that two rows gave counts once."""
    at, held, last = None, [], None
    for batch in batches:
        buf, offs = flat(batch.column("members"))
        cols = [batch.column(c).to_pylist() for c in (*keys, *rest)]
        for k, row in enumerate(zip(*cols, strict=True)):
            if row == last:
                continue
            last, key = row, row[: len(keys)]
            if key != at:
                if held:
                    yield at, held
                at, held = key, []
            held.append((*row[len(keys) :], _unpacked(buf[offs[k] : offs[k + 1]])))
    if held:
        yield at, held


class Sets:
    """Sets side by side, for overlaps of one with all."""

    def __init__(self, sets: list[np.ndarray]):
        self.sizes = np.array([len(x) for x in sets], np.int64)
        self.starts = np.cumsum(self.sizes) - self.sizes
        values, self.place = np.unique(np.concatenate(sets), return_inverse=True)
        self.mark = np.zeros(len(values), bool)

    def common(self, i: int) -> np.ndarray:
        mine = self.place[self.starts[i] : self.starts[i] + self.sizes[i]]
        self.mark[mine] = True
        out = np.add.reduceat(self.mark[self.place], self.starts, dtype=np.int64)
        self.mark[mine] = False
        return out

    def similar(self, i: int, common: np.ndarray, percent: int) -> np.ndarray:
        return 100 * common >= percent * (self.sizes + self.sizes[i] - common)


def group_links(digests: list[bytes], sets: list[np.ndarray], own: list[int], percent: int, whole: bool) -> list[tuple[bytes, bytes, int]]:
    """(a, b, common): links that close the components of a group, or with `whole` all its links; `own` is -1 for the anchor.

    Classes of one part are compared with each other and the anchor, those of two parts across.
    """
    x, out, k, own = Sets(sets), [], len(sets), np.array(own)
    anchor, cross = int(np.argmin(own)), len(np.unique(own)) > 2
    common = x.common(anchor)
    near = x.similar(anchor, common, percent)
    near[anchor] = True
    if not cross:
        out += [(digests[i], digests[anchor], int(common[i])) for i in np.flatnonzero(near) if i != anchor]
    root = np.where(near, anchor, np.arange(k))
    for i in range(k):
        if i == anchor or (near[i] and not whole):
            continue
        common = x.common(i)
        other = (own != own[i]) if cross else np.ones(k, bool)
        other[anchor] = False
        for t in np.flatnonzero(other & x.similar(i, common, percent)):
            if whole:
                if t < i:
                    out.append((digests[i], digests[t], int(common[t])))
            elif root[t] != root[i]:
                out.append((digests[i], digests[t], int(common[t])))
                root[root == root[i]] = root[t]
    return out


def family_links(documents: DataFrame, members: DataFrame, ends: DataFrame, p: JoinParams, scratch: Scratch, whole: bool) -> DataFrame:
    """a, b, common: links inside the groups of families; `members` has digest, anchor, lo, hi and own, the anchors in each group too."""
    keys = ["anchor", "lo", "hi"]

    def job(batches):
        for _, rows in _grouped(batches, keys, ["own", "digest"]):
            own, digests, sets = zip(*rows, strict=True)
            out = group_links(digests, sets, own, p.percent, whole)
            if out:
                yield _overlap_rows(out)

    found = fetched(documents, ends, members, p).repartition(*keys).sortWithinPartitions(*keys, "own", "digest")
    with _batches_of(documents.sparkSession, COMPARED):
        return scratch.staged(found.select(*keys, "own", "digest", "members").mapInArrow(tidy(job), OVERLAPS), "family-links")


OVERLAPS = "a binary, b binary, common long"


def _overlap_rows(rows: list[tuple[bytes, bytes, int]]) -> pa.RecordBatch:
    a, b, common = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(a, pa.binary()), pa.array(b, pa.binary()), pa.array(common, pa.int64())], ["a", "b", "common"])


def overlaps(documents: DataFrame, classes: DataFrame, pairs: DataFrame, p: JoinParams, scratch: Scratch) -> DataFrame:
    """a, b, common: the sizes of the overlaps of pairs (a, b) of class digests, by full comparison.

    A pair belongs to the end that has more pairs, its hub; a hub's pairs are dealt to groups of bounded size, and each group
    gets the hub's set and every leaf's set once.
    """
    pairs = scratch.staged(pairs.select("a", "b"), "pairs")
    ends = pairs.select(F.col("a").alias("digest")).unionAll(pairs.select("b")).groupBy("digest").agg(F.count(F.lit(1)).alias("deg"))
    ends = scratch.staged(ends.join(classes.select("digest", "rep"), "digest"), "ends")
    deg = ends.select("digest", "deg")
    both = pairs.join(deg.select(F.col("digest").alias("a"), F.col("deg").alias("da")), "a").join(deg.select(F.col("digest").alias("b"), F.col("deg").alias("db")), "b")
    first = F.col("da") >= F.col("db")
    both = both.select(F.when(first, F.col("a")).otherwise(F.col("b")).alias("hub"), F.when(first, F.col("b")).otherwise(F.col("a")).alias("leaf"), first.alias("straight"), F.greatest("da", "db").alias("deg"))
    parts = F.ceil(F.col("deg") / p.group).cast("int")
    leaves = both.select(F.col("leaf").alias("digest"), "hub", F.pmod(F.xxhash64("leaf"), parts).cast("int").alias("part"), F.lit(1).alias("side"), "straight")
    hubs = both.select("hub", parts.alias("parts")).distinct().select(F.col("hub").alias("digest"), "hub", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(0).alias("side"), F.lit(True).alias("straight"))
    routes = scratch.staged(leaves.unionByName(hubs), "routes")

    def job(batches):
        for (hub, _), rows in _grouped(batches, ["hub", "part"], ["side", "digest", "straight"]):
            if rows[0][0] != 0:
                raise RuntimeError("a group came without its hub")
            big, out = rows[0][3], []
            for _, d, straight, s in rows[1:]:
                x, y = (s, big) if len(s) <= len(big) else (big, s)
                common = int(np.count_nonzero(y[np.minimum(np.searchsorted(y, x), len(y) - 1)] == x))
                out.append((hub, d, common) if straight else (d, hub, common))
            if out:
                yield _overlap_rows(out)

    order = ["hub", "part", "side", "digest", "straight"]
    dealt = fetched(documents, ends, routes, p).repartition("hub", "part").sortWithinPartitions(*order)
    with _batches_of(documents.sparkSession, COMPARED):
        return scratch.staged(dealt.select(*order, "members").mapInArrow(tidy(job), OVERLAPS), "overlaps")


def similar(common: Column, na: Column, nb: Column, percent: int) -> Column:
    return 100 * common >= percent * (na + nb - common)


def families(classes: DataFrame, p: JoinParams) -> DataFrame:
    """digest, anchor, part, parts: for each class the anchor that it shares most min-hashes with (the smallest class of a bucket is its anchor).

    A family is dealt to as many parts as its size asks for; classes without an anchor have no row.
    """
    keys = classes.select("digest", F.posexplode("mins").alias("i", "key"))
    anchors = keys.groupBy("i", "key").agg(F.min("digest").alias("anchor"), F.count(F.lit(1)).alias("m")).where("m > 1").select("i", "key", "anchor")
    shared = keys.join(anchors, ["i", "key"]).where(F.col("digest") != F.col("anchor")).groupBy("digest", "anchor").agg(F.count(F.lit(1)).alias("m")).where(F.col("m") >= p.agree)
    best = shared.groupBy("digest").agg(F.max(F.struct("m", "anchor")).alias("x")).select("digest", "x.anchor")
    # An anchor that has an anchor itself brings its family along; anchors only ever get smaller.
    up = _sent_if_few(best.select(F.col("digest").alias("anchor"), F.col("anchor").alias("up")))
    for _ in range(HOPS):
        best = best.join(up, "anchor", "left").select("digest", F.coalesce("up", "anchor").alias("anchor"))
    best = best.join(classes.select("digest", "n"), "digest")
    size = best.groupBy("anchor").agg(F.greatest(F.ceil(F.count(F.lit(1)) / p.group), F.ceil(F.sum("n") / GROUP_MEMBERS)).cast("int").alias("parts"))
    return best.join(size, "anchor").select("digest", "anchor", F.pmod(F.xxhash64("digest"), F.col("parts")).cast("int").alias("part"), "parts")


def meetings(groups: DataFrame) -> DataFrame:
    """digest, anchor, lo, hi, own: which groups a class is sent to: each two parts of a family, unless it has more than PARTS_MOST.

    Of a larger family only the parts themselves meet; the index finds what lies across. The anchor is in each group, its own is -1.
    """
    i, j = F.col("part"), F.col("j")
    others = F.when(F.col("parts") <= PARTS_MOST, F.sequence(F.lit(0), F.col("parts") - 1)).otherwise(F.array(i))
    sent = groups.withColumn("j", F.explode(others)).select("digest", "anchor", F.least(i, j).alias("lo"), F.greatest(i, j).alias("hi"), i.alias("own"))
    return sent.unionByName(sent.select(F.col("anchor").alias("digest"), "anchor", "lo", "hi", F.lit(-1).alias("own")).distinct())


def components(links: DataFrame, scratch: Scratch, most_rounds: int = 60) -> DataFrame:
    """node, root: closed over links (a, b) by hooking roots to their smallest neighbour and jumping; smallest node is root."""
    nodes = links.select(F.col("a").alias("node")).union(links.select("b")).distinct()
    labels = scratch.staged(nodes.withColumn("root", F.col("node")), "labels")
    open_ = scratch.staged(links.select("a", "b").where("a <> b").distinct(), "open")
    for _ in range(most_rounds):
        both = open_.union(open_.select("b", "a"))
        hook = both.groupBy("a").agg(F.min("b").alias("up")).where("up < a").select(F.col("a").alias("node"), "up")
        for _ in range(3):  # each jump doubles the length of the hooked chains that are closed
            nxt = hook.select(F.col("node").alias("up"), F.col("up").alias("top"))
            hook = hook.join(nxt, "up", "left").select("node", F.coalesce("top", "up").alias("up"))
        hook = scratch.staged(hook, "hook")
        to = hook.withColumnRenamed("node", "root")
        before = labels, open_
        labels = scratch.staged(labels.join(to, "root", "left").select("node", F.coalesce("up", "root").alias("root")), "labels")
        moved = open_.join(hook.select(F.col("node").alias("a"), F.col("up").alias("ua")), "a", "left").join(hook.select(F.col("node").alias("b"), F.col("up").alias("ub")), "b", "left")
        open_ = scratch.staged(moved.select(F.coalesce("ua", "a").alias("a"), F.coalesce("ub", "b").alias("b")).where("a <> b").distinct(), "open")
        scratch.drop(hook, *before)
        if open_.isEmpty():
            return labels
    raise RuntimeError("components didn't close")


def counted_members(documents: DataFrame, chosen, p: JoinParams) -> DataFrame:
    """h, n: in how many classes each counted member occurs, if in two or more."""
    limit = p.limit

    def job(batches):
        held, size = [], 0
        for s, _ in _once(chosen.value, batches, p.words):
            held.append(s if len(s) <= p.small else s[: np.searchsorted(s, limit)])
            size += len(held[-1])
            if size > 1 << 20:
                yield _tally(held)
                held, size = [], 0
        if held:
            yield _tally(held)

    rows = texts(documents, binary=True).mapInArrow(tidy(job), "h long, n long")
    return rows.groupBy("h").agg(F.sum("n").alias("n")).where("n > 1")


def _tally(held: list[np.ndarray]) -> pa.RecordBatch:
    h, n = np.unique(np.concatenate(held), return_counts=True)
    return pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(n)], ["h", "n"])


def prefixes(sets: list[np.ndarray], multi: BitFilter, levels: list[BitFilter], p: JoinParams) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(set, member, place in the common order) of the members of the sets' prefixes that others may hold, for many sets at once.

    Order: members of the stretch that no other text holds, those held by few, members beyond the stretch, then by level.
    """
    n = np.array([len(s) for s in sets], np.int64)
    s, which = np.concatenate(sets), np.repeat(np.arange(len(sets)), n)
    inside = s < p.limit
    level = np.where(inside, 1, 2).astype(np.int8)
    at = np.flatnonzero(inside)
    level[at[~multi.has(s[at])]] = 0
    rest = np.flatnonzero(level)
    for i, held in enumerate(levels):
        rest = rest[held.has(s[rest])]  # a member that more texts than the next bound hold is in this filter too
        level[rest] = 3 + i
    order = np.lexsort((level, which))  # stable: members of a level stay in the order of their hashes
    place = np.arange(len(s)) - np.repeat(np.cumsum(n) - n, n)
    first = n - -(-p.percent * n // 100) + 1
    keep = (place < first[which]) & (level[order] > 0)
    return which[keep], s[order[keep]], place[keep]


def indexed(documents: DataFrame, chosen, multi: BitFilter, levels: list[BitFilter], p: JoinParams) -> DataFrame:
    """token, digest, n, at: the index rows of each class, `at` the member's place in the common order."""
    sent = documents.sparkSession.sparkContext.broadcast((multi, levels))

    def table(sets, digests):
        which, token, place = prefixes(sets, *sent.value, p)
        size = np.array([len(s) for s in sets], np.int32)
        return pa.RecordBatch.from_arrays([pa.array(token.view(np.int64)), pa.array(digests, pa.binary()).take(pa.array(which)), pa.array(size[which]), pa.array(place.astype(np.int32))], ["token", "digest", "n", "at"])

    def job(batches):
        sets, digests, size = [], [], 0
        for s, d in _once(chosen.value, batches, p.words):
            sets.append(s)
            digests.append(d)
            size += len(s)
            if size > 1 << 18:
                yield table(sets, digests)
                sets, digests, size = [], [], 0
        if sets:
            yield table(sets, digests)

    return texts(documents, binary=True).mapInArrow(tidy(job), "token long, digest binary, n int, at int")


def candidate_pairs(index: DataFrame, p: JoinParams) -> DataFrame:
    """a, b, na, nb (na >= nb): pairs of classes of different components and groups that share an index member within the bounds of size and place."""
    step = float(np.log(100 / p.percent))
    block = lambda n: F.floor(F.log(n.cast("double")) / F.lit(step)).cast("int")
    n, at = F.col("n").cast("long"), F.col("at").cast("long")
    least = F.ceil(n * F.lit(p.percent) / F.lit(100)).cast("long")
    most = F.least(n, F.expr(f"(CAST(n AS BIGINT) - at) * {100 + p.percent} DIV {p.percent} - n"))
    large = index.withColumn("least", least).withColumn("most", most).where("most >= least")
    large = large.select("token", F.col("digest").alias("a"), F.col("comp").alias("ca"), F.col("met").alias("ma"), F.col("n").alias("na"), F.col("at").alias("pa"), F.explode(F.sequence(block(F.col("least")), block(F.col("most")))).alias("block"))
    small = index.where((n - at) * F.lit(100 + p.percent) >= 2 * p.percent * n)
    small = small.select("token", F.col("digest").alias("b"), F.col("comp").alias("cb"), F.col("met").alias("mb"), F.col("n").alias("nb"), F.col("at").alias("pb"), block(F.col("n")).alias("block"))
    na, nb = F.col("na").cast("long"), F.col("nb").cast("long")
    met = large.join(small, ["token", "block"]).where(
        (F.col("ca") != F.col("cb")) & (F.col("ma") != F.col("mb")) & ((na > nb) | ((na == nb) & (F.col("a") < F.col("b")))) & (100 * nb >= p.percent * na) & (F.least(na - F.col("pa"), nb - F.col("pb")) * F.lit(100 + p.percent) >= p.percent * (na + nb))
    )
    return met.select("a", "b", "na", "nb").distinct()


def derived(pairs: DataFrame, star: DataFrame, answers, p: JoinParams, scratch: Scratch) -> DataFrame:
    """a, b, na, nb and `linked`: true, false, or null where the anchors' answers leave it open.

    `star` has digest, anchor, common and the anchor's size; `answers(pairs)` gives the overlaps of anchor pairs. A set without
    an anchor is its own, so its pairs with others of the kind are decided.
    """
    side = lambda k: star.select(F.col("digest").alias(k), F.col("anchor").alias(f"{k}_anchor"), F.col("common").alias(f"{k}_common"), F.col("size").alias(f"{k}_size"))
    x = pairs.join(_sent_if_few(side("a")), "a", "left").join(_sent_if_few(side("b")), "b", "left")
    for k in "ab":
        x = x.withColumn(f"{k}_more", F.coalesce(F.col(f"n{k}") - F.col(f"{k}_common"), F.lit(0))).withColumn(f"{k}_less", F.coalesce(F.col(f"{k}_size") - F.col(f"{k}_common"), F.lit(0))).withColumn(f"{k}_anchor", F.coalesce(f"{k}_anchor", k))
    lo, hi = F.least("a_anchor", "b_anchor"), F.greatest("a_anchor", "b_anchor")
    x = scratch.staged(x.withColumn("lo", lo).withColumn("hi", hi), "derivable")
    known = answers(x.where("lo <> hi").select(F.col("lo").alias("a"), F.col("hi").alias("b")).distinct())
    x = x.join(known.select(F.col("a").alias("lo"), F.col("b").alias("hi"), F.col("common").alias("met")), ["lo", "hi"], "left")
    # Of two sets of one anchor, the anchor's overlap with itself is its size.
    met = F.coalesce("met", "a_size", "b_size")
    same = F.col("lo") == F.col("hi")
    both = F.least(F.coalesce("a_common", "a_size", "b_size"), F.coalesce("b_common", "a_size", "b_size"), F.col("na"), F.col("nb")) + F.least("a_more", "b_more")
    most = F.least(F.when(same, both).otherwise(met + F.col("a_more") + F.col("b_more")), F.col("na"), F.col("nb"))
    least = F.greatest(met - F.col("a_less") - F.col("b_less"), F.lit(0))
    linked = F.when(similar(least, F.col("na"), F.col("nb"), p.percent), F.lit(True)).when(~similar(most, F.col("na"), F.col("nb"), p.percent), F.lit(False))
    return scratch.staged(x.select("a", "b", "na", "nb", linked.alias("linked")), "derived")


class Join:
    """The steps of the join over one table; with `whole` for all links, else for components. `scratch` has what they staged."""

    def __init__(self, documents: DataFrame, p: JoinParams, whole: bool = False):
        self.documents, self.p = documents, p
        self.scratch = Scratch(documents.sparkSession)
        with _batches_of(documents.sparkSession, SCANNED):
            self.rows = self.scratch.staged(summaries(documents, p), "rows")
        held = self.rows.where("n > 0").groupBy("digest").agg(F.min("doc_id").alias("rep"), F.max("n").alias("n"), F.max("mins").alias("mins"))
        self.classes = self.scratch.staged(held, "classes")
        self.groups = self.scratch.staged(families(self.classes, p), "families")
        members = self.scratch.staged(meetings(self.groups), "members")
        ends = members.select("digest").distinct().join(self.classes.select("digest", "rep"), "digest")
        self.near = family_links(documents, members, self.scratch.staged(ends, "ends"), p, self.scratch, whole)

    def _overlaps(self, pairs: DataFrame) -> DataFrame:
        return overlaps(self.documents, self.classes, pairs, self.p, self.scratch)

    def _linked(self, pairs: DataFrame) -> DataFrame:
        """a, b of the similar ones among pairs with sizes na and nb."""
        x = self._overlaps(pairs).join(pairs, ["a", "b"])
        return self.scratch.staged(x.where(similar(F.col("common"), F.col("na"), F.col("nb"), self.p.percent)).select("a", "b"), "links")

    def candidates(self, comp: DataFrame | None) -> DataFrame:
        """Pairs that the index leaves, of classes of different groups and, with components (node, root), of different ones."""
        p, spark = self.p, self.documents.sparkSession
        chosen = spark.sparkContext.broadcast(Chosen(self.classes))
        with _batches_of(spark, SCANNED):
            counts = self.scratch.staged(counted_members(self.documents, chosen, p), "counts")
        multi = bit_filter(counts.select("h"))
        levels = [bit_filter(counts.where(F.col("n") > k).select("h")) for k in p.levels]
        self.scratch.drop(counts)
        label = self.groups.select("digest", F.when(F.col("parts") <= PARTS_MOST, F.xxhash64("anchor")).otherwise(F.xxhash64("anchor", "part")).alias("met"))
        if comp is None:
            label = label.withColumn("comp", F.lit(None).cast("long"))
        else:
            label = label.join(comp.select(F.col("node").alias("digest"), F.xxhash64("root").alias("comp")), "digest", "full_outer")
        own = F.xxhash64("digest")
        index = indexed(self.documents, chosen, multi, levels, p).join(_sent_if_few(self.scratch.staged(label, "labels")), "digest", "left")
        index = index.select("token", "digest", "n", "at", F.coalesce("met", own).alias("met"), F.coalesce("comp", own).alias("comp"))
        with _batches_of(spark, SCANNED):
            index = self.scratch.staged(index, "index")
        found = self.scratch.staged(candidate_pairs(index, p), "candidates")
        self.scratch.drop(index)
        return found

    def answers(self) -> DataFrame:
        """digest, anchor, common, size: one near set of each class that a family linked, and their overlap."""
        one = self.near.groupBy(F.col("a").alias("digest")).agg(F.max(F.struct("common", "b")).alias("x")).select("digest", F.col("x.b").alias("anchor"), "x.common")
        return self.scratch.staged(one.join(self.classes.select(F.col("digest").alias("anchor"), F.col("n").alias("size")), "anchor"), "answers")

    def derived(self, pairs: DataFrame) -> DataFrame:
        return derived(pairs, self.answers(), self._overlaps, self.p, self.scratch)

    def closed(self) -> DataFrame:
        """node, root: components of all links between classes."""
        known = components(self.near, self.scratch)
        found = self.derived(self.candidates(known))
        links = self.near.select("a", "b").unionAll(found.where("linked").select("a", "b"))
        known = components(links, self.scratch)
        # What the near sets' answers leave open matters only between components.
        root = lambda k: known.select(F.col("node").alias(k), F.col("root").alias(f"r{k}"))
        rest = found.where("linked IS NULL").join(root("a"), "a", "left").join(root("b"), "b", "left").where("NOT coalesce(ra, a) <=> coalesce(rb, b)")
        rest = self.scratch.staged(rest.select("a", "b", "na", "nb"), "rest")
        if rest.isEmpty():
            return known
        return components(links.unionAll(self._linked(rest)), self.scratch)

    def links(self) -> DataFrame:
        """a, b: all links between classes, smaller digest first."""
        found = self.derived(self.candidates(None))
        more = self._linked(found.where("linked IS NULL").select("a", "b", "na", "nb"))
        every = self.near.select("a", "b").unionAll(found.where("linked").select("a", "b")).unionAll(more)
        return every.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def joined(documents: DataFrame, p: JoinParams = JoinParams()) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable by links), one row per input row."""
    join = Join(documents, p)
    closed = join.closed().select(F.col("node").alias("digest"), F.col("root").alias("comp"))
    named = join.rows.select("doc_id", "n", "digest").join(closed, "digest", "left").withColumn("comp", F.coalesce("comp", "digest"))
    least = named.where("n > 0").groupBy("comp").agg(F.min("doc_id").alias("component_id"))
    out = named.join(least, "comp", "left")
    out = out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))
    return join.scratch.last(out, "components")


def linked_classes(documents: DataFrame, p: JoinParams = JoinParams()) -> tuple[DataFrame, DataFrame]:
    """(members: doc_id, n_shingles, class_id; links: a, b of class ids), all links between different sets.

    Texts of equal sets share a class, so their links aren't spelled out; those between the sets of a large group of near copies
    are, and grow with its square.
    """
    join = Join(documents, p, whole=True)
    links = join.scratch.last(join.links(), "links", keep=[join.rows])
    return join.rows.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("digest")).alias("class_id")), links


def kept_one(documents: DataFrame, p: JoinParams = JoinParams()) -> DataFrame:
    """One document of each group stays, the one with the smallest doc_id; all columns are kept.

    Rows whose doc_id is null, or that have no words, stay.
    """
    gone = joined(documents, p).where(F.col("component_id") < F.col("doc_id")).select("doc_id").distinct()
    return documents.join(gone, "doc_id", "left_anti").select(documents.columns)


def op7_shingle_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joined(spark.read.parquet(f"{sf_dir}/documents.parquet"))
