"""Best-fit packing of token pieces into fixed-length sequences, improved by swaps.

Pieces shorter than a sequence are dealt by hash into groups of bounded size. A group is packed best fit from long to
short; then a local search takes documents of the emptiest bin and moves them into others, or exchanges one for
one, two for one and one for two, whenever that raises the sum of squared fills, until bins empty or nothing
helps. Bins that still have room return to the pool and are packed again with those of other groups, until one
group is left or no bin is saved. Longer documents are cut into whole sequences; only their first piece may be shorter.

Cases: a null or empty text is the end id alone (length 1); repeated rows and equal lengths are packed row by row;
an empty table gives no piece.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcomm.llm.bpe import GENERATION, closed, opened, tokenizer_path
from localcomm.llm.common import staged, texts, tidy

CAPACITY = 2048
GROUP = 4000
ROUNDS = 4
TASKS_MOST = 20_000
PIECES = "row long, doc_id long, piece int, start long, length long, ids_crc32 long"


def best_fit(lengths: list[int], capacity: int) -> list[list[int]]:
    """Bins of item numbers: each item, from long to short, goes where it leaves the least room."""
    bins: list[list[int]] = []
    with_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    some = 0  # bit r is set while a bin with room r is known
    for k in sorted(range(len(lengths)), key=lambda k: (-lengths[k], k)):
        size = lengths[k]
        fits = some >> size
        if fits:
            room = size + ((fits & -fits).bit_length() - 1)
            b = with_room[room].pop()
            if not with_room[room]:
                some ^= 1 << room
            bins[b].append(k)
            room -= size
        else:
            b, room = len(bins), capacity - size
            bins.append([k])
        with_room[room].append(b)
        some |= 1 << room
    return bins


def exchanged(lengths: list[int], bins: list[list[int]], capacity: int, effort: int = 200_000) -> list[list[int]]:
    """Raise the sum of squared fills by moves and swaps out of the emptiest bin until no bin can be emptied."""
    bins = [list(b) for b in bins]
    fill = [sum(lengths[k] for k in b) for b in bins]
    open_ = {b for b in range(len(bins)) if fill[b] < capacity}
    order = sorted(open_, key=lambda b: fill[b])
    room = sum(capacity - fill[b] for b in open_)
    for a in order:
        if a not in open_ or not bins[a]:
            continue
        while bins[a] and effort > 0:
            if room - (capacity - fill[a]) < fill[a]:
                return [b for b in bins if b]  # all the room elsewhere can't take this bin
            move = _best_exchange(lengths, bins, fill, open_, a, capacity)
            effort -= len(open_)
            if move is None:
                break
            give, take, t = move
            for k in give:
                bins[a].remove(k)
            for k in take:
                bins[t].remove(k)
            bins[t] += give
            bins[a] += take
            d = sum(lengths[k] for k in give) - sum(lengths[k] for k in take)
            fill[a] -= d
            fill[t] += d
            if fill[t] == capacity:
                open_.discard(t)
        if not bins[a]:
            open_.discard(a)
            room -= capacity
    return [b for b in bins if b]


def _best_exchange(lengths, bins, fill, open_, a, capacity):
    """The exchange of the highest gain in squared fill: what to give from bin a, what to take from bin t."""
    own = sorted(bins[a], key=lambda k: -lengths[k])[:24]
    singles = [((k,), lengths[k]) for k in own]
    pairs = [((own[i], own[j]), lengths[own[i]] + lengths[own[j]]) for i in range(min(8, len(own))) for j in range(i)]
    best, move = 0, None
    for t in open_:
        if t == a or fill[t] < fill[a]:
            continue
        free, apart = capacity - fill[t], fill[t] - fill[a]
        if (free + apart) * free <= best:
            continue  # even filling it up would gain less
        theirs = sorted(((lengths[k], k) for k in bins[t]))[:24]
        sizes = [x[0] for x in theirs]
        for gives, s in singles + pairs:
            if s <= free:
                if (apart + s) * s > best:
                    best, move = (apart + s) * s, (list(gives), [], t)
            else:
                i = bisect_left(sizes, s - free)
                if i < len(sizes) and sizes[i] < s and (g := (apart + s - sizes[i]) * (s - sizes[i])) > best:
                    best, move = g, (list(gives), [theirs[i][1]], t)
        for gives, s in singles:  # one for two
            for i in range(min(8, len(theirs))):
                j = bisect_left(sizes, s - free - sizes[i], i + 1)
                if j < len(sizes) and 0 < (d := s - sizes[i] - sizes[j]) <= free and (apart + d) * d > best:
                    best, move = (apart + d) * d, (list(gives), [theirs[i][1], theirs[j][1]], t)
    return move


def packed(lengths: list[int], capacity: int = CAPACITY) -> list[list[int]]:
    return exchanged(lengths, best_fit(lengths, capacity), capacity)


def pieces(documents: DataFrame, capacity: int = CAPACITY, tokenizer: str | None = None, end_id: int = 0, cached_words: int = GENERATION, keep: bool = True) -> DataFrame:
    """Pieces of every document in tokens, with a checksum of their ids; `row` tells apart rows that share a doc_id.

    Without `keep` a task forgets the tokenizer when it ends, for workers that need the memory for other stages.
    """
    path = tokenizer or tokenizer_path()

    def job(batches):
        enc, tail = opened(path, cached_words), np.array([end_id], "<u4").tobytes()
        row = TaskContext.get().partitionId() << 33
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part, out = batch.slice(lo, 512), []
                for doc_id, raw in zip(part.column("doc_id").to_pylist(), enc.encode(part.column("text").to_pylist()), strict=True):
                    raw += tail
                    n = len(raw) // 4
                    first = n % capacity or capacity
                    for k, at in enumerate([0, *range(first, n, capacity)]):
                        size = first if k == 0 else capacity
                        out.append((row, doc_id, k, at, size, zlib.crc32(raw[4 * at : 4 * (at + size)])))
                    row += 1
                cols = list(zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int32() if i == 2 else pa.int64()) for i, c in enumerate(cols)], [x.split()[0] for x in PIECES.split(", ")])
        if not keep:
            del enc
            closed(path, cached_words)

    return texts(documents).mapInArrow(tidy(job), PIECES)


def _packer(capacity: int, turn: int, final: bool):
    """Packs one group; bins with more room than 1/256 are loose unless this round is the last."""

    def job(frame: pd.DataFrame) -> pd.DataFrame:
        lengths = frame["length"].tolist()
        which, offset, loose = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64), np.zeros(len(lengths), bool)
        for b, held in enumerate(packed(lengths, capacity)):
            at = 0
            for k in held:
                which[k], offset[k] = b, at
                at += lengths[k]
            if at < capacity - capacity // 256 and not final:
                loose[held] = True
        key = (turn << 58) + (int(frame["g"].iloc[0]) << 24)
        return pd.DataFrame({"row": frame["row"], "piece": frame["piece"], "length": frame["length"], "sequence_id": which + key, "offset": offset, "loose": loose})

    return job


def assigned(items: DataFrame, capacity: int = CAPACITY, group: int = GROUP, rounds: int = ROUNDS) -> DataFrame:
    """row, piece, sequence_id and offset of pieces shorter than a sequence."""
    pool, done, last = items.select("row", "piece", "length"), [], None
    for turn in range(rounds):
        n = pool.count()
        if not n:
            break
        if last is not None and n > 0.97 * last:
            break
        groups = -(-n // group)
        final = groups == 1 or turn == rounds - 1

        dealt = pool.withColumn("g", F.pmod(F.xxhash64("row", "piece", F.lit(turn)), F.lit(groups)))
        dealt = dealt.repartition(min(groups, TASKS_MOST), "g")  # a group is little to read and much to do: a count of our own keeps Spark from gathering them
        out = staged(dealt.groupBy("g").applyInPandas(_packer(capacity, turn, final), "row long, piece int, length long, sequence_id long, offset long, loose boolean"), f"packed-{turn}")
        done.append(out)
        pool, last = out.where("loose").select("row", "piece", "length"), n
    if not done:
        return items.select("row", "piece", F.lit(0).cast("long").alias("sequence_id"), F.lit(0).cast("long").alias("offset")).limit(0)
    # What a later round packed again leaves the earlier round.
    kept = [d if i == len(done) - 1 else d.where("NOT loose") for i, d in enumerate(done)]
    out = kept[0]
    for d in kept[1:]:
        out = out.unionByName(d)
    return out.select("row", "piece", "sequence_id", "offset")


def packed_documents(documents: DataFrame, capacity: int = CAPACITY, tokenizer: str | None = None, cached_words: int = GENERATION, keep: bool = True) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    cut = staged(pieces(documents, capacity, tokenizer, cached_words=cached_words, keep=keep), "pieces")
    short, whole = cut.where(F.col("length") < capacity), cut.where(F.col("length") == capacity)
    spots = assigned(short, capacity)
    columns = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    full = whole.withColumn("sequence_id", F.monotonically_increasing_id() + F.lit(1 << 62)).withColumn("offset", F.lit(0).cast("long"))
    return short.join(spots, ["row", "piece"]).select(columns).unionByName(full.select(columns))


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
