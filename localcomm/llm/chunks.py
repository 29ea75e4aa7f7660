"""Content-addressed store of token ids.

A rolling hash over the ids cuts each document's stream into chunks, so that equal passages give equal chunks
wherever they start. A scanning task keeps each chunk it meets once in a staging pack; the digests of all tasks are
then reduced to one owner each, and packs are rewritten with the owned chunks only, so the store holds every
chunk once while the chunks of a document stay near each other. A recipe per document lists its chunks; recipes lie
in ascending doc_id order in a table whose partitions carry a Merkle root each; readers check every chunk's digest
and every document's root.

Cases: a null or empty text is the end id alone; equal documents share all chunks; rows that repeat a doc_id keep a
recipe each, next to each other; a null doc_id sorts first; an empty table gives an empty store.
"""

from __future__ import annotations

import hashlib
import zlib
from collections import OrderedDict
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcomm.llm.bpe import opened, tokenizer_path
from localcomm.llm.common import dropped, mixed, new_folder, staged, texts
from localcomm.llm.files import Reader, Roller


@dataclass(frozen=True)
class StoreParams:
    tokenizer: str | None = None
    end_id: int = 0
    mask_bits: int = 10
    least: int = 128
    most: int = 8192
    pack_bytes: int = 64 << 20
    window: int = 16


_TABLE = mixed(np.arange(1, 1 + (1 << 18), dtype=np.uint64))


def gear(ids: np.ndarray, window: int = 16) -> np.ndarray:
    """A rolling hash of the last `window` ids at each place, built by doubling the window.

    Streams may be hashed end to end: a cut lies at least `least` ids into a stream, beyond the reach of the one before.
    """
    with np.errstate(over="ignore"):
        h, span = _TABLE[ids & 0x3FFFF], 1
        while span < window:
            moved = np.zeros_like(h)
            moved[span:] = h[:-span] << np.uint64(span)
            h, span = h + moved, 2 * span
    return h


def cuts(hashes: np.ndarray, params: StoreParams) -> list[int]:
    """Ends of the chunks of one document."""
    n, out, at = len(hashes), [], 0
    marks = np.flatnonzero((hashes >> np.uint64(64 - params.mask_bits)) == 0) + 1
    k = 0
    while at < n:
        k = int(np.searchsorted(marks, at + params.least))
        end = int(marks[k]) if k < len(marks) else n
        end = min(end, at + params.most, n)
        out.append(end)
        at = end
    return out


def digest(raw: bytes) -> bytes:
    return hashlib.blake2b(raw, digest_size=16).digest()


def merkle(leaves: list[bytes]) -> bytes:
    """The root over digests; a last one without a partner goes up as it is."""
    level = leaves or [digest(b"")]
    while len(level) > 1:
        level = [digest(b"\1" + level[i] + level[i + 1]) if i + 1 < len(level) else level[i] for i in range(0, len(level), 2)]
    return level[0]


STAGE = "row long, doc_id long, n_tokens long, root binary, chunks array<struct<digest binary, pack string, at long, size int, ids int>>"


def staged_chunks(documents: DataFrame, folder: str, params: StoreParams) -> DataFrame:
    """Encode, cut and write staging packs; one row per document with its chunks."""
    path = params.tokenizer or tokenizer_path()

    def job(batches):
        enc, roll, seen = opened(path), Roller(folder, params.pack_bytes, ".ids"), {}
        zipper = zstandard.ZstdCompressor(level=1, write_content_size=True)
        small = enc.tok.get_vocab_size() <= 1 << 16
        tail = np.array([params.end_id], "<u4").tobytes()
        row = TaskContext.get().partitionId() << 33
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                raws = [raw + tail for raw in enc.encode(part.column("text").to_pylist())]
                if not raws:
                    continue
                ids = np.frombuffer(b"".join(raws), "<u4")
                hashes, width = gear(ids, params.window), 2 if small else 4
                kept = (ids.astype("<u2") if small else ids).tobytes()
                digests, wheres, counts, held, sizes, roots, base = [], [], [], [], [], [], 0
                for raw in raws:
                    n = len(raw) // 4
                    at, mine = 0, len(digests)
                    for end in cuts(hashes[base : base + n], params):
                        plain = kept[width * (base + at) : width * (base + end)]
                        key = digest(plain)
                        where = seen.get(key)
                        if where is None:
                            if roll.full:
                                roll.close()
                            packed = zipper.compress(plain)
                            where = seen[key] = (*roll.write(packed), len(packed))
                        digests.append(key)
                        wheres.append(where)
                        counts.append(end - at)
                        at = end
                    base += n
                    sizes.append(n)
                    held.append(len(digests))
                    roots.append(merkle(digests[mine:]))
                if len(seen) > 400_000:
                    seen.clear()  # a chunk met again is staged again; owners are settled over all tasks later
                packs, ats, lengths = zip(*wheres, strict=True)
                chunks = pa.StructArray.from_arrays([pa.array(digests, pa.binary()), pa.array(packs), pa.array(ats, pa.int64()), pa.array(lengths, pa.int32()), pa.array(counts, pa.int32())], ["digest", "pack", "at", "size", "ids"])
                rows = np.arange(row, row + len(raws))
                row += len(raws)
                yield pa.RecordBatch.from_arrays([pa.array(rows), part.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(roots, pa.binary()), pa.ListArray.from_arrays(pa.array([0, *held], pa.int32()), chunks)], ["row", "doc_id", "n_tokens", "root", "chunks"])
        roll.close()

    return texts(documents).mapInArrow(job, STAGE)


def compacted(owners: DataFrame, folder: str, params: StoreParams) -> DataFrame:
    """Copy owned chunks, pack by pack in order, into the final packs."""

    def job(batches):
        reader, roll = Reader(), Roller(folder, params.pack_bytes, ".pack")
        for batch in batches:
            digests, packs, ats, sizes = (batch.column(c).to_pylist() for c in ("digest", "pack", "at", "size"))
            where = []
            for pack, at, size in zip(packs, ats, sizes, strict=True):
                if roll.full:
                    roll.close()
                where.append(roll.write(reader.read(pack, at, size)))
            if where:
                yield pa.RecordBatch.from_arrays([pa.array(digests, pa.binary()), pa.array([w[0] for w in where]), pa.array([w[1] for w in where], pa.int64()), pa.array(sizes, pa.int32())], ["digest", "pack", "at", "size"])
        roll.close()

    ordered = owners.repartition(F.col("pack")).sortWithinPartitions("pack", "at")
    return ordered.mapInArrow(job, "digest binary, pack string, at long, size int")


RECIPE = "doc_id long, row long, n_tokens long, root binary, chunks array<struct<digest binary, pack string, at long, size int, ids int>>"


@dataclass
class Store:
    """Recipes in doc_id order (with `part` and `start_in_part`), one manifest row per part, the owned chunks."""

    recipes: DataFrame
    manifest: DataFrame
    chunks: DataFrame


def built(documents: DataFrame, params: StoreParams = StoreParams()) -> Store:
    spark = documents.sparkSession
    first = new_folder(spark, "ids-staging")
    rows = staged(staged_chunks(documents, first, params), "ids-rows")
    refs = rows.select("row", "doc_id", "n_tokens", "root", F.posexplode("chunks").alias("seq", "c"))
    owners = refs.groupBy("c.digest").agg(F.min(F.struct("c.pack", "c.at", "c.size")).alias("o")).select("digest", "o.pack", "o.at", "o.size")
    chunks = staged(compacted(owners, new_folder(spark, "ids-packs"), params), "ids-chunks")
    dropped(spark, first)
    refs = refs.select("row", "doc_id", "n_tokens", "root", "seq", F.col("c.digest").alias("digest"), F.col("c.ids").alias("ids"))
    placed = refs.join(chunks, "digest").groupBy("row", "doc_id", "n_tokens", "root").agg(
        F.array_sort(F.collect_list(F.struct("seq", "digest", "pack", "at", "size", "ids"))).alias("c")
    )
    placed = staged(placed.select("doc_id", "row", "n_tokens", "root", F.transform("c", lambda x: F.struct(x["digest"].alias("digest"), x["pack"].alias("pack"), x["at"].alias("at"), x["size"].alias("size"), x["ids"].alias("ids"))).alias("chunks")), "ids-placed")

    def numbered(batches):
        part, at = TaskContext.get().partitionId(), 0
        for batch in batches:
            n = np.asarray(batch.column("n_tokens"))
            ends = at + np.cumsum(n)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.full(len(n), part, np.int64)), pa.array(ends - n)], [*batch.schema.names, "part", "start_in_part"])
            at = int(ends[-1]) if len(n) else at

    ordered = placed.repartitionByRange("doc_id", "row").sortWithinPartitions("doc_id", "row")
    recipes = staged(ordered.mapInArrow(numbered, RECIPE + ", part long, start_in_part long"), "ids-recipes")
    # One row a part: its size and the root over its documents' roots in order.
    manifest = staged(recipes.groupBy("part").agg(F.sum("n_tokens").alias("n_tokens"), F.count(F.lit(1)).alias("n_docs"), F.sha2(F.concat_ws("", F.transform(F.array_sort(F.collect_list(F.struct("start_in_part", "row", F.hex("root").alias("h")))), lambda x: x["h"])), 256).alias("root")), "ids-manifest")
    return Store(recipes, manifest, chunks)


def streams(store: Store, params: StoreParams = StoreParams(), with_ids: bool = False) -> DataFrame:
    """Read the files back: doc_id, start, n_tokens, ids_crc32 (and the ids as unsigned 32-bit bytes); all is verified."""
    spark = store.recipes.sparkSession
    path = params.tokenizer or tokenizer_path()
    totals = store.manifest.select("part", "n_tokens").orderBy("part").collect()  # one row a partition
    before, at = {}, 0
    for r in totals:
        before[r["part"]], at = at, at + r["n_tokens"]
    sent = spark.sparkContext.broadcast(before)

    def job(batches):
        reader, unzip, hot = Reader(), zstandard.ZstdDecompressor(), OrderedDict()
        small = opened(path).tok.get_vocab_size() <= 1 << 16
        kind = "<u2" if small else "<u4"
        for batch in batches:
            out, lists = [], batch.column("chunks")
            ends, fields = np.asarray(lists.offsets).tolist(), lists.values
            digests, packs, ats, sizes = (fields.field(c).to_pylist() for c in ("digest", "pack", "at", "size"))
            for k, (doc_id, part, start, count, root) in enumerate(zip(*[batch.column(c).to_pylist() for c in ("doc_id", "part", "start_in_part", "n_tokens", "root")], strict=True)):
                i, j = ends[k], ends[k + 1]
                if merkle(digests[i:j]) != root:
                    raise ValueError(f"document {doc_id}: the recipe doesn't match its Merkle root")
                parts = []
                for c in range(i, j):
                    plain = hot.get(digests[c])
                    if plain is None:
                        plain = unzip.decompress(reader.read(packs[c], ats[c], sizes[c]))
                        if digest(plain) != digests[c]:
                            raise ValueError(f"document {doc_id}: a chunk doesn't match its digest")
                        hot[digests[c]] = plain
                        if len(hot) > 2048:
                            hot.popitem(last=False)
                    parts.append(plain)
                ids = np.frombuffer(b"".join(parts), kind).astype("<u4")
                if len(ids) != count:
                    raise ValueError(f"document {doc_id}: {len(ids)} ids for {count}")
                raw = ids.tobytes()
                out.append((doc_id, sent.value[part] + start, len(ids), zlib.crc32(raw), *([raw] if with_ids else [])))
            if out:
                cols = list(zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([*[pa.array(c, pa.int64()) for c in cols[:4]], *[pa.array(c, pa.binary()) for c in cols[4:]]], ["doc_id", "start", "n_tokens", "ids_crc32", "ids"][: len(cols)])

    return store.recipes.mapInArrow(job, "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids binary" * with_ids)


def op9_chunk_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams(built(spark.read.parquet(f"{sf_dir}/documents.parquet")))
