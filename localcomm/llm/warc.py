"""WARC in seekable Zstandard bundles.

Records are grouped into independent zstd frames; a bundle ends with a seek table in the public seekable format
(a skippable frame of compressed and plain sizes), and an index table maps each record's identifier to its bundle,
frame and offset inside the frame, so that one record costs one frame. Payloads of at least `min_revisit` bytes
that occur again become revisit records of the one with the largest page_id.

Bundles lie in the shared folder; writers name them afresh at each attempt and only the committed index names them.

Cases: a null html is an empty payload; a null url leaves its header out; line breaks and blanks in urls are
percent-encoded; rows that repeat a page_id with the same payload are each a response if that id is the largest;
null page_ids are written as `none` and read back as null; an empty table gives no bundle and no row.
"""

from __future__ import annotations

import base64
import hashlib
import re
import struct

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcomm.llm.common import new_folder, staged
from localcomm.llm.files import Reader, Roller

#: Fixed values of the seekable format: magic of the skippable frame that holds the table, magic of its footer.
TABLE_MAGIC, FOOTER_MAGIC = 0x184D2A5E, 0x8F92EAB1
FRAME_BYTES, BUNDLE_BYTES = 256 << 10, 64 << 20
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: Payloads that occur again, up to which their digests are sent to all tasks.
SEND_MOST = 200_000
#: Ranges of frames in which a bundle is read back, and tasks at most.
RANGES, TASKS_MOST = 4, 50_000
INDEX = "record_id string, page_id long, bundle string, frame_start long, frame_bytes long, offset long, length long"


def record(page_id, url, payload: bytes, digest: str, refers_to) -> tuple[str, bytes]:
    """The identifier and bytes of one record; `digest` is the payload's SHA-1 in hexadecimal."""
    name = f"<urn:page:{'none' if page_id is None else page_id}>"
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http + payload if refers_to is None else http
    lines = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {name}", "WARC-Date: 1970-01-01T00:00:00Z"]
    if url is not None:
        lines.append("WARC-Target-URI: " + re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url))
    if refers_to is not None:
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    lines += [f"WARC-Payload-Digest: sha1:{base64.b32encode(bytes.fromhex(digest)).decode()}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return name, "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


class BundleWriter:
    """Frames of records, rolled into bundles with a seek table each."""

    def __init__(self, folder: str):
        self.roll = Roller(folder, BUNDLE_BYTES, ".warc.zst")
        self.zip = zstandard.ZstdCompressor(level=3, write_checksum=True)
        self.held, self.size, self.table = [], 0, []

    def add(self, key: tuple, data: bytes):
        self.held.append((key, self.size, data))
        self.size += len(data)
        return self.flush() if self.size >= FRAME_BYTES else []

    def flush(self) -> list[tuple]:
        if not self.held:
            return []
        frame = self.zip.compress(b"".join(d for _, _, d in self.held))
        path, at = self.roll.write(frame)
        rows = [(*key, path, at, len(frame), off, len(d)) for key, off, d in self.held]
        self.table.append((len(frame), self.size))
        self.held, self.size = [], 0
        if self.roll.full:
            self._end()
        return rows

    def _end(self) -> None:
        if self.table:
            body = b"".join(struct.pack("<II", *x) for x in self.table) + struct.pack("<IBI", len(self.table), 0, FOOTER_MAGIC)
            self.roll.write(struct.pack("<II", TABLE_MAGIC, len(body)) + body)
        self.roll.close()
        self.table = []

    def close(self) -> list[tuple]:
        rows = self.flush()
        self._end()
        return rows


def seek_table(reader: Reader, path: str) -> list[tuple[int, int, int]]:
    """(start, compressed size, plain size) of each frame of a bundle, from its footer."""
    size = reader.size(path)
    count, _, magic = struct.unpack("<IBI", reader.read(path, size - 9, 9))
    if magic != FOOTER_MAGIC:
        raise ValueError(f"{path} has no seek table")
    body = reader.read(path, size - 9 - 8 * count, 8 * count)
    out, at = [], 0
    for packed, plain in struct.iter_unpack("<II", body):
        out.append((at, packed, plain))
        at += packed
    return out


def parsed(data: bytes, at: int = 0) -> tuple[dict[str, str], bytes, int]:
    """Headers, block and end of the record that starts at `at`."""
    end = data.index(b"\r\n\r\n", at)
    first, *rest = data[at:end].decode().split("\r\n")
    if not first.startswith("WARC/"):
        raise ValueError("no WARC record here")
    head = dict(x.split(": ", 1) for x in rest)
    body = end + 4
    size = int(head["Content-Length"])
    return head, data[body : body + size], body + size + 4


def classified(pages: DataFrame, min_revisit: int = 1000) -> DataFrame:
    """page_id, url, payload, digest and refers_to (the response's page_id, null for responses)."""
    payload = F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary")
    own = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), payload.alias("payload")).withColumn("digest", F.sha1("payload"))
    often = own.where(F.octet_length("payload") >= min_revisit).groupBy("digest").agg(F.max("page_id").alias("first_of"), F.count(F.lit(1)).alias("n")).where("n > 1").select("digest", "first_of")
    often = staged(often, "repeated-payloads")
    if often.limit(SEND_MOST + 1).count() <= SEND_MOST:
        joined = own.join(F.broadcast(often), "digest", "left")  # payloads stay where they are
    else:  # only payloads that may be revisits travel
        large = F.octet_length("payload") >= min_revisit
        joined = own.where(large).join(often, "digest", "left").unionByName(own.where(~large).withColumn("first_of", F.lit(None).cast("long")))
    return joined.select("page_id", "url", "payload", "digest", F.when(~F.col("page_id").eqNullSafe(F.col("first_of")), F.col("first_of")).alias("refers_to"))


def written(records: DataFrame, folder: str) -> DataFrame:
    """Write bundles; the index has one row for each record."""
    names = [x.split()[0] for x in INDEX.split(", ")]
    types = [pa.string(), pa.int64(), pa.string(), *[pa.int64()] * 4]

    def table(rows):
        cols = list(zip(*rows, strict=True))
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)

    def job(batches):
        out = BundleWriter(folder)
        for batch in batches:
            rows = []
            for page_id, url, payload, digest, refers in zip(*[batch.column(c).to_pylist() for c in ("page_id", "url", "payload", "digest", "refers_to")], strict=True):
                name, data = record(page_id, url, payload, digest, refers)
                rows += out.add((name, page_id), data)
            if rows:
                yield table(rows)
        rows = out.close()
        if rows:
            yield table(rows)

    return records.mapInArrow(job, INDEX)


READ = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string"


def _page(urn: str):
    return None if urn.endswith(":none>") else int(urn[len("<urn:page:") : -1])


def read_back(bundles: DataFrame) -> DataFrame:
    """Every record of the bundles (column `bundle`), frame by frame by the seek table; digests are checked.

    A bundle is read in RANGES ranges of its frames, dealt evenly: Spark would gather so short a list of names in one task.
    """
    names = staged(bundles.select("bundle").distinct(), "bundles")
    tasks = min(TASKS_MOST, max(1, RANGES * names.count()))
    dealt = names.select("bundle", F.explode(F.sequence(F.lit(0), F.lit(RANGES - 1))).alias("part")).repartition(tasks)

    def job(batches):
        reader, unzip = Reader(), zstandard.ZstdDecompressor()
        for batch in batches:
            for path, part in zip(batch.column("bundle").to_pylist(), batch.column("part").to_pylist(), strict=True):
                frames = seek_table(reader, path)
                for start, packed, plain in frames[len(frames) * part // RANGES : len(frames) * (part + 1) // RANGES]:
                    data, at, rows = unzip.decompress(reader.read(path, start, packed), max_output_size=plain), 0, []
                    while at < len(data):
                        head, block, at = parsed(data, at)
                        rows.append(_described(head, block))
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.string() if k in (2, 3, 5) else pa.int64()) for k, c in enumerate(zip(*rows, strict=True))], [x.split()[0] for x in READ.split(", ")])

    return dealt.mapInArrow(job, READ)


def _described(head: dict[str, str], block: bytes) -> tuple:
    http, _, payload = block.partition(b"\r\n\r\n")
    size = int(re.search(rb"Content-Length: (\d+)", http)[1])
    digest = base64.b32decode(head["WARC-Payload-Digest"].removeprefix("sha1:")).hex()
    kind = head["WARC-Type"]
    if kind == "response" and (len(payload) != size or hashlib.sha1(payload).hexdigest() != digest):
        raise ValueError(f"{head['WARC-Record-ID']}: the payload doesn't match its digest")
    return _page(head["WARC-Record-ID"]), size, digest, kind, _page(head["WARC-Refers-To"]) if kind == "revisit" else None, head.get("WARC-Target-URI")


def fetched(index: DataFrame) -> DataFrame:
    """The records of chosen index rows by one seek each: page_id, headers, block."""

    def job(batches):
        reader, unzip = Reader(), zstandard.ZstdDecompressor()
        for batch in batches:
            rows = []
            for page_id, path, start, size, off, length in zip(*[batch.column(c).to_pylist() for c in ("page_id", "bundle", "frame_start", "frame_bytes", "offset", "length")], strict=True):
                frame = unzip.decompress(reader.read(path, start, size))
                head, block, _ = parsed(frame[off : off + length])
                rows.append((page_id, list(head.items()), block))
            if rows:
                cols = list(zip(*rows, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.map_(pa.string(), pa.string())), pa.array(cols[2], pa.binary())], ["page_id", "headers", "block"])

    return index.mapInArrow(job, "page_id long, headers map<string,string>, block binary")


def archived(pages: DataFrame, min_revisit: int = 1000) -> DataFrame:
    """Write all pages to bundles and return the staged index."""
    folder = new_folder(pages.sparkSession, "warc-bundles")
    return staged(written(classified(pages, min_revisit), folder), "warc-index")


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = archived(spark.read.parquet(f"{sf_dir}/pages.parquet"))
    back = read_back(index)
    return back.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE = """
WITH p AS (SELECT CAST(page_id AS BIGINT) AS page_id, coalesce(html, '') AS html, sha1(coalesce(html, '')) AS digest FROM pages),
often AS (SELECT digest, max(page_id) AS first_of FROM p WHERE octet_length(encode(html)) >= 1000 GROUP BY digest HAVING count(*) > 1)
SELECT page_id, CAST(octet_length(encode(html)) AS BIGINT) AS payload_bytes, p.digest AS payload_digest,
       CASE WHEN first_of IS NOT NULL AND first_of IS DISTINCT FROM page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN first_of IS DISTINCT FROM page_id THEN first_of END AS refers_to
FROM p LEFT JOIN often ON often.digest = p.digest
"""
