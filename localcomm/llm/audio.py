"""Telephony audio: mu-law and A-law by lookup tables, IMA ADPCM blocks by numpy across blocks, resampled PCM.

The stored forms are RIFF/WAVE files of one channel: 8-bit mu-law (format 7), 8-bit A-law (format 6), IMA ADPCM
(format 17, blocks of a 4-byte head and 576 bytes of codes) and 16-bit PCM (format 1). ADPCM is decoded for all
blocks of a batch at once: the loop runs over the places in a block, not over blocks.

Cases: a null text is an empty payload, padded to one unit of 576 bytes; a text of any length makes one file;
equal texts make equal files; a null id makes a file like any other; an empty table makes none; a stream that isn't one of these formats raises ValueError in `parsed`.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from localcomm.llm.common import flat, new_folder, slices, texts

UNIT = 576
PCM, ALAW, ULAW, IMA = 1, 6, 7, 17
RATE_IN, RATE_OUT = 8000, 16000
CHUNK = 1 << 20

#: Fixed values of IMA ADPCM: how a code moves the step index, and the 89 step sizes.
INDEX_MOVE = np.array([-1, -1, -1, -1, 2, 4, 6, 8, -1, -1, -1, -1, 2, 4, 6, 8], np.int32)
IMA_STEPS = np.array(
    [7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118,
     130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066,
     2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767], np.int32)


def _ulaw_table() -> np.ndarray:
    code = ~np.arange(256, dtype=np.int32) & 0xFF
    size = (((code & 15) << 3) + 132 << ((code >> 4) & 7)) - 132
    return np.where(code & 128, -size, size).astype(np.int16)


def _alaw_table() -> np.ndarray:
    code = np.arange(256, dtype=np.int32) ^ 0x55
    seg, low = (code >> 4) & 7, (code & 15) << 4
    size = np.where(seg == 0, low + 8, (low + 264) << np.maximum(seg - 1, 0))
    return np.where(code & 128, size, -size).astype(np.int16)


ULAW_TABLE, ALAW_TABLE = _ulaw_table(), _alaw_table()


def ima_blocks(codes: np.ndarray, first: np.ndarray, index: np.ndarray) -> np.ndarray:
    """Decode B blocks of C code bytes (low nibble first) to B x 2C samples; `first` and `index` are the heads' states."""
    blocks, size = codes.shape
    nibbles = np.empty((2 * size, blocks), np.uint8)
    nibbles[0::2] = (codes & 15).T
    nibbles[1::2] = (codes >> 4).T
    out = np.empty((2 * size, blocks), np.int16)
    value, at = first.astype(np.int32), index.astype(np.int32)
    for k in range(2 * size):
        c = nibbles[k]
        value = np.clip(value + IMA_DELTA[at, c], -32768, 32767)
        at = np.clip(at + INDEX_MOVE[c], 0, 88)
        out[k] = value
    return out.T


def _ima_delta() -> np.ndarray:
    step, code = IMA_STEPS[:, None], np.arange(16)[None, :]
    size = (step >> 3) + np.where(code & 4, step, 0) + np.where(code & 2, step >> 1, 0) + np.where(code & 1, step >> 2, 0)
    return np.where(code & 8, -size, size).astype(np.int32)


IMA_DELTA = _ima_delta()


def wave(kind: int, body: bytes, rate: int = RATE_IN) -> bytes:
    """A one-channel RIFF/WAVE file around coded bytes."""
    if kind == IMA:
        block, bits, extra = UNIT + 4, 4, struct.pack("<HH", 2, 2 * UNIT + 1)
        per_s = rate * block // (2 * UNIT + 1)
    elif kind == PCM:
        block, bits, extra, per_s = 2, 16, b"", 2 * rate
    else:
        block, bits, extra, per_s = 1, 8, struct.pack("<H", 0), rate
    fmt = struct.pack("<HHIIHH", kind, 1, rate, per_s, block, bits) + extra
    pad = b"\0" * (len(body) & 1)
    return b"RIFF" + struct.pack("<I", 20 + len(fmt) + len(body) + len(pad)) + b"WAVEfmt " + struct.pack("<I", len(fmt)) + fmt + b"data" + struct.pack("<I", len(body)) + body + pad


def parsed(media: bytes) -> tuple[int, int, bytes]:
    """(format, rate, coded bytes) of a RIFF/WAVE file."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a RIFF/WAVE file")
    at, kind, rate = 12, None, 0
    while at + 8 <= len(media):
        name, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if name == b"fmt ":
            kind, _, rate = struct.unpack_from("<HHI", media, at + 8)
        elif name == b"data":
            if kind not in (PCM, ALAW, ULAW, IMA):
                raise ValueError(f"format {kind} isn't handled")
            return kind, rate, media[at + 8 : at + 8 + size]
        at += 8 + size + (size & 1)
    raise ValueError("no data chunk")


def stored(payload: bytes) -> bytes:
    """A payload of whole units as a file; its checksum picks among the three codecs, so equal payloads agree."""
    kind = (ULAW, ALAW, IMA)[zlib.crc32(payload) % 3]
    if kind != IMA:
        return wave(kind, payload)
    codes = np.frombuffer(payload, np.uint8).reshape(-1, UNIT)
    return wave(IMA, np.hstack([np.zeros((len(codes), 4), np.uint8), codes]).tobytes())


def coded(media: bytes) -> tuple[int, bytes]:
    """The format and the code bytes, without ADPCM block heads, of a stored file."""
    kind, _, body = parsed(media)
    if kind == IMA:
        body = np.frombuffer(body, np.uint8).reshape(-1, UNIT + 4)[:, 4:].tobytes()
    return kind, body


def decoded(files: list[bytes]) -> list[np.ndarray]:
    """16-bit samples of stored files; the ADPCM blocks of all files are decoded together."""
    out, waiting = [None] * len(files), []
    for i, media in enumerate(files):
        kind, _, body = parsed(media)
        if kind == IMA:
            waiting.append((i, np.frombuffer(body, np.uint8).reshape(-1, UNIT + 4)))
        elif kind == PCM:
            out[i] = np.frombuffer(body, "<i2")
        else:
            out[i] = (ULAW_TABLE if kind == ULAW else ALAW_TABLE)[np.frombuffer(body, np.uint8)]
    if waiting:
        blocks = np.concatenate([b for _, b in waiting])
        heads = blocks[:, :2].copy().view("<i2")[:, 0]
        samples = ima_blocks(blocks[:, 4:], heads, blocks[:, 2])
        at = 0
        for i, b in waiting:
            out[i] = samples[at : at + len(b)].reshape(-1)
            at += len(b)
    return out


def resampled(pcm: np.ndarray, up: int = RATE_OUT // RATE_IN) -> np.ndarray:
    """Twice the rate: kept samples, and between them the 4-point interpolation (-1, 9, 9, -1) / 16 in whole numbers."""
    if up != 2:
        raise ValueError("only a doubled rate is built")
    x = np.concatenate([pcm[:1], pcm, pcm[-1:], pcm[-1:]]).astype(np.int32)
    mid = (9 * (x[1:-2] + x[2:-1]) - x[:-3] - x[3:] + 8) >> 4
    out = np.empty(2 * len(pcm), np.int16)
    out[0::2] = pcm
    out[1::2] = np.clip(mid, -32768, 32767)
    return out


def as_pcm(media: bytes) -> bytes:
    """A stored file as 16-bit PCM at the doubled rate."""
    return wave(PCM, resampled(decoded([media])[0]).astype("<i2").tobytes(), RATE_OUT)


def padded(payload: bytes) -> bytes:
    return payload + b"\xff" * (-len(payload) % UNIT or UNIT * (not payload))


def feature(kind: int, pcm: np.ndarray) -> str:
    """`described` of a sound that isn't resampled yet."""
    return described(kind, resampled(pcm))


def described(kind: int, sound: np.ndarray) -> str:
    """Codec, samples, peak, mean size, sign changes of resampled sound, all in whole numbers."""
    wide = np.abs(sound.astype(np.int32))
    changes = int(np.count_nonzero((sound[1:] < 0) != (sound[:-1] < 0)))
    return f"{ {ULAW: 'ulaw', ALAW: 'alaw', IMA: 'ima', PCM: 'pcm'}[kind]}:{len(sound)}:{int(wide.max())}:{int(wide.sum()) // len(sound)}:{changes}"


def coded_files(documents: DataFrame) -> DataFrame:
    """doc_id, n_bytes and media, the coded file of each text."""

    def job(batches):
        for batch in batches:
            buf, offs = flat(batch.column("text"))
            for i, j in slices(offs, CHUNK):
                media = [stored(padded(buf[offs[k] : offs[k + 1]].tobytes())) for k in range(i, j)]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), pa.array(offs[i + 1 : j + 1] - offs[i:j]), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])

    return texts(documents, binary=True).mapInArrow(job, "doc_id long, n_bytes long, media binary")


#: Effort of compression and bytes it sees at a time: coded files and sound together take more than the input otherwise allows.
ZSTD_LEVEL = 12
PAGE = 8 << 20


def _stored(df: DataFrame, name: str) -> DataFrame:
    path = new_folder(df.sparkSession, name)
    df.write.option("compression", "zstd").option("parquet.compression.codec.zstd.level", ZSTD_LEVEL).option("parquet.page.size", PAGE).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def archived(documents: DataFrame) -> DataFrame:
    """`coded_files`, written to the shared folder and read from there."""
    return _stored(coded_files(documents), "audio")


def packed(sound: np.ndarray) -> tuple[bytes, bytes]:
    """Doubled PCM without loss: every second sample, and by how much those between differ from `resampled`.

    Up to 256 different samples are a table, after the number of its values, and a byte for each sample; beyond, they follow a zero as they are.
    """
    kept = np.ascontiguousarray(sound[0::2])
    between = (sound[1::2] - resampled(kept)[1::2]).astype("<i2").tobytes()
    values, codes = np.unique(kept, return_inverse=True)
    if len(values) > 256:
        return struct.pack("<H", 0) + kept.astype("<i2").tobytes(), between
    return struct.pack("<H", len(values)) + values.astype("<i2").tobytes() + codes.astype(np.uint8).tobytes(), between


def unpacked(kept: bytes, between: bytes) -> np.ndarray:
    many = struct.unpack_from("<H", kept)[0]
    told = np.frombuffer(kept, "<i2", many, 2)[np.frombuffer(kept, np.uint8, offset=2 + 2 * many)] if many else np.frombuffer(kept, "<i2", offset=2)
    sound = resampled(told)
    sound[1::2] += np.frombuffer(between, "<i2")
    return sound


DIGESTS = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string"


def resampled_archive(media: DataFrame) -> DataFrame:
    """Digests of the files of `archived`, read from their bytes, and their PCM at the doubled rate, written to the shared folder and read from there.

    Sound goes by format, `kept` and `between`, as `packed` says: as plain PCM it takes four to eight times the payload.
    """

    def job(batches):
        for batch in batches:
            buf, offs = flat(batch.column("media"))
            for i, j in slices(offs, CHUNK):
                files = [buf[offs[k] : offs[k + 1]].tobytes() for k in range(i, j)]
                bodies = [coded(f) for f in files]
                sounds = [packed(resampled(x)) for x in decoded(files)]
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("doc_id").slice(i, j - i),
                        batch.column("n_bytes").slice(i, j - i),
                        pa.array([len(b) for _, b in bodies], pa.int64()),
                        pa.array([hashlib.sha256(b).hexdigest() for _, b in bodies]),
                        pa.array([zlib.crc32(b[-32:]) for _, b in bodies], pa.int64()),
                        pa.array([len(f) for f in files], pa.int64()),
                        pa.array([hashlib.sha256(f).hexdigest() for f in files]),
                        pa.array([k for k, _ in bodies], pa.int32()),
                        pa.array([k for k, _ in sounds], pa.binary()),
                        pa.array([b for _, b in sounds], pa.binary()),
                    ],
                    [*(x.split()[0] for x in DIGESTS.split(", ")), "kind", "kept", "between"],
                )

    schema = f"{DIGESTS}, kind int, kept binary, between binary"
    return _stored(media.select("doc_id", "n_bytes", "media").mapInArrow(job, schema), "pcm")


def _sounds(batch, i: int, j: int) -> list[np.ndarray]:
    return [unpacked(k, b) for k, b in zip(batch.column("kept").slice(i, j - i).to_pylist(), batch.column("between").slice(i, j - i).to_pylist(), strict=True)]


def pcm_archived(media: DataFrame) -> DataFrame:
    """doc_id and pcm, each file of `archived` as 16-bit PCM at the doubled rate, from the bytes that `resampled_archive` wrote."""

    def job(batches):
        for batch in batches:
            _, offs = flat(batch.column("between"))
            for i, j in slices(offs, CHUNK):
                pcm = [wave(PCM, x.astype("<i2").tobytes(), RATE_OUT) for x in _sounds(batch, i, j)]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), pa.array(pcm, pa.binary())], ["doc_id", "pcm"])

    return resampled_archive(media).select("doc_id", "kept", "between").mapInArrow(job, "doc_id long, pcm binary")


FIELDS = f"{DIGESTS}, feature string"


def inspected(media: DataFrame) -> DataFrame:
    """Digests of the files of `archived`, and features of the stored PCM that `resampled_archive` made of them."""
    names = [x.split()[0] for x in DIGESTS.split(", ")]

    def job(batches):
        for batch in batches:
            _, offs = flat(batch.column("between"))
            for i, j in slices(offs, CHUNK):
                kinds = batch.column("kind").slice(i, j - i).to_pylist()
                told = pa.array([described(k, s) for k, s in zip(kinds, _sounds(batch, i, j), strict=True)])
                yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(i, j - i) for c in names), told], [*names, "feature"])

    return resampled_archive(media).mapInArrow(job, FIELDS)


def op1_audio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return inspected(archived(spark.read.parquet(f"{sf_dir}/documents.parquet")))
