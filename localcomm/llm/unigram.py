"""Unigram pieces by Viterbi over a double-array trie, with byte fallback and whitespace-marker decoding.

The vocabulary is read from a SentencePiece model file (its protobuf is parsed here); pieces keep their scores, and
the path of the highest total score wins. All words of a batch that aren't cached are segmented together: the
Viterbi loop runs over places in a word and piece lengths, and the trie's base/check arrays are followed for all
words at once with numpy.

No piece but runs of markers holds the marker after its first place (checked when the model is read), so the best
path of a text is the concatenation of its marker-led words' best paths; runs of several markers stay with the
word that follows them and are segmented with it.

Cases: a null or empty text has no pieces; characters beyond the vocabulary become their UTF-8 byte pieces;
texts with neighbouring blanks keep them all; equal texts get equal ids; very long words are segmented alone.
Scores add up in double precision, so a far lower unknown cannot blur later choices; ties go to the path found first,
scanning starts from left to right.
"""

from __future__ import annotations

import re
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from localcomm.llm.common import texts

#: Fixed values of SentencePiece: the whitespace marker, the piece kinds, and how far an unknown lies below the lowest score.
MARK = "▁"
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNKNOWN_PENALTY = 10.0
GENERATION = 200_000
WIDTH = 32


def model_path(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _varint(b: bytes, i: int) -> tuple[int, int]:
    out = shift = 0
    while True:
        c = b[i]
        i += 1
        out |= (c & 127) << shift
        shift += 7
        if c < 128:
            return out, i


def _fields(b: bytes):
    """(number, value) of the fields of a protobuf message."""
    i = 0
    while i < len(b):
        key, i = _varint(b, i)
        kind = key & 7
        if kind == 0:
            value, i = _varint(b, i)
        elif kind == 2:
            n, i = _varint(b, i)
            value, i = b[i : i + n], i + n
        else:
            n = 8 if kind == 1 else 4
            value, i = b[i : i + n], i + n
        yield key >> 3, value


def read_pieces(path: str) -> list[tuple[str, float, int]]:
    """(piece, score, kind) by id."""
    out = []
    with open(path, "rb") as f:
        body = f.read()
    for number, value in _fields(body):
        if number == 1:
            d = dict(_fields(value))
            out.append((d[1].decode(), struct.unpack("<f", d[2])[0] if 2 in d else 0.0, d.get(3, NORMAL)))
    return out


class DoubleArray:
    """A trie over symbol codes in base/check arrays; `value` holds the id of the piece that ends at a node, or -1."""

    def __init__(self, keys: list[tuple[tuple[int, ...], int]]):
        tree: dict = {}
        for key, ident in keys:
            node = tree
            for c in key:
                node = node.setdefault(c, {})
            node[0] = ident
        size = 1 << 17
        self.base, self.check, self.value = np.zeros(size, np.int64), np.full(size, -1, np.int64), np.full(size, -1, np.int64)
        used = bytearray(size)
        used[0] = 1
        self.check[0] = 0
        free_from, todo = 1, [(tree, 0)]
        top = 0
        while todo:
            node, at = todo.pop()
            self.value[at] = node.get(0, -1)
            codes = sorted(c for c in node if c)
            if not codes:
                continue
            while used[free_from]:
                free_from += 1
            spot = free_from
            while True:
                b = spot - codes[0]
                if b >= 0:
                    if b + codes[-1] >= size:
                        self._grow(b + codes[-1] + 1)
                        used.extend(bytes(len(self.base) - len(used)))
                        size = len(self.base)
                    if not any(used[b + c] for c in codes):
                        break
                spot += 1
                while spot < size and used[spot]:
                    spot += 1
                if spot >= size:
                    self._grow(size + 1)
                    used.extend(bytes(len(self.base) - len(used)))
                    size = len(self.base)
            self.base[at] = b
            for c in codes:
                used[b + c] = 1
                self.check[b + c] = at
                todo.append((node[c], b + c))
            top = max(top, b + codes[-1])
        # Room for any code past the last node, so that a step needs no bounds check.
        self.reach = top + 1

    def _grow(self, least: int) -> None:
        more = max(least, 2 * len(self.base)) - len(self.base)
        self.base = np.append(self.base, np.zeros(more, np.int64))
        self.check = np.append(self.check, np.full(more, -1, np.int64))
        self.value = np.append(self.value, np.full(more, -1, np.int64))

    def step(self, nodes: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """The children of nodes by codes (0: none); -1 where there is none."""
        to = self.base[nodes] + codes
        ok = (codes > 0) & (to < len(self.check))
        to = np.where(ok, to, 0)
        return np.where(ok & (self.check[to] == nodes), to, -1)


class Unigram:
    def __init__(self, pieces: list[tuple[str, float, int]]):
        self.pieces = pieces
        # The whole-text optimum splits at words only if no other piece crosses a marker.
        for p, _, kind in pieces:
            if kind in (NORMAL, USER) and MARK in p[1:] and p.strip(MARK):
                raise ValueError(f"piece {p!r} crosses a word's start")
        usable = [(p, s, i) for i, (p, s, k) in enumerate(pieces) if k in (NORMAL, USER)]
        letters = sorted({c for p, _, _ in usable for c in p})
        self.codes = np.zeros(0x110000, np.int32)
        self.codes[[ord(c) for c in letters]] = np.arange(1, len(letters) + 1)
        self.longest = max((len(p) for p, _, _ in usable), default=1)
        self.trie = DoubleArray([(tuple(self.codes[[ord(c) for c in p]].tolist()), i) for p, _, i in usable])
        self.scores = np.array([s for _, s, _ in pieces])
        self.unknown = next((i for i, (_, _, k) in enumerate(pieces) if k == UNKNOWN), 0)
        self.low = min((s for _, s, _ in usable), default=0.0) - UNKNOWN_PENALTY
        self.byte_id = {int(p[3:5], 16): i for i, (p, _, k) in enumerate(pieces) if k == BYTE}
        self.surface = [bytes([int(p[3:5], 16)]) if k == BYTE else b" \xe2\x81\x87 " if k == UNKNOWN else b"" if k == CONTROL else p.replace(MARK, " ").encode() for p, _, k in pieces]
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def segment(self, words: list[str]) -> list[list[int]]:
        """The best path of each word; words of like length share one run of the Viterbi loop."""
        out: list = [None] * len(words)
        order = sorted(range(len(words)), key=lambda k: len(words[k]))
        at = 0
        while at < len(order):
            longest = max(len(words[order[at]]), 4)
            end = at
            while end < len(order) and len(words[order[end]]) <= longest + longest // 8 and (end - at) * (longest + 1) < 2_000_000:
                end += 1
            some = order[at:end]
            for k, path in zip(some, self._viterbi([words[k] for k in some]), strict=True):
                out[k] = path
            at = end
        return out

    def _viterbi(self, words: list[str]) -> list[list[int]]:
        n = len(words)
        lengths = np.array([len(w) for w in words])
        wide = int(lengths.max())
        points = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), "<u4")
        codes = np.zeros((wide + 1, n), np.int32)
        rows = np.repeat(np.arange(n), lengths)
        place = np.arange(len(points)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
        codes[place, rows] = self.codes[points]
        best = np.full((wide + 1, n), -np.inf)
        best[0] = 0
        piece, start = np.full((wide + 1, n), -1, np.int32), np.zeros((wide + 1, n), np.int32)
        for i in range(wide):
            live = np.flatnonzero(lengths > i)
            nodes, here, single = np.zeros(len(live), np.int64), live, np.zeros(n, bool)
            for size in range(1, min(self.longest, wide - i) + 1):
                nodes = self.trie.step(nodes, codes[i + size - 1, here])
                ok = nodes >= 0
                nodes, here = nodes[ok], here[ok]
                if not len(here):
                    break
                ids = self.trie.value[nodes]
                hit = ids >= 0
                to, w = here[hit], ids[hit]
                total = best[i, to] + self.scores[w]
                if size == 1:
                    single[to] = True
                # The library keeps the first best path it meets for an end, scanning starts from left to right.
                better = total > best[i + size, to]
                to, w, total = to[better], w[better], total[better]
                best[i + size, to], piece[i + size, to], start[i + size, to] = total, w, i
            alone = live[~single[live]]
            total = best[i, alone] + self.low
            better = total > best[i + 1, alone]
            alone, total = alone[better], total[better]
            best[i + 1, alone], piece[i + 1, alone], start[i + 1, alone] = total, -1, i
        # Walk all paths back together, one piece a turn.
        at, turns = lengths.copy(), []
        while (going := np.flatnonzero(at > 0)).size:
            turns.append((going, piece[at[going], going], start[at[going], going], at[going]))
            at[going] = start[at[going], going]
        paths: list[list[int]] = [[] for _ in range(n)]
        for going, ids, starts, ends in reversed(turns):
            for k, ident, s, e in zip(going.tolist(), ids.tolist(), starts.tolist(), ends.tolist(), strict=True):
                if ident >= 0:
                    paths[k].append(ident)
                else:
                    paths[k] += self.fallback(words[k][s:e])
        return paths

    def fallback(self, text: str) -> list[int]:
        if len(self.byte_id) < 256:
            return [self.unknown]
        return [self.byte_id[b] for b in text.encode("utf-8", "surrogatepass")]

    def encode(self, some: list[str]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit integers."""
        if len(self.young) > GENERATION:
            self.young, self.old = {}, self.young
        split = [words_of(t) for t in some]
        need = set()
        for s in split:
            need.update(s)
        young, old, new = self.young, self.old, []
        for w in need:
            if w not in young:
                got = old.get(w)
                if got is None:
                    new.append(w)
                else:
                    young[w] = got
        for lo in range(0, len(new), 50_000):
            part = new[lo : lo + 50_000]
            for w, path in zip(part, self.segment(part), strict=True):
                young[w] = np.array(path, "<u4").tobytes()
        return [b"".join([young[w] for w in s]) for s in split]

    def decode(self, ids: np.ndarray) -> str:
        """Text of ids: byte pieces join to characters, markers become blanks, the leading one goes."""
        surface = self.surface
        raw = b"".join([surface[i] for i in ids.tolist()])
        return (raw[1:] if raw[:1] == b" " else raw).decode("utf-8", "replace")


def words_of(text: str) -> list[str]:
    """Marker-led words of a text with its added leading marker; blanks without a word join the next one."""
    if not text:
        return []
    marked = MARK + text.replace(" ", MARK)
    if MARK + MARK in marked or marked.endswith(MARK):
        return re.findall(f"{MARK}+[^{MARK}]*", marked)
    return [MARK + w for w in marked.split(MARK)[1:]]


_open: dict[str, Unigram] = {}


def opened(path: str) -> Unigram:
    if path not in _open:
        _open[path] = Unigram(read_pieces(path))
    return _open[path]


FIELDS = "doc_id long, n_pieces long, n_byte_pieces long, ids_crc32 long, decoded_equal boolean"


def encoded(documents: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, ids (unsigned 32-bit little-endian bytes) of every text."""
    path = path or model_path()

    def job(batches):
        model = opened(path)
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text"), pa.array(model.encode(part.column("text").to_pylist()), pa.binary())], ["doc_id", "text", "ids"])

    return texts(documents).mapInArrow(job, "doc_id long, text string, ids binary")


def decoded(ids: DataFrame, path: str | None = None) -> DataFrame:
    """Adds `decoded`, the text of column `ids`."""
    path = path or model_path()

    def job(batches):
        model = opened(path)
        for batch in batches:
            back = [model.decode(np.frombuffer(x, "<u4")) for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(back, pa.string())], [*batch.schema.names, "decoded"])

    from pyspark.sql.types import StringType, StructType

    return ids.mapInArrow(job, StructType(list(ids.schema.fields)).add("decoded", StringType()))


def digested(documents: DataFrame, path: str | None = None) -> DataFrame:
    """Counts and checksum of the ids of every text, and whether decoding gives the text again."""
    path = path or model_path()

    def job(batches):
        model = opened(path)
        is_byte = np.zeros(len(model.pieces), bool)
        is_byte[list(model.byte_id.values())] = True
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                some = part.column("text").to_pylist()
                raws = model.encode(some)
                ids = [np.frombuffer(r, "<u4") for r in raws]
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column("doc_id"),
                        pa.array([len(x) for x in ids], pa.int64()),
                        pa.array([int(is_byte[x].sum()) for x in ids], pa.int64()),
                        pa.array([zlib.crc32(r) for r in raws], pa.int64()),
                        pa.array([model.decode(x) == t for x, t in zip(ids, some, strict=True)]),
                    ],
                    [x.split()[0] for x in FIELDS.split(", ")],
                )

    return texts(documents).mapInArrow(job, FIELDS)


def op10_unigram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digested(spark.read.parquet(f"{sf_dir}/documents.parquet"))
