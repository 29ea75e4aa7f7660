"""Line dedup by a log-template tree of fixed depth.

A line's tokens are its runs of non-blanks; a token with a digit is a variable field. The tree's path is the token
count, then the first `lead` tokens; lines of one leaf are of one template when the rest agrees but for one of
`segments` stretches (which becomes variable), or wholly if the rest is short. A template that occurs in at
least `min_docs` documents recurs: its lines are dropped from every document but the one with the smallest doc_id.

With `passage_words`, passages recur too, from `passage_docs` documents on and word for word (digits count): from each
line the shortest stretch of lines of at least that many words, and the shortest that ends with it. A shared run of lines
of so many words is covered by such stretches. Lines between two of a stretch that hold no word stay.
Both are found in the texts as they come in, so that neither hides the other.

Python hashes the tokens of many texts at once and emits one row per (template, document) pre-aggregated; counts
are summed by Spark. Recurring templates are few; up to `broadcast_most` of them are sent to all tasks, beyond
that lines are joined with them.

Cases: a null or empty text has no line that can be dropped and comes back as it is (null stays null in
`deduplicated`, empty in the query); lines of fewer than `min_tokens` tokens are never dropped; blank lines stay;
rows that repeat a doc_id count as documents of their own and keep a template if that id is the smallest; a null
doc_id counts but loses nothing; other columns are kept, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcomm.llm.common import MULT, flat, fresh, mixed, run_hashes, slices, staged, texts, tidy

CHUNK = 1 << 18
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_WILD = np.uint64(0x5BD1E995)


@dataclass(frozen=True)
class TemplateParams:
    lead: int = 3
    segments: int = 4
    min_rest: int = 8
    min_tokens: int = 4
    min_docs: int = 10
    broadcast_most: int = 500_000
    passage_words: int = 0  # 0: no passages
    passage_docs: int = 2
    templates: bool = True


#: What production runs with: templates and passages; and passages alone, for texts whose templates are gone.
PASSAGES = TemplateParams(passage_words=50)
ONLY_PASSAGES = TemplateParams(passage_words=50, templates=False)
#: Odd, so that they have an inverse and a stretch has the same key at any place of a text.
_STEPS = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)


def line_keys(b: np.ndarray, offs: np.ndarray, p: TemplateParams) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(line, key a, key b) of every template of every line of some texts, and each line's row and end in the bytes.

    Lines are numbered through all texts; a text of k line ends has k + 1 lines.
    """
    n, size = len(offs) - 1, len(b)
    newline = np.flatnonzero(b == 10)
    row_of_nl = np.searchsorted(offs, newline, side="right") - 1
    per_row = np.bincount(row_of_nl, minlength=n) + 1
    line_row = np.repeat(np.arange(n), per_row)
    ends = np.empty(len(line_row), np.int64)
    last = np.cumsum(per_row) - 1
    inner = np.ones(len(line_row), bool)
    inner[last] = False
    ends[last], ends[inner] = offs[1:], newline
    none = np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.uint64), line_row, ends
    if not size:
        return none
    blank = _BLANK[b]
    edge = np.ones(size, bool)
    edge[1:] = blank[1:] != blank[:-1]
    edge[offs[:-1][offs[:-1] < size]] = True
    starts = np.flatnonzero(edge)
    lengths = np.diff(np.append(starts, size))
    h = run_hashes(b, starts, lengths)
    h = np.where(np.add.reduceat(_DIGIT[b].astype(np.int32), starts) > 0, _WILD, h)
    token = ~blank[starts]
    starts, h = starts[token], h[token]
    if not len(h):
        return none
    line = np.searchsorted(ends, starts, side="right")
    count = np.bincount(line, minlength=len(ends))
    first = np.cumsum(count) - count
    place = np.arange(len(h)) - first[line]
    total = count[line]
    rest = total - p.lead
    part = np.where(place < p.lead, 0, np.where(rest < p.min_rest, 1, 1 + (place - p.lead) * p.segments // np.maximum(rest, 1)))
    with np.errstate(over="ignore"):
        h = mixed(h + place.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        cell = line * (p.segments + 1) + part
        cut = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))
        sums = np.zeros(len(ends) * (p.segments + 1), np.uint64)
        sums[cell[cut]] = np.add.reduceat(h, cut)
        sums = sums.reshape(len(ends), p.segments + 1)
        use = np.flatnonzero(count >= p.min_tokens)
        a = mixed(sums[use, 0] + count[use].astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))
        whole = sums[use, 1:].sum(1, dtype=np.uint64)
        long = count[use] - p.lead >= p.min_rest
        out = [(use[~long], a[~long], mixed(whole[~long]))]
        for v in range(p.segments):
            out.append((use[long], a[long], mixed(whole[long] - sums[use[long], v + 1] + np.uint64(v + 1))))
    return np.concatenate([x[0] for x in out]), np.concatenate([x[1] for x in out]), np.concatenate([x[2] for x in out]), line_row, ends


def passage_keys(b: np.ndarray, offs: np.ndarray, p: TemplateParams) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(first line, last line, key a, key b) of the shortest stretches of `passage_words` words of some texts; lines are numbered as above."""
    ends = np.sort(np.concatenate([np.flatnonzero(b == 10), offs[1:]]))
    none = tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.uint64, np.uint64))
    if not len(b):
        return none
    blank = _BLANK[b]
    edge = np.ones(len(b), bool)
    edge[1:] = blank[1:] != blank[:-1]
    edge[offs[:-1][offs[:-1] < len(b)]] = True
    starts = np.flatnonzero(edge)
    h = run_hashes(b, starts, np.diff(np.append(starts, len(b))))
    token = ~blank[starts]
    starts, h = starts[token], h[token]
    if not len(h):
        return none
    line = np.searchsorted(ends, starts, side="right")
    cut = np.flatnonzero(np.append(True, line[1:] != line[:-1]))
    held = line[cut]  # the lines with words, in order
    before = np.append(cut, len(h))  # words before each of them
    row = np.searchsorted(offs, starts[cut], side="right")
    opens = np.searchsorted(row, row, side="left")
    closes = np.searchsorted(row, row, side="right")
    k = np.arange(len(held))
    ahead = np.searchsorted(before, before[:-1] + p.passage_words) - 1
    back = np.searchsorted(before, before[1:] - p.passage_words, side="right") - 1
    fits, fits_back = ahead < closes, back >= opens
    lo, hi = np.append(k[fits], back[fits_back]), np.append(ahead[fits], k[fits_back])
    both = np.unique(lo * len(held) + hi)
    lo, hi = both // len(held), both % len(held)
    keys = []
    with np.errstate(over="ignore"):
        h = mixed(h + (np.arange(len(h)) - np.repeat(cut, np.diff(before))).astype(np.uint64) * MULT)
        whole = mixed(np.add.reduceat(h, cut))
        for i, step in enumerate(_STEPS):
            up = np.cumprod(np.append(np.uint64(1), np.full(len(held) - 1, step, np.uint64)), dtype=np.uint64)
            down = np.cumprod(np.append(np.uint64(1), np.full(len(held) - 1, pow(step, -1, 1 << 64), np.uint64)), dtype=np.uint64)
            sums = np.append(np.uint64(0), np.cumsum(mixed(whole + np.uint64(i + 1)) * up, dtype=np.uint64))
            keys.append(mixed((sums[hi + 1] - sums[lo]) * down[lo] + (before[hi + 1] - before[lo]).astype(np.uint64)))
    return held[lo], held[hi], keys[0], keys[1]


def spans(b: np.ndarray, offs: np.ndarray, p: TemplateParams) -> tuple[np.ndarray, ...]:
    """(first line, last line, key a, key b) of all that may recur, and each line's row and end; key a is odd for passages."""
    line, a, key, line_row, ends = line_keys(b, offs, p)
    if not p.templates:
        line, a, key = line[:0], a[:0], key[:0]
    last, a = line, a & ~np.uint64(1)
    if p.passage_words:
        lo, hi, pass_a, pass_b = passage_keys(b, offs, p)
        line, last, a, key = np.append(line, lo), np.append(last, hi), np.append(a, pass_a | np.uint64(1)), np.append(key, pass_b)
    return line, last, a, key, line_row, ends


def _gone(first: np.ndarray, last: np.ndarray, buf: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Which lines lie in some of the spans and hold a word."""
    depth = np.zeros(len(ends) + 1, np.int64)
    np.add.at(depth, first, 1)
    np.add.at(depth, last + 1, -1)
    gone = np.cumsum(depth[:-1]) > 0
    words = np.append(0, np.cumsum(~_BLANK[buf]))
    return gone & (np.diff(words[np.append(0, ends)]) > 0)


def _counts(params: TemplateParams):
    """Templates and passages of each stretch of texts: key, number of rows that hold it, smallest id."""

    def job(batches):
        for batch in batches:
            buf, offs = flat(batch.column("text"))
            docs = batch.column("doc_id").to_numpy(zero_copy_only=False).astype(np.float64) if batch.column("doc_id").null_count else np.asarray(batch.column("doc_id"))
            ids = np.where(np.isnan(docs), np.iinfo(np.int64).max, docs).astype(np.int64) if docs.dtype.kind == "f" else docs
            for i, j in slices(offs, CHUNK):
                line, _, a, b, line_row, _ = spans(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i], params)
                if not len(line):
                    continue
                row = line_row[line]
                order = np.lexsort((row, b, a))
                a, b, row = a[order], b[order], row[order]
                new_key = np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1]))
                new_row = new_key | np.append(True, row[1:] != row[:-1])
                at = np.flatnonzero(new_key)
                held = np.add.reduceat(new_row.astype(np.int64), at)
                least = np.minimum.reduceat(ids[i:j][row], at)
                yield pa.RecordBatch.from_arrays([pa.array(a[at].view(np.int64)), pa.array(b[at].view(np.int64)), pa.array(held), pa.array(least)], ["a", "b", "n", "first"])

    return job


def recurring(documents: DataFrame, params: TemplateParams = TemplateParams()) -> DataFrame:
    """a, b, n, first: the templates of at least `min_docs` documents and the passages of `passage_docs`, by key."""
    rows = texts(documents, binary=True).mapInArrow(tidy(_counts(params)), "a long, b long, n long, first long")
    return rows.groupBy("a", "b").agg(F.sum("n").alias("n"), F.min("first").alias("first")).where(F.col("n") >= F.when(F.col("a").bitwiseAND(1) == 1, params.passage_docs).otherwise(params.min_docs))


def _stripped(buf, offs, gone, line_row, ends):
    """The texts without the marked lines, and how many lines each had and lost."""
    n = len(offs) - 1
    lines, lost = np.bincount(line_row, minlength=n), np.bincount(line_row[gone], minlength=n)
    out, raw = [], buf.tobytes()
    first = np.cumsum(lines) - lines
    for r in range(n):
        if not lost[r]:
            out.append(raw[offs[r] : offs[r + 1]])
            continue
        kept, at = [], int(offs[r])
        for k in range(first[r], first[r] + lines[r]):
            if not gone[k]:
                kept.append(raw[at : ends[k]])
            at = int(ends[k]) + 1
        out.append(b"\n".join(kept))
    return out, lines, lost


def _cleaned_batches(mark):
    """Runs `mark` (which lines go) over stretches of a batch: bytes of the cleaned texts, lines and losses."""

    def run(batch):
        buf, offs = flat(batch.column("text"))
        text, lines, lost = [], [], []
        for i, j in slices(offs, CHUNK):
            t, n, k = mark(batch.slice(i, j - i), buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i])
            text += t
            lines.append(n)
            lost.append(k)
        zero = np.zeros(0, np.int64)
        return text, np.concatenate(lines or [zero]), np.concatenate(lost or [zero])

    return run


def told(documents: DataFrame) -> list[str]:
    """What `cleaned` calls its two counts: `_lines` and `_lost`, unless the documents have such columns."""
    return fresh(documents, "_lines", "_lost")


def cleaned(documents: DataFrame, params: TemplateParams = TemplateParams()) -> DataFrame:
    """All columns of the documents, the text without recurring lines, and its lines before and those lost (see `told`)."""
    spark = documents.sparkSession
    n_lines, n_lost = told(documents)
    key, digest, marks = fresh(documents, "_key", "_digest", "_gone")
    found = staged(recurring(documents, params), "templates")
    few = found.limit(params.broadcast_most + 1).count() <= params.broadcast_most
    schema = documents.schema
    wide = documents.withColumn(key, F.coalesce(F.col("doc_id").cast("long"), F.lit(np.iinfo(np.int64).min)))
    if few:
        table = found.select("a", "b", "first").toArrow()  # at most broadcast_most rows
        a, b = (np.asarray(table[c]).view(np.uint64) for c in ("a", "b"))
        both = mixed(a) ^ b
        order = np.argsort(both)
        sent = spark.sparkContext.broadcast((both[order], b[order], np.asarray(table["first"])[order]))

        def mark(batch, buf, offs):
            both, second, first = sent.value
            line, last, a, b, line_row, ends = spans(buf, offs, params)
            gone = np.zeros(len(ends), bool)
            if len(both) and len(line):
                at = np.minimum(np.searchsorted(both, mixed(a) ^ b), len(both) - 1)
                ids = np.asarray(batch.column(key))[line_row[line]]
                hit = (both[at] == (mixed(a) ^ b)) & (second[at] == b) & (first[at] < ids)
                gone = _gone(line[hit], last[hit], buf, ends)
            return _stripped(buf, offs, gone, line_row, ends)

        source = wide
    else:
        # Too many to send: lines meet their templates in a join, and each row gets the numbers of its lines that go.
        text = F.coalesce(F.col("text").cast("string"), F.lit(""))
        wide = wide.withColumn(digest, F.sha2(text, 256))
        own = wide.select(F.col(key).alias("key"), F.col(digest).alias("h"), text.cast("binary").alias("text"))

        def keys(batches):
            for batch in batches:
                buf, offs = flat(batch.column("text"))
                for i, j in slices(offs, CHUNK):
                    line, last, a, b, line_row, ends = spans(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i], params)
                    row = line_row[line]
                    start = np.searchsorted(line_row, np.arange(j - i))
                    take = pa.array(row + i)
                    yield pa.RecordBatch.from_arrays([batch.column("key").take(take), batch.column("h").take(take), pa.array((line - start[row]).astype(np.int32)), pa.array((last - start[row]).astype(np.int32)), pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["key", "h", "line", "last", "a", "b"])

        hits = own.mapInArrow(tidy(keys), "key long, h string, line int, last int, a long, b long").join(found, ["a", "b"]).where("first < key")
        hits = hits.groupBy(F.col("key").alias(key), F.col("h").alias(digest)).agg(F.collect_set(F.struct("line", "last")).alias(marks))
        source = wide.join(hits, [key, digest], "left")

        def mark(batch, buf, offs):
            _, _, _, _, line_row, ends = spans(buf, offs, params)
            start = np.searchsorted(line_row, np.arange(len(offs) - 1))
            hits = [(start[r] + x["line"], start[r] + x["last"]) for r, found in enumerate(batch.column(marks).to_pylist()) for x in found or ()]
            first, last = np.array(hits, np.int64).reshape(-1, 2).T
            gone = _gone(first, last, buf, ends)
            return _stripped(buf, offs, gone, line_row, ends)

    run = _cleaned_batches(mark)
    from pyspark.sql.types import IntegerType, StructType

    names = schema.fieldNames()

    def job(batches):
        for batch in batches:
            text, lines, lost = run(batch)
            old = batch.column("text")
            new = pa.array([t.decode("utf-8", "replace") for t in text], old.type)
            if old.null_count:
                import pyarrow.compute as pc

                new = pc.if_else(old.is_valid(), new, old)
            yield pa.RecordBatch.from_arrays([*[new if c == "text" else batch.column(c) for c in names], pa.array(lines.astype(np.int32)), pa.array(lost.astype(np.int32))], [*names, n_lines, n_lost])

    return source.mapInArrow(tidy(job), StructType(list(schema.fields)).add(n_lines, IntegerType()).add(n_lost, IntegerType()))


def deduplicated(documents: DataFrame, params: TemplateParams = TemplateParams()) -> DataFrame:
    """The documents without recurring lines, in their own columns; those left blank by it go."""
    out, lost = cleaned(documents, params), F.col(told(documents)[1])
    if "n_chars" in documents.columns:
        kind = documents.schema["n_chars"].dataType
        out = out.withColumn("n_chars", F.when(lost > 0, F.char_length("text").cast(kind)).otherwise(F.col("n_chars")))
    return out.where((lost == 0) | F.col("text").rlike(r"[^ \t\n\x0B\f\r]")).select(documents.columns)


def op4_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole job: templates, and passages of 50 words from two documents on."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = cleaned(docs, PASSAGES)
    return out.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("_lines").cast("long").alias("n_lines"), F.col("_lost").cast("long").alias("n_dropped"), F.coalesce("text", F.lit("")).alias("text"))


def oracle(p: TemplateParams = TemplateParams(), source: str = "documents") -> str:
    """The same by strings: templates are lists of tokens with wildcards."""
    rest = f"list_slice(toks, {p.lead + 1}, len(toks))"
    return f"""
WITH base AS (SELECT row_number() OVER () AS rn, CAST(doc_id AS BIGINT) AS doc_id, coalesce(text, '') AS text FROM {source}),
lines AS (SELECT rn, doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS place FROM base),
tokens AS (SELECT rn, doc_id, line, place, list_transform(list_filter(regexp_split_to_array(line, '[\\t\\x0B\\f\\r ]+'), lambda x: x <> ''), lambda x: CASE WHEN regexp_matches(x, '[0-9]') THEN '<*>' ELSE x END) AS toks FROM lines),
variants AS (
  SELECT rn, doc_id, place, len(toks) || '|' || array_to_string(toks, ' ') AS template FROM tokens WHERE len(toks) >= {p.min_tokens} AND len(toks) - {p.lead} < {p.min_rest}
  UNION ALL
  SELECT rn, doc_id, place, len(toks) || '|' || v || '|' || array_to_string(list_slice(toks, 1, {p.lead}), ' ') || '|' || array_to_string(list_transform(list_zip({rest}, range(len({rest}))), lambda z: CASE WHEN z[2] * {p.segments} // len({rest}) = v THEN '<*>' ELSE z[1] END), ' ') AS template
  FROM tokens, range({p.segments}) AS r(v) WHERE len(toks) - {p.lead} >= {p.min_rest}
),
recurring AS (SELECT template, min(doc_id) AS first_of FROM (SELECT DISTINCT rn, doc_id, template FROM variants) GROUP BY template HAVING count(*) >= {p.min_docs}),
gone AS (SELECT DISTINCT rn, place FROM variants JOIN recurring USING (template) WHERE first_of < doc_id),
kept AS (SELECT l.rn, count(*) AS n_lines, count(g.place) AS n_dropped, string_agg(CASE WHEN g.place IS NULL THEN line END, chr(10) ORDER BY l.place) AS text
  FROM lines l LEFT JOIN gone g ON g.rn = l.rn AND g.place = l.place GROUP BY l.rn)
SELECT b.doc_id, n_lines, n_dropped, coalesce(k.text, '') AS text FROM base b JOIN kept k USING (rn)
"""


def passages_oracle(p: TemplateParams = PASSAGES, source: str = "documents") -> str:
    """Templates as above, and passages by comparing the words of stretches of lines."""
    before, after = oracle(p, source).split("gone AS (")
    templates, rest = after.split("),\nkept AS", 1)
    stretches = f"""
held AS (SELECT *, row_number() OVER o AS k, sum(words) OVER o - words AS c FROM (SELECT rn, doc_id, place, len(list_filter(regexp_split_to_array(line, '[\\t\\x0B\\f\\r ]+'), lambda x: x <> '')) AS words, array_to_string(list_filter(regexp_split_to_array(line, '[\\t\\x0B\\f\\r ]+'), lambda x: x <> ''), ' ') AS line FROM lines) WHERE words > 0 WINDOW o AS (PARTITION BY rn ORDER BY place)),
stretches AS (
  SELECT f.rn, f.k AS lo, min(g.k) AS hi FROM held f JOIN held g ON g.rn = f.rn AND g.k >= f.k AND g.c + g.words - f.c >= {p.passage_words} GROUP BY f.rn, f.k
  UNION
  SELECT g.rn, max(f.k), g.k FROM held f JOIN held g ON g.rn = f.rn AND g.k >= f.k AND g.c + g.words - f.c >= {p.passage_words} GROUP BY g.rn, g.k
),
passages AS (SELECT s.rn, s.lo, s.hi, any_value(h.doc_id) AS doc_id, string_agg(h.line, chr(10) ORDER BY h.k) AS passage FROM stretches s JOIN held h ON h.rn = s.rn AND h.k BETWEEN s.lo AND s.hi GROUP BY s.rn, s.lo, s.hi),
shared AS (SELECT passage, min(doc_id) AS first_of FROM passages GROUP BY passage HAVING count(DISTINCT rn) >= {p.passage_docs}),
gone AS ({templates} UNION SELECT h.rn, h.place FROM passages q JOIN shared USING (passage) JOIN held h ON h.rn = q.rn AND h.k BETWEEN q.lo AND q.hi WHERE first_of < q.doc_id)"""
    return f"{before.rstrip()}{stretches},\nkept AS{rest}"
