"""Quality classifier: ordinal cumulative-link regression on graded ratings.

One weight vector over hashed text features is shared by all grades; ordered thresholds cut its score into
grades, so P(grade >= k) = sigmoid(score - threshold[k-1]). The features of a text are the distinct hashed
letter runs (lower case), their first bytes and symbol runs it holds, and a few banded rates (repeated words, capital words,
symbols). Featurising is plain numpy over the bytes of many texts at once.

The model is fitted on the driver on at most `max_labelled` labelled rows, taken in the order of a hash of the
id (a documented bound that doesn't depend on the size of the corpus); every document is scored.

Cases: null or empty text has only the rates as features and still gets a score; repeated ids are scored row by
row, and fitted with the smallest of their texts; a null id is scored and never fitted; an empty table gives no row; without usable labels (none, or one grade only) grades are null and nothing is rejected; labels with null
fields are left out; other columns are ignored by `score` and kept by `selected`.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcomm.llm.common import flat, mixed, run_hashes, slices, texts, tidy

SPACE_BITS = 22
CHUNK = 1 << 18
#: Bytes of a long word that make a feature of their own, so that inflected forms share a weight.
STEM = 5

#: Byte classes: 0 blank and control, 1 letter (all of UTF-8 beyond ASCII too), 2 digit, 3 symbol.
CLASS = np.full(256, 3, np.uint8)
CLASS[:33] = 0
CLASS[127] = 0
CLASS[128:] = 1
CLASS[48:58] = 2
CLASS[65:91] = 1
CLASS[97:123] = 1
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


@dataclass(frozen=True)
class QualityParams:
    max_labelled: int = 6000
    min_rows: int = 10
    min_z: float = 5.0
    l2: float = 0.0002
    steps: int = 400
    rate: float = 0.05
    reject_below_grade: int = 2
    min_tail: float = 0.5
    seed: int = 7


@dataclass
class OrdinalModel:
    """Weights at hashed places (sparse) and one threshold between each grade and the next."""

    places: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    weights: np.ndarray = field(default_factory=lambda: np.zeros(0, np.float32))
    thresholds: np.ndarray = field(default_factory=lambda: np.zeros(0))

    def dense(self) -> np.ndarray:
        w = np.zeros(1 << SPACE_BITS, np.float32)
        w[self.places] = self.weights
        return w

    def tails(self, scores: np.ndarray) -> np.ndarray:
        """P(grade >= k) for k = 1..K, one column each."""
        return 1.0 / (1.0 + np.exp(-np.clip(scores[:, None] - self.thresholds[None, :], -60, 60)))


def featurised(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, place) of every distinct hashed feature of each row."""
    n = len(offs) - 1
    rows_out, places_out = [], []
    for i, j in slices(offs, CHUNK):
        r, p = _chunk(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i])
        rows_out.append(r + i)
        places_out.append(p)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(rows_out), np.concatenate(places_out)


def tails_of(buf: np.ndarray, offs: np.ndarray, model: OrdinalModel, w: np.ndarray) -> np.ndarray:
    """P(grade >= k) of each row, rounded; features live only as long as their stretch of rows, however many a batch has."""
    scores = np.zeros(len(offs) - 1)
    for i, j in slices(offs, CHUNK):
        rows, places = _chunk(buf[offs[i] : offs[j]], offs[i : j + 1] - offs[i])
        scores[i:j] = np.bincount(rows, weights=w[places], minlength=j - i)
    return np.round(model.tails(scores), 6)


def _chunk(b: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    n, size = len(offs) - 1, len(b)
    if size:
        kind, low = CLASS[b], LOWER[b]
        edge = np.ones(size, bool)
        edge[1:] = kind[1:] != kind[:-1]
        edge[offs[:-1][offs[:-1] < size]] = True
        starts = np.flatnonzero(edge)
        lengths = np.diff(np.append(starts, size))
        h, k = run_hashes(low, starts, lengths), kind[starts]
        row = np.searchsorted(offs, starts, side="right") - 1
        word = k == 1
        wh, wrow = h[word], row[word]
        same = np.zeros(len(wh), bool)
        same[1:] = (wh[1:] == wh[:-1]) & (wrow[1:] == wrow[:-1])
        ws, wl = starts[word], lengths[word]
        upper = (b[ws] < 91) & (b[ws + wl - 1] < 91) & (wl > 1)
        sym = k == 3
        words, syms = np.bincount(wrow, minlength=n), np.bincount(row[sym], minlength=n)
        repeats = np.bincount(wrow[same], minlength=n)
        capitals = np.bincount(wrow[upper], minlength=n)
        keep = word | sym
        long = wl > STEM
        stem = np.zeros(int(long.sum()), np.uint64)
        for c in range(STEM):
            stem = (stem << np.uint64(8)) | low[ws[long] + c]
        hash_rows = np.concatenate([row[keep], wrow[long]])
        hash_vals = np.concatenate([h[keep] ^ (k[keep].astype(np.uint64) << np.uint64(60)), mixed(stem + np.uint64(1 << 50))])
    else:
        words = syms = repeats = capitals = np.zeros(n, np.int64)
        hash_rows, hash_vals = np.zeros(0, np.int64), np.zeros(0, np.uint64)
    per = np.maximum(words, 1)
    bands = np.stack([np.minimum(8, (16 * x) // per) + 16 * c for c, x in enumerate((repeats, capitals, syms), 1)], 1)
    banded = mixed(bands.ravel().astype(np.uint64) + np.uint64(1 << 40))
    rows = np.concatenate([hash_rows, np.repeat(np.arange(n), 3)])
    places = (np.concatenate([hash_vals, banded]) >> np.uint64(64 - SPACE_BITS)).astype(np.int64)
    both = np.unique(rows * (1 << SPACE_BITS) + places)
    return both >> SPACE_BITS, both & ((1 << SPACE_BITS) - 1)


def fit_ordinal(rows: np.ndarray, places: np.ndarray, grades: np.ndarray, params: QualityParams) -> OrdinalModel:
    """Penalised maximum likelihood of the proportional-odds model by Adam steps over the full sample."""
    classes = int(grades.max()) + 1 if len(grades) else 0
    if classes < 2 or len(np.unique(grades)) < 2:
        return OrdinalModel()
    used, col, held = np.unique(places, return_inverse=True, return_counts=True)
    # Rare features, and those whose rows lie above each threshold about as often as all rows, tell nothing beyond this sample.
    often = np.zeros(len(used), bool)
    for k in range(1, classes):
        y = (grades >= k).astype(np.float64)
        z = (np.bincount(col, weights=y[rows]) / held - y.mean()) / (y.std() + 1e-9) * np.sqrt(held)
        often |= np.abs(z) >= params.min_z
    often &= held >= params.min_rows
    rows, col = rows[often[col]], (np.cumsum(often) - 1)[col[often[col]]]
    used = used[often]
    n, d, cuts = len(grades), len(used), classes - 1
    share = np.clip([(grades >= k).mean() for k in range(1, classes)], 1e-3, 1 - 1e-3)
    theta = -np.log(share / (1 - share))
    gaps = np.log(np.maximum(np.diff(theta), 1e-2))
    state = np.concatenate([np.zeros(d), theta[:1], gaps])
    m, v = np.zeros_like(state), np.zeros_like(state)
    weight = np.sqrt(n / (len(np.unique(grades)) * np.maximum(np.bincount(grades, minlength=classes), 1)))[grades]
    for t in range(1, params.steps + 1):
        w = state[:d]
        cut = np.cumsum(np.concatenate([state[d : d + 1], np.exp(state[d + 1 :])]))
        score = np.bincount(rows, weights=w[col], minlength=n)
        # P(y = k) is the difference of two neighbouring tails; its gradient comes from both.
        tail = 1 / (1 + np.exp(-np.clip(score[:, None] - cut[None, :], -40, 40)))
        padded = np.hstack([np.ones((n, 1)), tail, np.zeros((n, 1))])
        p = np.maximum(padded[np.arange(n), grades] - padded[np.arange(n), grades + 1], 1e-9)
        slope = tail * (1 - tail)
        hi = np.where(grades[:, None] == np.arange(1, classes)[None, :], slope, 0)
        lo = np.where(grades[:, None] == np.arange(0, cuts)[None, :], slope, 0)
        g_cut_rows = (hi - lo) / p[:, None] * weight[:, None]
        g_score = -g_cut_rows.sum(1)
        g_w = np.bincount(col, weights=g_score[rows], minlength=d) / n + params.l2 * w
        g_cut = g_cut_rows.sum(0) / n
        back = np.cumsum(g_cut[::-1])[::-1]
        grad = np.concatenate([g_w, back[:1], back[1:] * np.exp(state[d + 1 :])])
        m = 0.9 * m + 0.1 * grad
        v = 0.999 * v + 0.001 * grad**2
        state = state - params.rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    w = state[:d]
    keep = np.abs(w) > 1e-3
    return OrdinalModel(used[keep], w[keep].astype(np.float32), np.cumsum(np.concatenate([state[d : d + 1], np.exp(state[d + 1 :])])))


def graded(labels: DataFrame) -> DataFrame:
    """Ratings from the two flags: 0 low quality, 1 good but toxic, 2 good and clean."""
    q, t = F.col("quality").cast("int"), F.coalesce(F.col("toxic").cast("int"), F.lit(0))
    return labels.where(F.col("doc_id").isNotNull() & q.isNotNull()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min(F.when(q < 1, 0).when(t > 0, 1).otherwise(2)).alias("grade"))


def _features_job(batches):
    for batch in batches:
        buf, offs = flat(batch.column("text"))
        rows, places = featurised(buf, offs)
        ends = np.searchsorted(rows, np.arange(batch.num_rows + 1))
        yield pa.RecordBatch.from_arrays([batch.column("grade"), pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(places))], ["grade", "places"])


def train(documents: DataFrame, ratings: DataFrame, params: QualityParams = QualityParams()) -> OrdinalModel:
    """Fit on the first `max_labelled` ratings in hash order; only their feature lists reach the driver."""
    chosen = ratings.orderBy(F.xxhash64("doc_id", F.lit(params.seed)), "doc_id").limit(params.max_labelled)
    body = texts(documents, binary=True).join(F.broadcast(chosen), "doc_id")  # bounded by max_labelled rows
    one = body.groupBy("doc_id").agg(F.min("text").alias("text"), F.min("grade").alias("grade"))  # of rows that repeat an id, the smallest text
    got = one.select("text", "grade").mapInArrow(tidy(_features_job), "grade int, places array<long>").toArrow()
    if not got.num_rows:
        return OrdinalModel()
    lists = got["places"].combine_chunks()
    sizes = np.diff(np.asarray(lists.offsets))
    return fit_ordinal(np.repeat(np.arange(got.num_rows), sizes), np.asarray(lists.flatten()), np.asarray(got["grade"]).astype(np.int64), params)


def score(documents: DataFrame, model: OrdinalModel, params: QualityParams = QualityParams()) -> DataFrame:
    """doc_id, expected_grade, p_ge_1..p_ge_K, rejected; one row for each input row, no shuffle."""
    cuts = len(model.thresholds)
    names = [f"p_ge_{k}" for k in range(1, max(cuts, 2) + 1)]
    schema = "doc_id long, expected_grade double, " + ", ".join(f"{n} double" for n in names) + ", rejected boolean"
    sent = documents.sparkSession.sparkContext.broadcast(model)
    k = min(params.reject_below_grade, cuts)

    def job(batches):
        model = sent.value
        w = model.dense() if cuts else None
        for batch in batches:
            n = batch.num_rows
            if not cuts:
                none = pa.nulls(n, pa.float64())
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), none, *[none] * len(names), pa.array(np.zeros(n, bool))], ["doc_id", "expected_grade", *names, "rejected"])
                continue
            buf, offs = flat(batch.column("text"))
            tails = tails_of(buf, offs, model, w)
            cols = [pa.array(tails[:, c]) if c < cuts else pa.nulls(n, pa.float64()) for c in range(len(names))]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.round(tails.sum(1), 6)), *cols, pa.array(tails[:, k - 1] < params.min_tail)], ["doc_id", "expected_grade", *names, "rejected"])

    return texts(documents, binary=True).mapInArrow(tidy(job), schema)


def selected(documents: DataFrame, model: OrdinalModel, params: QualityParams = QualityParams()) -> DataFrame:
    """The documents that aren't rejected, with all their columns, rejected row by row."""
    if not len(model.thresholds):
        return documents
    k = min(params.reject_below_grade, len(model.thresholds))
    sent = documents.sparkSession.sparkContext.broadcast(model)

    def job(batches):
        model = sent.value
        w = model.dense()
        for batch in batches:
            buf, offs = flat(batch.column("text"))
            tails = tails_of(buf, offs, model, w)
            yield batch.filter(pa.array(tails[:, k - 1] >= params.min_tail))

    return documents.mapInArrow(tidy(job), documents.schema)


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return score(docs, train(docs, graded(spark.read.parquet(f"{sf_dir}/labels.parquet"))))
