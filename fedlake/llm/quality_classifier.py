"""Quality by ordinal cumulative-link regression on graded ratings.

A document's features are the distinct normalised tokens of its whole text,
hashed into ``2 ** bits`` buckets: words without case and surrounding marks,
their beginnings of 4 to 6 letters, the marks themselves, and whether a word is
written in capitals. One weight vector is shared by all grades; grade ``j`` or better has probability
``sigmoid(w . x - threshold_j)`` with ordered thresholds. Selection uses the
tail probability of a grade and the expected grade.

The fit uses a bounded sample of rated rows (``SAMPLE_ROWS``, chosen by hash of
the id, so it doesn't depend on order or size of the table). A score test at
the model without features keeps the buckets whose link to the grade can't be
chance (``MIN_Z`` standard errors, ``MIN_ROWS`` rows); weights of all others are
zero, so the many words of a long document don't add up to noise. All documents
are scored over whole texts in one pass.

Grades of the rated rows here: 0 toxic, 1 not toxic but poor, 2 good.

Defined results: a null or empty text scores by the bias alone, that is by the
thresholds; ratings with null parts are skipped; a rating that repeats counts
once by its lowest grade; without two grades among the ratings every document
gets the one grade there is (or the top grade without any) and is kept if it
passes the tail; an empty table gives no rows; extra columns are ignored by
``score`` and kept by ``select``.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fedlake.llm.runtime import CACHE_WORDS, WordCache, slices, strings

BITS = 22
SAMPLE_ROWS = 12_000
MIN_ROWS = 8
MIN_Z = 6.0
GRADES = 3
#: Selection: probability of the top grade.
TAIL_GRADE = 2
TAIL = 0.5
L2 = 5e-5
PASSES = 300
#: Rows whose buckets are counted at a time.
FIT_ROWS = 1000


def _is_word(c: str) -> bool:
    return c.isalnum() or c == "_"


def token_buckets(token: str, bits: int = BITS) -> tuple[int, ...]:
    """Feature buckets of one whitespace token."""
    start, end = 0, len(token)
    while start < end and not _is_word(token[start]):
        start += 1
    while end > start and not _is_word(token[end - 1]):
        end -= 1
    shift, names = 32 - bits, []
    if start < end:
        body = token[start:end]
        lower = body.lower()
        names.append("w:" + lower)
        names += [f"p{k}:{lower[:k]}" for k in (4, 5, 6) if len(lower) > k]
        if len(body) > 1 and body.isupper():
            names.append("capitals")
    if start:
        names.append("f:" + token[:start])
    if end < len(token):
        names.append("b:" + token[end:])
    return tuple([crc32(n.encode()) >> shift for n in names])


def variety_bucket(n_words: int, n_distinct: int, bits: int = BITS) -> int:
    """Feature bucket of a text's share of distinct words, in eighths, by the power of two of its length."""
    return crc32(f"d{n_words.bit_length()}:{8 * n_distinct // max(1, n_words)}".encode()) >> (32 - bits)


class Featurizer:
    """Distinct buckets of texts for one Python worker; with ``wanted``, only those buckets."""

    def __init__(self, bits: int = BITS, wanted: set[int] | None = None):
        self.bits, self.wanted = bits, wanted
        self.cache = WordCache(3 * CACHE_WORDS)

    def _buckets(self, token: str) -> tuple[int, ...]:
        found = token_buckets(token, self.bits)
        return found if self.wanted is None else tuple(self.wanted.intersection(found))

    def __call__(self, text: str) -> np.ndarray:
        words = text.split()
        tokens = set(words)
        new = self.cache.missing(tokens)
        if len(new) < len(tokens):  # the cache may have been emptied just now
            new = [t for t in tokens if t not in self.cache]
        self.cache.update((t, self._buckets(t)) for t in new)
        found = {variety_bucket(len(words), len(tokens), self.bits)}
        found.update(*filter(None, map(self.cache.__getitem__, tokens)))
        return np.fromiter(found, np.int64, len(found))


@dataclass
class OrdinalModel:
    """Sparse weights over buckets and ordered thresholds."""

    buckets: np.ndarray
    weights: np.ndarray
    thresholds: np.ndarray
    bits: int = BITS

    def dense(self) -> np.ndarray:
        out = np.zeros(1 << self.bits, np.float32)
        out[self.buckets] = self.weights
        return out

    def tails(self, score: np.ndarray) -> np.ndarray:
        """P(grade >= j) for j = 1.. ."""
        return 1 / (1 + np.exp(-np.clip(score[:, None] - self.thresholds[None, :], -50, 50)))


def fit_ordinal(flat: np.ndarray, sizes: np.ndarray, grades: np.ndarray, n_grades: int, bits: int = BITS, l2: float = L2, passes: int = PASSES, min_rows: int = MIN_ROWS, min_z: float = MIN_Z) -> OrdinalModel:
    """Maximum likelihood of the cumulative logits with a ridge, by accelerated full-batch gradients.

    flat, sizes: buckets of all rows one after the other, and how many each row
    has. Thresholds are a first value and positive gaps (exponentials), which
    keeps their order. Rare grades weigh up to the geometric mean of equal and
    natural weights. The fixed number of passes stops early on purpose: it regularises.
    """
    n, ends = len(sizes), np.cumsum(sizes)
    share = np.bincount(grades, minlength=n_grades) / max(1, n)
    if n == 0 or (share > 0).sum() < 2:
        only = int(grades[0]) if n else n_grades - 1
        return OrdinalModel(np.zeros(0, np.int64), np.zeros(0, np.float32), np.array([-30.0 if j <= only else 30.0 for j in range(1, n_grades)]), bits)
    weight = np.sqrt(1 / (n_grades * np.maximum(share, 1e-9)))[grades]
    weight /= weight.sum()
    above = np.array([(share[j:].sum()) for j in range(1, n_grades)]).clip(1e-6, 1 - 1e-6)
    start = np.maximum.accumulate(np.log(1 - above) - np.log(above) + 1e-3 * np.arange(n_grades - 1))
    below = np.concatenate([[0.0], np.cumsum(share)])
    pull = (below[grades] + below[grades + 1]) - 1  # score of the latent at the model of thresholds alone
    pull -= np.average(pull, weights=weight)
    scaled = pull * weight * n
    count, moved = np.zeros(1 << bits, np.int32), np.zeros(1 << bits, np.float32)
    for k in range(0, n, FIT_ROWS):  # a few rows at a time: the driver holds the buckets once
        part = flat[ends[k] - sizes[k] : ends[min(k + FIT_ROWS, n) - 1]]
        count += np.bincount(part, minlength=1 << bits).astype(np.int32)
        moved += np.bincount(part, np.repeat(scaled[k : k + FIT_ROWS], sizes[k : k + FIT_ROWS]), 1 << bits).astype(np.float32)
    frequent = (count >= min_rows) & (np.abs(moved) >= min_z * np.sqrt(np.maximum(count * scaled.var(), 1e-12)))
    used = np.flatnonzero(frequent)
    p = len(used)
    at = np.flatnonzero(frequent[flat])
    col, owner = np.searchsorted(used, flat[at]), np.searchsorted(ends, at, side="right")
    theta = np.concatenate([np.zeros(p), [start[0]], np.log(np.maximum(np.diff(start), 1e-3))])
    df = np.bincount(col, minlength=p)
    step = np.concatenate([1 / np.sqrt(1 + df / n * 20), np.full(n_grades - 1, 1.0)])

    def gradient(theta):
        w, first, gaps = theta[:p], theta[p], np.exp(theta[p + 1 :])
        cuts = first + np.concatenate([[0.0], np.cumsum(gaps)])
        score = np.bincount(owner, w[col], n)
        sig = lambda x: 1 / (1 + np.exp(-np.clip(x, -50, 50)))
        tail = np.column_stack([np.ones(n), sig(score[:, None] - cuts[None, :]), np.zeros(n)])
        upper, lower = tail[np.arange(n), grades], tail[np.arange(n), grades + 1]
        mass = np.maximum(upper - lower, 1e-12)
        du, dl = upper * (1 - upper), lower * (1 - lower)
        by_score = -weight * (du - dl) / mass
        by_cut = np.zeros((n, n_grades + 1))
        by_cut[np.arange(n), grades] += weight * du / mass
        by_cut[np.arange(n), grades + 1] -= weight * dl / mass
        cut = by_cut[:, 1:-1].sum(axis=0)
        tail_sum = np.cumsum(cut[::-1])[::-1]
        g = np.concatenate([np.bincount(col, by_score[owner], p) + l2 * w, [tail_sum[0]], tail_sum[1:] * gaps])
        return g

    mean, var, look = np.zeros_like(theta), np.zeros_like(theta), theta
    for t in range(1, passes + 1):
        g = gradient(look)
        mean, var = 0.9 * mean + 0.1 * g, 0.999 * var + 0.001 * g * g
        rate = 0.1 * step * (1 - t / (passes + 1)) + 0.002
        look = look - rate * (mean / (1 - 0.9**t)) / (np.sqrt(var / (1 - 0.999**t)) + 1e-8)
    cuts = look[p] + np.concatenate([[0.0], np.cumsum(np.exp(look[p + 1 :]))])
    return OrdinalModel(used, look[:p].astype(np.float32), cuts, bits)


def grade(quality: Column, toxic: Column) -> Column:
    return F.when(toxic != 0, F.lit(0)).when(quality == 0, F.lit(1)).otherwise(F.lit(2))


def rated_sample(labels: DataFrame, rows: int = SAMPLE_ROWS) -> DataFrame:
    """(doc_id, grade) of at most ``rows`` rated ids, smallest hash first."""
    rated = labels.where("doc_id is not null and quality is not null and toxic is not null")
    graded = rated.select(F.col("doc_id").cast("long").alias("doc_id"), grade(F.col("quality"), F.col("toxic")).alias("grade")).groupBy("doc_id").agg(F.min("grade").alias("grade"))
    # every partition sends its first rows to the driver, so only hashes that can be among the first take part
    total = graded.count()
    share = (rows + 10 * math.sqrt(rows) + 100) / max(1, total)
    if share < 1:
        near = graded.where(F.xxhash64("doc_id") < int(share * (1 << 64)) - (1 << 63))
        graded = near if near.count() >= rows else graded
    return graded.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)


def fit(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS) -> OrdinalModel:
    """Fit on the sample's documents; what reaches the driver is bounded by ``rows`` feature lists."""
    sample = F.broadcast(rated_sample(labels, rows).withColumnRenamed("doc_id", "_rated"))  # at most ``rows`` pairs of numbers
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(sample, F.col("doc_id") == F.col("_rated")).select("doc_id", "grade", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        features = Featurizer()
        for part in slices(batches, "text"):
            found = [features(t).astype(np.int32) for t in strings(part, "text")]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("grade"), pa.array(found, pa.list_(pa.int32()))], ["doc_id", "grade", "buckets"])

    found = texts.mapInArrow(run, "doc_id long, grade int, buckets array<int>").toArrow().sort_by("doc_id")
    if not found.num_rows:
        return fit_ordinal(np.zeros(0, np.int32), np.zeros(0, np.int64), np.zeros(0, np.int64), GRADES)
    lists = found.column("buckets").combine_chunks()
    return fit_ordinal(np.asarray(lists.flatten()), np.asarray(lists.value_lengths()).astype(np.int64), np.asarray(found.column("grade")).astype(np.int64), GRADES)


def score(docs: DataFrame, model: OrdinalModel, tail_grade: int = TAIL_GRADE, tail: float = TAIL) -> DataFrame:
    """(doc_id, latent, expected_grade, tail_probability, kept) of every document."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the buckets seen in the sample

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights = shared.value.dense()
        features = Featurizer(shared.value.bits, set(shared.value.buckets.tolist()))
        for part in slices(batches, "text"):
            latent = np.array([float(weights[features(t)].sum(dtype=np.float64)) for t in strings(part, "text")])
            tails = shared.value.tails(latent)
            top = tails[:, tail_grade - 1]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(latent), pa.array(tails.sum(axis=1)), pa.array(top), pa.array(top >= tail)], ["doc_id", "latent", "expected_grade", "tail_probability", "kept"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, latent double, expected_grade double, tail_probability double, kept boolean")


def select(docs: DataFrame, model: OrdinalModel, tail_grade: int = TAIL_GRADE, tail: float = TAIL) -> DataFrame:
    """The accepted documents with all their columns, in one pass without a join."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights = shared.value.dense()
        features = Featurizer(shared.value.bits, set(shared.value.buckets.tolist()))
        for part in slices(batches, "text"):
            latent = np.array([float(weights[features(t)].sum(dtype=np.float64)) for t in strings(part, "text")])
            yield part.filter(pa.array(shared.value.tails(latent)[:, tail_grade - 1] >= tail))

    return docs.mapInArrow(run, schema)
