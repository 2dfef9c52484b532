"""Quality rules with robust multivariate outliers.

Base rules reject very short and very repetitive texts. The others become
transformed statistic vectors, and every group of language and source gets a
minimum-covariance-determinant estimate of their centre and scatter. Starts are
fixed ones (quartile widths around the median and both quartiles, and the plain
moments) and drawn ones (a few points each). Concentration steps alternate between
the covariance of the three quarters of rows nearest to the centre and distances
under it; after two of them the starts with the smallest determinants go on until
their determinant doesn't change any more. The smallest one wins; a reweighted
estimate over the rows inside the 97.5 % ellipsoid follows. A document is rejected
if its squared Mahalanobis distance exceeds the chi-square quantile of ``level``.

Scatter has a floor per statistic: differences below it don't matter, and
statistics that are constant in a group can't reject everything else. Rows of a
group are therefore summed first in boxes as wide as the floors (number, sums and
products of the vectors, before the shuffle): a group of any number of rows comes
down to the boxes that it occupies, whose number the statistics' ranges bound.
Moments are exact sums over all rows; a box counts as near or far by its mean, and
the last one by the share that makes the number of rows right.

Groups under ``MIN_GROUP`` rows are estimated together with the other small
groups of their language, then of all languages; what is still too few has no
verdict beyond the base rules.

Defined results: a null text has no words and fails the base rules; null
language or source is a group of its own; repeated rows count and repeat; an
empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property, lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.llm.runtime import cut, fresh, one_blas_thread, slices, utf8

SYMBOLS = b"#*$%&|<>"
WINDOW = 5
MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20
#: Statistic vector: name and scatter floor (one standard deviation that never counts as unusual).
FEATURES = (("x_word_length", 0.20), ("x_symbols", 0.05), ("x_dup_lines", 0.10), ("x_repeats", 0.05))
NAMES = [n for n, _ in FEATURES]
FLOORS = [f for _, f in FEATURES]
KEEP_SHARE = 0.75
#: Starts drawn at random, those that go on after two steps, steps at most, and the change of a log determinant that ends them.
DRAWN = 40
BEST = 5
STEPS = 100
SETTLED = 1e-9
SEED = 11
LEVEL = 0.999999
MIN_GROUP = 50
#: Tables of one short row per group are broadcast up to this many groups; larger ones are joined by shuffle.
BROADCAST_GROUPS = 20_000
_CONTINUED = bytes(range(0x80, 0xC0))
_SPACES = b" \t\n\x0b\x0c\r"


# -- chi-square ---------------------------------------------------------
def chi2_cdf(x: float, d: int) -> float:
    """Regularised lower incomplete gamma at (d/2, x/2), by its series or continued fraction."""
    if x <= 0:
        return 0.0
    a, z = d / 2, x / 2
    front = math.exp(a * math.log(z) - z - math.lgamma(a))
    if z < a + 1:
        term = total = 1 / a
        n = a
        while abs(term) > 1e-16 * abs(total):
            n += 1
            term *= z / n
            total += term
        return front * total
    b, c = z + 1 - a, 1e300
    h = e = 1 / b
    for i in range(1, 500):
        an = -i * (i - a)
        b += 2
        e = 1 / (an * e + b)
        c = b + an / c
        h *= e * c
        if abs(e * c - 1) < 1e-15:
            break
    return 1 - front * h


@lru_cache(maxsize=64)
def chi2_quantile(p: float, d: int) -> float:
    low, high = 0.0, 1.0
    while chi2_cdf(high, d) < p:
        high *= 2
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if chi2_cdf(mid, d) < p else (low, mid)
    return (low + high) / 2


@lru_cache(maxsize=64)
def consistency(share: float, d: int) -> float:
    """What the covariance of the central ``share`` of a normal cloud must be multiplied by."""
    return share / chi2_cdf(chi2_quantile(share, d), d + 2)


# -- statistics of a text -----------------------------------------------
def repeat_words(ids: np.ndarray, doc: np.ndarray, n_docs: int) -> np.ndarray:
    """Words of each document inside five-word windows that occur twice or more in it. ids, doc: flat word ids and owners."""
    n = len(ids) - WINDOW + 1
    if n <= 0:
        return np.zeros(n_docs, np.int64)
    at = np.flatnonzero(doc[:n] == doc[WINDOW - 1 :])
    # windows are numbered pair by pair, exactly: 2 words, then 4, then 5; the owner joins the last pair
    pair = _number(ids[:-1], ids[1:])
    four = _number(pair[:-2], pair[2:])
    five = _number(four[:-1][at], ids[4:][at])
    key = _number(doc[at], five)
    twice = np.bincount(key)[key] > 1 if len(key) else np.zeros(0, bool)
    edge = np.zeros(len(ids) + 1, np.int64)
    np.add.at(edge, at[twice], 1)
    np.add.at(edge, at[twice] + WINDOW, -1)
    return np.bincount(doc[np.cumsum(edge[:-1]) > 0], minlength=n_docs)


def _number(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """A dense number for every distinct pair."""
    if not len(a):
        return np.zeros(0, np.int64)
    return np.unique(a.astype(np.int64) * (int(b.max()) + 1) + b, return_inverse=True)[1]


def dup_lines(text: bytes) -> tuple[int, int]:
    """(lines with a word that equal an earlier line, lines with a word)."""
    lines = [x for x in text.split(b"\n") if x and not x.isspace()]
    return len(lines) - len(set(lines)), len(lines)


def text_stats(texts: list[bytes]) -> dict[str, np.ndarray]:
    words = [t.split() for t in texts]
    n_words = np.fromiter(map(len, words), np.int64, len(texts))
    number: dict[bytes, int] = {}
    flat = np.fromiter((number.setdefault(w, len(number)) for ws in words for w in ws), np.int64, int(n_words.sum()))
    pairs = [dup_lines(t) for t in texts]
    return {
        "n_words": n_words,
        "word_chars": np.array([len(t.translate(None, _CONTINUED + _SPACES)) for t in texts], np.int64),
        "n_symbols": np.array([len(t) - len(t.translate(None, SYMBOLS)) for t in texts], np.int64),
        "n_dup_lines": np.array([p[0] for p in pairs], np.int64),
        "n_lines": np.array([p[1] for p in pairs], np.int64),
        "n_repeat_words": repeat_words(flat, np.repeat(np.arange(len(texts)), n_words), len(texts)),
    }


STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def statistics(docs: DataFrame) -> DataFrame:
    """doc_id, group keys, the statistics and base_failed of every document; one pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text"):
            stats = text_stats(utf8(part, "text"))
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("lang_key"), part.column("group_key"), *[pa.array(stats[k]) for k in (*STATS, "n_lines")]], ["doc_id", "lang_key", "group_key", *STATS, "n_lines"])

    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.to_json(F.struct(F.col("lang").cast("string").alias("l"))).alias("lang_key"),
        F.to_json(F.struct(F.col("lang").cast("string").alias("l"), F.col("source").cast("string").alias("s"))).alias("group_key"),
        F.col("text").cast("string").alias("text"),
    )
    out = rows.mapInArrow(run, "doc_id long, lang_key string, group_key string, " + ", ".join(f"{k} long" for k in (*STATS, "n_lines")))
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    return out.withColumn("base_failed", failed)


def vectors(stats: DataFrame) -> DataFrame:
    """The transformed statistic vector of each document with words."""
    n = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    return stats.withColumns(
        {
            "x_word_length": F.log(F.greatest(F.col("word_chars"), F.lit(1)) / n),
            "x_symbols": F.log1p(F.col("n_symbols") / n),
            "x_dup_lines": F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1)).cast("double"),
            "x_repeats": F.col("n_repeat_words") / n,
        }
    )


# -- robust estimates ---------------------------------------------------
def _by_group(table: DataFrame) -> DataFrame:
    """A table of one row per group, materialised and marked for broadcast where its count bounds its size."""
    table = cut(table)
    return F.broadcast(table) if table.count() <= BROADCAST_GROUPS else table


def assign_groups(rows: DataFrame) -> DataFrame:
    """``cell``: the group a row is estimated with, by the fallbacks for small groups; null if there are too few."""
    own = rows.groupBy("group_key", "lang_key").agg(F.count("*").alias("n"))
    by_lang, whole = Window.partitionBy("lang_key", F.col("n") < MIN_GROUP), Window.partitionBy("pooled")
    own = own.withColumn("pool", F.sum("n").over(by_lang))
    named = F.when(F.col("n") >= MIN_GROUP, F.concat(F.lit("g"), "group_key")).when(F.col("pool") >= MIN_GROUP, F.concat(F.lit("l"), "lang_key"))
    own = own.withColumn("cell", named).withColumn("pooled", F.col("cell").isNull())
    own = own.withColumn("rest", F.sum("n").over(whole))
    cell = F.coalesce("cell", F.when(F.col("rest") >= MIN_GROUP, F.lit("rest")))
    return rows.join(_by_group(own.select("group_key", cell.alias("cell"))), "group_key", "left")


def _entries() -> list[tuple[int, int]]:
    return [(i, j) for i in range(len(FEATURES)) for j in range(i, len(FEATURES))]


@dataclass
class Boxes:
    """Rows of one group in boxes: number, sums and summed products (by ``_entries``)."""

    n: np.ndarray
    sums: np.ndarray
    products: np.ndarray

    @cached_property
    def means(self) -> np.ndarray:
        return self.sums / self.n[:, None]

    def moments(self, part: np.ndarray, share: float) -> tuple[np.ndarray, np.ndarray]:
        """Centre and floored scatter over ``part`` of each box, as the central ``share`` of a normal cloud."""
        total = part @ self.n
        centre, second = part @ self.sums / total, part @ self.products / total
        cov = np.zeros((len(centre), len(centre)))
        for (i, j), x in zip(_entries(), second, strict=True):
            cov[i, j] = cov[j, i] = (x - centre[i] * centre[j]) * consistency(share, len(centre))
        return centre, floored(cov)

    def distances(self, centre: np.ndarray, cov: np.ndarray) -> np.ndarray:
        off = self.means - centre
        return np.einsum("ij,ij->i", off @ np.linalg.inv(cov), off)

    def nearest(self, distance: np.ndarray, rows: float) -> np.ndarray:
        """The part of each box that the given number of rows nearest to the centre takes."""
        order = np.argsort(distance, kind="stable")
        before = np.cumsum(self.n[order]) - self.n[order]
        part = np.zeros(len(order))
        part[order] = np.clip((rows - before) / self.n[order], 0, 1)
        return part

    def starts(self, rng: np.random.Generator) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        q = []
        for x in self.means.T:
            order = np.argsort(x, kind="stable")
            upto = np.cumsum(self.n[order])
            q.append(x[order[np.searchsorted(upto, upto[-1] * np.array([0.25, 0.5, 0.75]))]])
        q = np.array(q)
        spread = np.diag(np.maximum((q[:, 2] - q[:, 0]) / 1.349, FLOORS) ** 2)
        for k in (1, 0, 2):
            yield q[:, k], spread
        yield self.moments(np.ones(len(self.n)), 1.0)
        for _ in range(DRAWN):
            few = self.means[rng.choice(len(self.n), len(FEATURES) + 1, p=self.n / self.n.sum())]
            yield few.mean(axis=0), floored(np.cov(few.T, bias=True))

    def concentrated(self, model: tuple[np.ndarray, np.ndarray], steps: int, share: float) -> tuple[float, tuple[np.ndarray, np.ndarray]]:
        """(log determinant, model) after concentration steps, at most ``steps``."""
        rows, last = np.ceil(share * self.n.sum()), np.inf
        for _ in range(steps):
            model = self.moments(self.nearest(self.distances(*model), rows), share)
            now = float(np.linalg.slogdet(model[1])[1])
            if abs(last - now) < SETTLED:
                break
            last = now
        return now, model

    def estimate(self, steps: int = STEPS, share: float = KEEP_SHARE) -> tuple[float, np.ndarray, np.ndarray]:
        """(smallest log determinant, reweighted centre, reweighted scatter)."""
        tried = [self.concentrated(m, 2, share) for m in self.starts(np.random.default_rng(SEED))]
        tried = sorted(tried, key=lambda x: x[0])[:BEST]
        logdet, model = min((self.concentrated(m, steps, share) for _, m in tried), key=lambda x: x[0])
        inside = (self.distances(*model) <= chi2_quantile(0.975, len(FEATURES))).astype(float)
        return logdet, *self.moments(inside, 0.975)


def floored(cov: np.ndarray) -> np.ndarray:
    out = np.array(cov)
    d = range(len(out))
    out[d, d] = np.maximum(out[d, d], 0) + np.square(FLOORS)
    return out


def robust_models(rows: DataFrame, steps: int = STEPS, share: float = KEEP_SHARE) -> DataFrame:
    """cell, centre, inverse scatter and smallest log determinant. rows: cell and the statistic vector."""
    d, entries = len(FEATURES), _entries()
    box = [F.floor(F.col(n) / f).alias(f"b{k}") for k, (n, f) in enumerate(FEATURES)]
    sums = [F.sum(n).alias(f"s{k}") for k, n in enumerate(NAMES)]
    products = [F.sum(F.col(NAMES[i]) * F.col(NAMES[j])).alias(f"p{i}{j}") for i, j in entries]
    boxes = rows.groupBy("cell", *box).agg(F.count("*").alias("n"), *sums, *products)
    outputs = [*[f"m{k}" for k in range(d)], *[f"i{i}{j}" for i, j in entries], "logdet"]

    def fit(found: pd.DataFrame) -> pd.DataFrame:
        one_blas_thread()
        found = found.sort_values([f"b{k}" for k in range(d)])
        held = Boxes(found["n"].to_numpy(float), found[[f"s{k}" for k in range(d)]].to_numpy(), found[[f"p{i}{j}" for i, j in entries]].to_numpy())
        logdet, centre, cov = held.estimate(steps, share)
        inverse = np.linalg.inv(cov)
        return pd.DataFrame([[found["cell"].iloc[0], *centre, *[inverse[i, j] for i, j in entries], logdet]], columns=["cell", *outputs])

    return _by_group(boxes.groupBy("cell").applyInPandas(fit, "cell string, " + ", ".join(f"{c} double" for c in outputs)))


def _distance() -> Column:
    diff = [F.col(n) - F.col(f"m{k}") for k, n in enumerate(NAMES)]
    terms = [diff[i] * diff[j] * F.col(f"i{i}{j}") * (1 if i == j else 2) for i, j in _entries()]
    return sum(terms[1:], terms[0])


def _with_distance(rows: DataFrame, models: DataFrame) -> DataFrame:
    return rows.join(models, "cell", "left").withColumn("distance", _distance()).drop(*[c for c in models.columns if c != "cell"])


def judge(docs: DataFrame, level: float = LEVEL, steps: int = STEPS) -> DataFrame:
    """One row per document: doc_id, the statistics, base_failed, kept, distance."""
    rows = cut(assign_groups(vectors(cut(statistics(docs)))))
    sound = rows.where(~F.col("base_failed") & F.col("cell").isNotNull()).select("cell", *NAMES)
    judged = _with_distance(rows, robust_models(sound, steps))
    kept = ~F.col("base_failed") & (F.coalesce("distance", F.lit(0.0)) <= chi2_quantile(level, len(FEATURES)))
    return judged.select("doc_id", *STATS, "base_failed", kept.alias("kept"), "distance")


def keep(docs: DataFrame, level: float = LEVEL) -> DataFrame:
    """The documents kept, all columns; a doc_id that repeats is kept if all its rows are."""
    name = fresh("kept", docs.columns)
    judged = judge(docs.select("doc_id", "text", "lang", "source"), level)
    whole = judged.groupBy("doc_id").agg(F.min("kept").alias("all_kept")).where("all_kept").select(F.col("doc_id").alias(name))
    return docs.join(whole, F.col("doc_id").eqNullSafe(F.col(name)), "left_semi")
