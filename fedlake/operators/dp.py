"""User-level differential privacy on displacement vectors."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fedlake.functions import hashing
from fedlake.functions.vectors import clip_l1, clip_l2

#: Fixed-point scale of sums that must not depend on their order.
FIXED = 1 << 32


def sensitivity(clip: float, size: int, adjacency: str = "replace") -> float:
    """How far one user can move the bounded mean."""
    if adjacency == "replace":
        return 2 * clip / size
    if adjacency == "add_remove":
        return clip / size
    raise ValueError("adjacency is 'replace' or 'add_remove'")


def sigma(clip: float, size: int, z: float, adjacency: str = "replace") -> float:
    return z * sensitivity(clip, size, adjacency)


def clipped(vectors: DataFrame, clip: float, norm: str = "l2") -> DataFrame:
    """Column ``vec`` clipped; non-finite vectors become zero but keep their place in the fixed divisor."""
    bad = F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    safe = F.when(bad, F.transform("vec", lambda x: F.lit(0.0))).otherwise(F.col("vec"))
    return vectors.withColumn("vec", (clip_l2 if norm == "l2" else clip_l1)(safe, clip))


def bounded_mean(vectors: DataFrame, size: int, fixed_point: bool = False) -> DataFrame:
    """(pos, value): the sum of ``vec`` over a fixed divisor.

    With ``fixed_point`` the summands are whole numbers of 2^-32, rounded toward
    zero so that clipped norms stay within their bound; the sum then doesn't
    depend on the partitioning.
    """
    cells = vectors.select(F.posexplode("vec").alias("pos", "x"))
    if fixed_point:
        whole = F.when(F.col("x") < 0, F.ceil(F.col("x") * FIXED)).otherwise(F.floor(F.col("x") * FIXED)).cast("long")
        return cells.groupBy("pos").agg((F.sum(whole) / float(FIXED) / size).alias("value"))
    return cells.groupBy("pos").agg((F.sum("x") / size).alias("value"))


def noise_column(scale: float, seed: str, *key) -> Column:
    """Gaussian noise as a function of its key: row-sharded parameters add it wherever they lie."""
    return F.lit(float(scale)) * hashing.normal(seed, *key)


def lazy_noise(scale: float, seed: str, rounds_missed: Column, *key) -> Column:
    """The noise an untouched row gathered over several rounds, drawn once with the summed variance."""
    return F.lit(float(scale)) * F.sqrt(rounds_missed.cast("double")) * hashing.normal(seed + ":lazy", *key)


# -- driver side ---------------------------------------------------------
def clip_vector(v: np.ndarray, bound: float) -> np.ndarray:
    if not np.isfinite(v).all():
        return np.zeros_like(v)
    size = float(np.linalg.norm(v))
    return v if size <= bound else v * (bound / size)


def clip_vector_l1(v: np.ndarray, bound: float) -> np.ndarray:
    if not np.isfinite(v).all():
        return np.zeros_like(v)
    size = float(np.abs(v).sum())
    return v if size <= bound else v * (bound / size)


def generator(seed: int, *key: int, secure: bool = False) -> np.random.Generator:
    """Philox keyed by the draw; ``secure`` takes operating-system entropy instead."""
    return np.random.default_rng() if secure else np.random.Generator(np.random.Philox(np.random.SeedSequence([seed, *key])))


def gaussian(shape: int, scale: float, seed: int, *key: int, secure: bool = False) -> np.ndarray:
    return generator(seed, *key, secure=secure).standard_normal(shape) * scale


def laplace(shape: int, scale: float, seed: int, *key: int, secure: bool = False) -> np.ndarray:
    return generator(seed, *key, secure=secure).laplace(0.0, scale, shape) if scale > 0 else np.zeros(shape)


def gaussian_distributed(shape: int, scale: float, size: int, seed: int, *key: int) -> np.ndarray:
    """A client's share of noise: ``size`` of them average to deviation ``scale``."""
    return gaussian(shape, scale * math.sqrt(size), seed, *key)


def audit(shift: float, scale: float, trials: int, seed: int = 0) -> dict[str, float]:
    """Empirical two-world bound: the largest log-ratio of bin counts of mean + noise with and without one user's shift."""
    r = np.random.default_rng(seed)
    a, b = r.normal(0, scale, trials), r.normal(shift, scale, trials)
    edges = np.quantile(np.concatenate([a, b]), np.linspace(0, 1, 41))
    x, y = np.histogram(a, edges)[0] + 1.0, np.histogram(b, edges)[0] + 1.0
    enough = (x > 50) & (y > 50)
    return {"epsilon_seen": float(np.abs(np.log(x[enough] / y[enough])).max()) if enough.any() else 0.0, "bins": int(enough.sum())}
