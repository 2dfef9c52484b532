"""Local updates of a small logistic model inside Catalyst: one packed row per client, no Python.

The model has a bias and two features; it is the exactly checkable twin of the
network kernels in ``plans``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fedlake.functions.vectors import sigmoid

FIXED_WEIGHTS = (-0.4, 0.3, -0.2)


def linear(w: Column, x1: Column, x2: Column) -> Column:
    return w["w0"] + w["w1"] * x1 + w["w2"] * x2


def pack(rows: DataFrame, by: str = "client_id") -> DataFrame:
    """(client, n, rows): rows is an ordered array of (item_id, x1, x2, y)."""
    return rows.groupBy(by).agg(F.sort_array(F.collect_list(F.struct("item_id", "x1", "x2", "y"))).alias("rows")).withColumn("n", F.size("rows"))


def weights(values: tuple[float, float, float]) -> Column:
    return F.struct(*[F.lit(float(v)).alias(f"w{k}") for k, v in enumerate(values)])


def mean_gradient(rows: Column, w: Column) -> Column:
    """Gradient of the mean cross-entropy over an array of rows; zero without rows."""
    zero = F.struct(F.lit(0.0).alias("g0"), F.lit(0.0).alias("g1"), F.lit(0.0).alias("g2"))

    def add(g: Column, r: Column) -> Column:
        error = sigmoid(linear(w, r["x1"], r["x2"])) - r["y"]
        return F.struct((g["g0"] + error).alias("g0"), (g["g1"] + error * r["x1"]).alias("g1"), (g["g2"] + error * r["x2"]).alias("g2"))

    n = F.greatest(F.size(rows), F.lit(1)).cast("double")
    return F.aggregate(rows, zero, add, lambda g: F.struct(*[(g[f"g{k}"] / n).alias(f"g{k}") for k in range(3)]))


def sgd(rows: Column, start: Column, steps: int, rate: float) -> Column:
    """Weights after full-batch gradient steps."""

    def step(w: Column, _: Column) -> Column:
        g = mean_gradient(rows, w)
        return F.struct(*[(w[f"w{k}"] - F.lit(float(rate)) * g[f"g{k}"]).alias(f"w{k}") for k in range(3)])

    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, step)


def coordinates(columns: list[Column]) -> Column:
    """(coord, value) rows of three columns."""
    return F.explode(F.array(*[F.struct(F.lit(k).alias("coord"), c.alias("value")) for k, c in enumerate(columns)]))
