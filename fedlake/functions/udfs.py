"""Python functions for what plain SQL users want to call: Arrow-batched scalars, an aggregate, a table function, recursion."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import pandas_udf, udtf


def score_udf(weights: tuple[float, float, float]) -> Callable:
    """A scalar function (x1, x2) -> probability, one Arrow batch at a time."""
    w = np.array(weights)

    @pandas_udf("double")
    def score(x1: pd.Series, x2: pd.Series) -> pd.Series:
        return pd.Series(1 / (1 + np.exp(-(w[0] + w[1] * x1.to_numpy() + w[2] * x2.to_numpy()))))

    return score


def vector_mean_udf() -> Callable:
    """The mean vector of a group. A group meets in one task: for bounded groups; ``dp.bounded_mean`` scales beyond."""

    @pandas_udf("array<double>")
    def vector_mean(vectors: pd.Series) -> np.ndarray:
        return np.mean(np.stack(vectors.to_numpy()), axis=0)

    return vector_mean


class SessionItems:
    """One row per item of a session array."""

    def eval(self, items: list):
        for pos, item in enumerate(items or []):
            yield pos, item


def register(spark: SparkSession) -> list[str]:
    """Names of the functions that ``spark.sql`` can call from now on."""
    spark.udf.register("vector_mean", vector_mean_udf())
    spark.udtf.register("session_items", udtf(SessionItems, returnType="pos int, item_id string"))
    return ["vector_mean", "session_items"]


def iterate_sql(given: DataFrame, start: str, step: str, n: int) -> DataFrame:
    """(k, w): w after k = 0..n applications of the SQL expression ``step`` over w and the columns of the one row of ``given``, by a recursive common table."""
    names = ", ".join(given.columns)
    given.createOrReplaceTempView("iterate_given")
    return given.sparkSession.sql(f"WITH RECURSIVE s(k, w, {names}) AS (SELECT 0, CAST({start} AS DOUBLE), {names} FROM iterate_given UNION ALL SELECT k + 1, {step}, {names} FROM s WHERE k < {int(n)}) SELECT k, w FROM s")
