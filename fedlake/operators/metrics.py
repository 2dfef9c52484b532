"""Ranking measures from ranks: one row per case (a positive of a test user's ranking half)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KS = (5, 10, 20, 30)


def hit(rank: Column, k: int) -> Column:
    return (rank <= k).cast("double")


def gain(rank: Column, k: int) -> Column:
    return F.when(rank <= k, 1.0 / F.log2(rank + 1.0)).otherwise(F.lit(0.0))


def per_user(ranks: DataFrame, ks: tuple[int, ...] = KS, denominator: str = "positives") -> DataFrame:
    """(client_id, k, hits, ndcg) from (client_id, item_id, rank).

    ``denominator='rows'`` divides by all rows of the ranking half, given as column ``n_rows``.
    """
    measure = F.array(*[F.struct(F.lit(k).alias("k"), hit(F.col("rank"), k).alias("hit"), gain(F.col("rank"), k).alias("gain")) for k in ks])
    cases = ranks.withColumn("m", F.explode(measure))
    if denominator == "positives":
        return cases.groupBy("client_id", F.col("m.k").alias("k")).agg(F.avg("m.hit").alias("hits"), F.avg("m.gain").alias("ndcg"))
    if denominator == "rows":
        return cases.groupBy("client_id", F.col("m.k").alias("k")).agg((F.sum("m.hit") / F.max("n_rows")).alias("hits"), (F.sum("m.gain") / F.max("n_rows")).alias("ndcg"))
    raise ValueError("denominator is 'positives' or 'rows'")


def summary(users: DataFrame) -> DataFrame:
    """(metric, k, value, users): means over users."""
    means = users.groupBy("k").agg(F.avg("hits").alias("hits"), F.avg("ndcg").alias("ndcg"), F.count("*").alias("users"))
    return means.select("k", "users", F.explode(F.array(F.struct(F.lit("hits").alias("metric"), F.col("hits").alias("value")), F.struct(F.lit("ndcg").alias("metric"), F.col("ndcg").alias("value")))).alias("m")).select("m.metric", "k", "m.value", "users")


def pivot_k(long: DataFrame, ks: tuple[int, ...] = KS) -> DataFrame:
    """One row per metric, one column per k."""
    wide = long.groupBy("metric").pivot("k", list(ks)).agg(F.first("value"))
    return wide.select("metric", *[F.col(str(k)).alias(f"k{k}") for k in ks])


def relative_gap(a: float, b: float) -> float:
    """How much of ``a`` is lost in ``b``."""
    return (a - b) / a if a else 0.0


def bootstrap(users: DataFrame, replicates: int = 200) -> DataFrame:
    """(k, low, high) of mean Hits@k over resampled users: Poisson weights from the user's hash, one distributed aggregation."""
    from fedlake.functions.hashing import uniform

    def weight(b: Column) -> Column:
        u = uniform("boot", F.col("client_id"), b)
        return F.when(u < 0.3679, 0).when(u < 0.7358, 1).when(u < 0.9197, 2).when(u < 0.9810, 3).otherwise(4)

    drawn = users.withColumn("b", F.explode(F.sequence(F.lit(1), F.lit(replicates)))).withColumn("w", weight(F.col("b")))
    means = drawn.groupBy("k", "b").agg((F.sum(F.col("w") * F.col("hits")) / F.greatest(F.sum("w"), F.lit(1))).alias("m"))
    return means.groupBy("k").agg(F.percentile_approx("m", 0.025).alias("low"), F.percentile_approx("m", 0.975).alias("high"))
