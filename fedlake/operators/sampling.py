"""Drawing the clients of each round."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.functions.hashing import uniform


def draw_fixed(clients: DataFrame, size: int, rounds: int, seed: str = "round") -> DataFrame:
    """(round, client_id): exactly ``size`` distinct clients a round, those with the smallest draws."""
    total = clients.count()
    if size > total:
        raise ValueError(f"a round of {size} clients can't be drawn from {total}")
    drawn = clients.select("client_id").withColumn("round", F.explode(F.array(*[F.lit(r) for r in range(rounds)]))).withColumn("u", uniform(seed, F.col("round"), F.col("client_id")))
    # only draws under a bound that holds ``size`` of them reach the window
    bound = min(1.0, 3.0 * size / total + 60.0 / total)
    ranked = drawn.where(F.col("u") < bound).withColumn("_k", F.row_number().over(Window.partitionBy("round").orderBy("u", "client_id")))
    return ranked.where(F.col("_k") <= size).select("round", "client_id")


def draw_poisson(clients: DataFrame, q: float, rounds: int, seed: str = "poisson") -> DataFrame:
    """(round, client_id): every client joins a round with probability q; no shuffle."""
    drawn = clients.select("client_id").withColumn("round", F.explode(F.array(*[F.lit(r) for r in range(rounds)])))
    return drawn.where(uniform(seed, F.col("round"), F.col("client_id")) < q).select("round", "client_id")


def draw_schedule(spark: SparkSession, total: int, size: int, rounds: int, seed: str = "schedule") -> DataFrame:
    """(round, ordinal): ``size`` distinct of ``total`` client ordinals for every round, in O(rounds * size).

    Draws don't depend on data, so all rounds are drawn before any is run:
    hashed ordinals with repeats, of which the first ``size`` distinct ones count.
    """
    if size > total:
        raise ValueError(f"a round of {size} clients can't be drawn from {total}")
    tries = 4 * size + 64 if size < total // 2 else 24 * total
    draws = spark.range(rounds * tries).select(F.floor(F.col("id") / tries).cast("int").alias("round"), (F.col("id") % tries).alias("j"))
    placed = draws.withColumn("ordinal", F.floor(uniform(seed, F.col("round"), F.col("j")) * total).cast("long"))
    first = placed.groupBy("round", "ordinal").agg(F.min("j").alias("j"))
    return first.withColumn("_k", F.row_number().over(Window.partitionBy("round").orderBy("j"))).where(F.col("_k") <= size).select("round", "ordinal")


def restrict(df: DataFrame, schedule: DataFrame) -> DataFrame:
    """Rows of the scheduled clients, with their round."""
    return df.join(schedule, "client_id")
