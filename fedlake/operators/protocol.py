"""Evaluation protocol: users into train and test, a test user's rows into a tuning and a ranking half."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.functions.hashing import uniform, uniform_sql

TRAIN_SHARE = 0.8


def user_split(client: Column, share: float = TRAIN_SHARE) -> Column:
    """'train' or 'test' by a hash of the id; no shuffle."""
    return F.when(uniform("user-split", client) < share, "train").otherwise("test")


def split_rows(rows: DataFrame) -> DataFrame:
    """``row_split``: 'tune' or 'rank', alternating in hash order inside each client, so halves differ by one row at most."""
    order = Window.partitionBy("client_id").orderBy(uniform("row-split", F.col("client_id"), F.col("item_id")), "item_id")
    return rows.withColumn("row_split", F.when(F.row_number().over(order) % 2 == 1, "tune").otherwise("rank"))


ROW_SPLIT_SQL = f"CASE WHEN row_number() OVER (PARTITION BY client_id ORDER BY {uniform_sql('row-split', 'client_id', 'item_id')}, item_id) % 2 = 1 THEN 'tune' ELSE 'rank' END"


def shadow_split(clients: DataFrame, share: float = 1 / 6) -> DataFrame:
    """part: shadow or private; used: 80 % of shadow and half of private clients train their model."""
    part = uniform("shadow", F.col("client_id")) < share
    used = uniform("used", F.col("client_id"))
    return clients.select("client_id", F.when(part, "shadow").otherwise("private").alias("part"), F.when(part, used < 0.8).otherwise(used < 0.5).alias("used"))
