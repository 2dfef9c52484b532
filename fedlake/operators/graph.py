"""Client graphs through shared items."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.functions.hashing import uniform


def _keyed(item: Column) -> Column:
    return F.md5(F.concat(F.lit("k#"), item.cast("string")).cast("binary"))


def ring_neighbours(interactions: DataFrame, per_item: int = 2) -> DataFrame:
    """A bounded choice of co-users, by a keyed hash of an item: the next ones in a hashed order of its users.

    It leaves most co-users of a popular item out; ``co_user_means`` covers all of them.
    """
    keyed = interactions.select("client_id", "item_id", _keyed(F.col("item_id")).alias("hid"))
    order = Window.partitionBy("hid").orderBy(uniform("ring", F.col("client_id"), F.col("item_id")), "client_id")
    met = keyed.select("client_id", F.array(*[F.lead("client_id", k).over(order) for k in range(1, per_item + 1)]).alias("n"))
    return met.select("client_id", F.explode("n").alias("neighbour")).where("neighbour is not null").groupBy("client_id", "neighbour").agg(F.count("*").alias("common"))


def co_user_means(interactions: DataFrame, vectors: DataFrame, columns: list[str], clients: DataFrame | None = None) -> DataFrame:
    """(client_id, columns): over a client's items, the mean of the mean vector of all other users of the item.

    Every co-user counts, and no pair of users is formed: vectors are summed by
    keyed item (before the shuffle), and a client's own one is taken out of the
    sum. Items that nobody else has count nothing; clients without co-users
    don't appear. With ``clients`` only theirs are computed.
    """
    mine = interactions.select("client_id", _keyed(F.col("item_id")).alias("hid")).distinct()
    asked = mine if clients is None else mine.join(clients.select("client_id"), "client_id", "left_semi")
    shared = mine if clients is None else mine.join(asked.select("hid").distinct(), "hid", "left_semi")
    sums = shared.join(vectors.select("client_id", *columns), "client_id").groupBy("hid").agg(F.count("*").alias("_n"), *[F.sum(c).alias(f"_s{k}") for k, c in enumerate(columns)]).where("_n > 1")
    own = asked.join(vectors.select("client_id", *columns), "client_id").join(sums, "hid")
    others = own.select("client_id", *[((F.col(f"_s{k}") - F.col(c)) / (F.col("_n") - 1)).alias(c) for k, c in enumerate(columns)])
    return others.groupBy("client_id").agg(*[F.avg(c).alias(c) for c in columns])
