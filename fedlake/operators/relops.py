"""Relational helpers: interval and as-of joins, ranked groups, tops, profiles, set checks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


#: Clients whose untouched items may be listed.
MOST_CLIENTS = 100_000


def range_join(df: DataFrame, bands: list[tuple[float, float, int]], value: str, out: str) -> DataFrame:
    """Each row with the band (low, high] that holds its value; bands are a short literal list, so they are broadcast."""
    table = df.sparkSession.createDataFrame([(float(a), float(b), int(c)) for a, b, c in bands], f"_low double, _high double, {out} int")
    return df.join(F.broadcast(table), (F.col(value) > F.col("_low")) & (F.col(value) <= F.col("_high"))).drop("_low", "_high")


def asof(left: DataFrame, right: DataFrame, by: str, ts: str, take: str, out: str, tie: str) -> DataFrame:
    """``out``: the right side's ``take`` of its latest row of the same ``by`` not after the left row.

    One union and one window: both sides share a shuffle and a sort, and no pair
    is formed. At equal times the right side comes first, its largest ``tie`` last.
    """
    marked = right.select(F.col(by), F.col(ts), F.lit(0).alias("_side"), F.col(tie).alias("_tie"), F.col(take).alias("_take"), *[F.lit(None).cast(t).alias(f"_l_{c}") for c, t in left.dtypes if c not in (by, ts)])
    probes = left.select(F.col(by), F.col(ts), F.lit(1).alias("_side"), F.lit(None).cast(dict(right.dtypes)[tie]).alias("_tie"), F.lit(None).cast(dict(right.dtypes)[take]).alias("_take"), *[F.col(c).alias(f"_l_{c}") for c in left.columns if c not in (by, ts)])
    order = Window.partitionBy(by).orderBy(ts, "_side", "_tie").rowsBetween(Window.unboundedPreceding, 0)
    found = marked.unionByName(probes).withColumn(out, F.last("_take", ignorenulls=True).over(order)).where("_side = 1")
    return found.select(by, ts, *[F.col(f"_l_{c}").alias(c) for c in left.columns if c not in (by, ts)], out)


def within_gap(df: DataFrame, by: str, seconds: Column, ident: str, gap: int) -> DataFrame:
    """(a_id, b_id): consecutive rows of one key no more than ``gap`` seconds apart, by one window."""
    order = Window.partitionBy(by).orderBy("_s", ident)
    rows = df.withColumn("_s", seconds)
    pairs = rows.select(F.lag(ident).over(order).alias("a_id"), F.col(ident).alias("b_id"), (F.col("_s") - F.lag("_s").over(order)).alias("_d"))
    return pairs.where((F.col("_d") <= gap) & F.col("a_id").isNotNull()).select("a_id", "b_id")


def top_k(df: DataFrame, by: list[str], order: list[Column], k: int, rank: str = "rank") -> DataFrame:
    """The first k rows of each group; Spark keeps k rows a group before the shuffle."""
    return df.withColumn(rank, F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col(rank) <= k)


def unseen(items: DataFrame, clients: DataFrame, seen: DataFrame) -> DataFrame:
    """(client_id, item_id) never touched, for a bounded set of clients (a round's draw); more than ``MOST_CLIENTS`` are an error."""
    if clients.limit(MOST_CLIENTS + 1).count() > MOST_CLIENTS:
        raise ValueError(f"candidates of more than {MOST_CLIENTS} clients are ranked by counting, not listed")
    return F.broadcast(clients.select("client_id")).join(items.select("item_id"), F.lit(True), "inner").join(seen.select("client_id", "item_id"), ["client_id", "item_id"], "left_anti")


def disjoint_and_complete(parts: list[DataFrame], whole: DataFrame, key: str) -> DataFrame:
    """One row: how many keys are in two parts, in none, and in all together."""
    tagged = parts[0].select(key).withColumn("_part", F.lit(0))
    for n, p in enumerate(parts[1:], 1):
        tagged = tagged.unionByName(p.select(key).withColumn("_part", F.lit(n)))
    counts = whole.select(key).distinct().join(tagged.groupBy(key).agg(F.countDistinct("_part").alias("_n")), key, "full")
    return counts.agg(F.sum((F.col("_n") > 1).cast("long")).alias("in_two"), F.sum(F.col("_n").isNull().cast("long")).alias("in_none"), F.count("*").alias("keys"))


def profile(df: DataFrame, by: str, label: str, ts: str) -> DataFrame:
    """Rows, positives, first and last time of each key."""
    return df.groupBy(by).agg(F.count("*").alias("n"), F.sum(label).alias("positives"), F.min(ts).alias("first_ts"), F.max(ts).alias("last_ts"))


def merge_sparse(maps: DataFrame, by: str, column: str) -> DataFrame:
    """Sum of sparse vectors (map<slot, value>) by key, one row per slot."""
    return maps.select(by, F.explode(column).alias("slot", "value")).groupBy(by, "slot").agg(F.sum("value").alias("value"))


def vector_mean(column: str, size: int) -> list[Column]:
    """Aggregates for the mean of an array column, one per position."""
    return [F.avg(F.element_at(column, k + 1)).alias(f"v{k}") for k in range(size)]
