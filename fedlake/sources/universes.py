"""The two sets of clients, items and interactions that the given tables carry.

P (purchases): customers, parts, orders joined with their lines; stars from the
quantity. E (events): users, (event type, k) pairs; stars from the value.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.functions.hashing import uniform, uniform_sql
from fedlake.sources.tables import load

#: Stars above this are a positive label.
POSITIVE_ABOVE = 3
EVENT_CUTS = (10, 25, 50, 80)
STAMP = "yyyy-MM-dd HH:mm:ss"
STAMP_SQL = "%Y-%m-%d %H:%M:%S"


def positive(stars: Column) -> Column:
    return F.when(stars > POSITIVE_ABOVE, 1).otherwise(0)


def purchase_rows(spark: SparkSession, folder: str) -> DataFrame:
    """Every order line with its client: client_id, item_id, stars, ts (repeats included)."""
    lines = load(spark, folder, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"])
    orders = load(spark, folder, "orders", ["o_orderkey", "o_custkey", "o_orderdate"])
    stars = F.least(F.lit(5), F.ceil(F.col("l_quantity") / 10)).cast("int")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("client_id"), F.col("l_partkey").alias("item_id"), stars.alias("stars"), F.col("o_orderdate").alias("ts"))


def purchases(spark: SparkSession, folder: str) -> DataFrame:
    """P: client_id, item_id, stars, label, last_ts; repeats keep the most stars and the last date."""
    best = purchase_rows(spark, folder).groupBy("client_id", "item_id").agg(F.max("stars").alias("stars"), F.max("ts").alias("last_ts"))
    return best.select("client_id", "item_id", "stars", positive(F.col("stars")).alias("label"), "last_ts")


def event_rows(spark: SparkSession, folder: str) -> DataFrame:
    """Every event with its item: event_id, client_id, item_id, stars, ts, event_type, value, k."""
    rows = load(spark, folder, "events", ["event_id", "ts", "user_id", "event_type", "value", "props"])
    k = F.get_json_object("props", "$.k")
    stars = F.lit(1)
    for cut in EVENT_CUTS:
        stars = stars + F.when(F.col("value") > cut, 1).otherwise(0)
    return rows.select("event_id", F.col("user_id").alias("client_id"), F.concat_ws("#", "event_type", k).alias("item_id"), stars.alias("stars"), "ts", "event_type", "value", k.cast("int").alias("k"))


def event_interactions(spark: SparkSession, folder: str) -> DataFrame:
    """E: client_id, item_id, stars, label, n, last_ts."""
    best = event_rows(spark, folder).groupBy("client_id", "item_id").agg(F.max("stars").alias("stars"), F.count("*").alias("n"), F.max("ts").alias("last_ts"))
    return best.select("client_id", "item_id", "stars", positive(F.col("stars")).alias("label"), "n", "last_ts")


@dataclass
class Universe:
    """Interactions with the client and item tables that describe them."""

    name: str
    interactions: DataFrame
    users: DataFrame
    items: DataFrame
    clip: float
    rounds: int
    epochs: int
    clients: int


def balance_decile(customers: DataFrame) -> DataFrame:
    """client_id, decile of the account balance over all clients.

    Deciles come from a histogram of balances in cents, so no task sorts all
    clients: the decile of a balance is fixed by the clients below it.
    """
    cents = customers.select(F.col("c_custkey").alias("client_id"), F.round(F.col("c_acctbal") * 100).cast("long").alias("cents"))
    counts = cents.groupBy("cents").agg(F.count("*").alias("n"))
    coarse = counts.groupBy(F.floor(F.col("cents") / 10_000).alias("block")).agg(F.sum("n").alias("held"))
    before = Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)  # one row per hundred units of balance
    blocks = coarse.withColumn("before", F.coalesce(F.sum("held").over(before), F.lit(0))).withColumn("total", F.sum("held").over(Window.partitionBy()))
    fine = Window.partitionBy("block").orderBy("cents").rowsBetween(Window.unboundedPreceding, -1)
    placed = counts.withColumn("block", F.floor(F.col("cents") / 10_000)).join(blocks, "block").withColumn("below", F.col("before") + F.coalesce(F.sum("n").over(fine), F.lit(0)))
    return cents.join(placed.select("cents", F.floor(F.col("below") * 10 / F.col("total")).cast("int").alias("decile")), "cents").select("client_id", "decile")


def purchase_users(spark: SparkSession, folder: str) -> DataFrame:
    """client_id, segment, nation, region, decile: side features only."""
    customers = load(spark, folder, "customer", ["c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment"])
    nations = load(spark, folder, "nation", ["n_nationkey", "n_name", "n_regionkey"])
    regions = load(spark, folder, "region", ["r_regionkey", "r_name"])
    named = customers.join(nations, F.col("c_nationkey") == F.col("n_nationkey"), "left").join(regions, F.col("n_regionkey") == F.col("r_regionkey"), "left")
    return named.select(F.col("c_custkey").alias("client_id"), F.col("c_mktsegment").alias("segment"), F.col("n_name").alias("nation"), F.col("r_name").alias("region")).join(balance_decile(customers), "client_id", "left")


def purchase_items(spark: SparkSession, folder: str) -> DataFrame:
    """item_id, brand, type, size, price band, words of the name."""
    parts = load(spark, folder, "part")
    return parts.select(F.col("p_partkey").alias("item_id"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), F.col("p_size").cast("string").alias("size"), F.floor(F.col("p_retailprice") / 100).cast("string").alias("price_band"), F.array_distinct(F.split(F.lower("p_name"), " ")).alias("words"))


def event_users(spark: SparkSession, folder: str) -> DataFrame:
    """client_id, hour band, weekday and weekend flag of the client's most frequent context."""
    rows = load(spark, folder, "events", ["user_id", "ts"])
    context = rows.select(F.col("user_id").alias("client_id"), F.floor(F.hour("ts") / 6).cast("string").alias("hour_band"), F.dayofweek("ts").cast("string").alias("weekday"))
    counted = context.groupBy("client_id", "hour_band", "weekday").agg(F.count("*").alias("n"))
    best = counted.groupBy("client_id").agg(F.max_by(F.struct("hour_band", "weekday"), F.struct("n", "hour_band", "weekday")).alias("c"))
    return best.select("client_id", "c.hour_band", "c.weekday", F.col("c.weekday").isin("1", "7").cast("string").alias("weekend"))


def event_items(spark: SparkSession, folder: str) -> DataFrame:
    """item_id, event type, decade of k, popularity and mean-value bands."""
    rows = event_rows(spark, folder)
    return rows.groupBy("item_id", "event_type", "k").agg(F.count("*").alias("n"), F.avg("value").alias("cost")).select("item_id", "event_type", F.floor(F.col("k") / 10).cast("string").alias("decade"), F.floor(F.log2("n")).cast("string").alias("popularity"), F.floor(F.col("cost") / 25).cast("string").alias("cost_band"))


def universe(spark: SparkSession, folder: str, name: str) -> Universe:
    if name == "P":
        return Universe("P", purchases(spark, folder), purchase_users(spark, folder), purchase_items(spark, folder), 40.0, 80, 100, 20)
    if name == "E":
        return Universe("E", event_interactions(spark, folder), event_users(spark, folder), event_items(spark, folder), 35.0, 40, 100, 30)
    raise ValueError(f"no universe {name!r}: P or E")


def thin_activity(interactions: DataFrame, exponent: float = 1.2, smallest: int = 5, seed: str = "tail") -> DataFrame:
    """A long-tailed copy: each client keeps a hash-chosen subset whose size follows a power law."""
    share = F.pow(uniform(seed, F.col("client_id")), F.lit(float(exponent)))
    ranked = interactions.withColumn("_rank", F.row_number().over(Window.partitionBy("client_id").orderBy(uniform(seed + ":row", F.col("client_id"), F.col("item_id")), "item_id"))).withColumn("_n", F.count("*").over(Window.partitionBy("client_id")))
    return ranked.where(F.col("_rank") <= F.greatest(F.lit(smallest), F.ceil(share * F.col("_n")))).drop("_rank", "_n")


def plant_preferences(interactions: DataFrame, users: DataFrame, items: DataFrame, user_field: str = "segment", item_field: str = "type", seed: str = "plant", noise: float = 0.1) -> DataFrame:
    """A learnable copy: the label is a hashed affinity of two side features, flipped with probability ``noise``."""
    joined = interactions.drop("label", "stars").join(users.select("client_id", F.col(user_field).alias("_u")), "client_id").join(items.select("item_id", F.col(item_field).alias("_v")), "item_id")
    likes = (uniform(seed, F.col("_u"), F.col("_v")) < 0.5).cast("int")
    flip = (uniform(seed + ":flip", F.col("client_id"), F.col("item_id")) < noise).cast("int")
    label = F.abs(likes - flip)
    return joined.withColumn("label", label).withColumn("stars", 2 + 3 * label).drop("_u", "_v")


# -- DuckDB text of the same ---------------------------------------------
PURCHASES_SQL = f"""
p AS (
  SELECT client_id, item_id, stars, (stars > {POSITIVE_ABOVE})::INTEGER AS label, last_ts FROM (
    SELECT o_custkey AS client_id, l_partkey AS item_id, max(least(5, ceil(l_quantity / 10)))::INTEGER AS stars, max(o_orderdate) AS last_ts
    FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2))"""
EVENT_ROWS_SQL = f"""
ev AS (
  SELECT event_id, user_id AS client_id, event_type || '#' || json_extract_string(props, '$.k') AS item_id,
         (1{''.join(f' + (value > {c})::INTEGER' for c in EVENT_CUTS)})::INTEGER AS stars,
         ts, event_type, value, json_extract_string(props, '$.k')::INTEGER AS k FROM events)"""
USERS_SQL = """
usr AS (
  SELECT c_custkey AS client_id, c_mktsegment AS segment, n_name AS nation, r_name AS region,
         floor((rank() OVER (ORDER BY round(c_acctbal * 100)::BIGINT) - 1) * 10.0 / count(*) OVER ())::INTEGER AS decile
  FROM customer LEFT JOIN nation ON c_nationkey = n_nationkey LEFT JOIN region ON n_regionkey = r_regionkey)"""
USER_SPLIT_SQL = f"CASE WHEN {uniform_sql('user-split', 'client_id')} < 0.8::DOUBLE THEN 'train' ELSE 'test' END"
