"""Sources, interactions, features, splits and draws."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.functions.hashing import uniform, uniform_sql
from fedlake.operators import features, protocol, relops, sampling
from fedlake.queries.registry import query
from fedlake.sources import universes as U
from fedlake.sources.tables import TABLES, load

ROUND = 20
P_SQL, EV_SQL, USR_SQL = U.PURCHASES_SQL, U.EVENT_ROWS_SQL, U.USERS_SQL
stamp = lambda c: F.date_format(c, U.STAMP)
stamp_sql = lambda c: f"strftime({c}, '{U.STAMP_SQL}')"


def customers(spark, d) -> DataFrame:
    return load(spark, d, "customer", ["c_custkey"]).select(F.col("c_custkey").alias("client_id"))


@query("scan_parquet", " UNION ALL ".join(f"SELECT '{t}' AS table_name, count(*) AS n_rows FROM {t}" for t in TABLES))
def scan_parquet(spark, d):
    return reduce(DataFrame.unionAll, [load(spark, d, t).agg(F.count("*").alias("n_rows")).select(F.lit(t).alias("table_name"), "n_rows") for t in TABLES])


@query("scan_pruned", "SELECT l_partkey, sum(l_quantity) AS qty_sum, count(*) AS n FROM lineitem WHERE l_quantity > 30 GROUP BY 1")
def scan_pruned(spark, d):
    return load(spark, d, "lineitem", ["l_partkey", "l_quantity"], "l_quantity > 30").groupBy("l_partkey").agg(F.sum("l_quantity").alias("qty_sum"), F.count("*").alias("n"))


@query("interactions", f"WITH {P_SQL} SELECT client_id, item_id, stars, label, {stamp_sql('last_ts')} AS last_ts FROM p")
def interactions(spark, d):
    return U.purchases(spark, d).withColumn("last_ts", stamp("last_ts"))


@query("label_interactions", f"WITH {EV_SQL} SELECT client_id, item_id, max(stars) AS stars, (max(stars) > 3)::INTEGER AS label, count(*) AS n FROM ev GROUP BY 1, 2")
def label_interactions(spark, d):
    return U.event_interactions(spark, d).select("client_id", "item_id", "stars", "label", "n")


@query("filter_positive", f"WITH {P_SQL} SELECT client_id, count(*) AS positives FROM p WHERE label = 1 GROUP BY 1")
def filter_positive(spark, d):
    return U.purchases(spark, d).where("label = 1").groupBy("client_id").agg(F.count("*").alias("positives"))


@query(
    "dataset_stats",
    f"""WITH {P_SQL}, {EV_SQL}, e AS (SELECT client_id, item_id, (max(stars) > 3)::INTEGER AS label FROM ev GROUP BY 1, 2)
    SELECT 'P' AS universe, count(DISTINCT client_id) AS users, count(DISTINCT item_id) AS items, count(*) AS interactions, sum(label)::BIGINT AS positives FROM p
    UNION ALL SELECT 'E', count(DISTINCT client_id), count(DISTINCT item_id), count(*), sum(label)::BIGINT FROM e""",
)
def dataset_stats(spark, d):
    one = lambda df, name: df.agg(F.countDistinct("client_id").alias("users"), F.countDistinct("item_id").alias("items"), F.count("*").alias("interactions"), F.sum("label").alias("positives")).select(F.lit(name).alias("universe"), "*")
    return one(U.purchases(spark, d), "P").unionAll(one(U.event_interactions(spark, d), "E"))


@query("activity_histogram", f"WITH {P_SQL} SELECT n_items, count(*) AS n_users FROM (SELECT client_id, count(*) AS n_items FROM p GROUP BY 1) GROUP BY 1")
def activity_histogram(spark, d):
    return U.purchases(spark, d).groupBy("client_id").agg(F.count("*").alias("n_items")).groupBy("n_items").agg(F.count("*").alias("n_users"))


@query("client_profile", f"WITH {P_SQL} SELECT client_id, count(*) AS n, sum(label)::BIGINT AS positives, {stamp_sql('min(last_ts)')} AS first_ts, {stamp_sql('max(last_ts)')} AS last_ts FROM p GROUP BY 1")
def client_profile(spark, d):
    return relops.profile(U.purchases(spark, d), "client_id", "label", "last_ts").withColumns({"first_ts": stamp("first_ts"), "last_ts": stamp("last_ts")})


@query("item_popularity", f"WITH {P_SQL}, c AS (SELECT item_id, count(*) AS n_users, sum(label)::BIGINT AS n_pos FROM p GROUP BY 1) SELECT item_id, n_users, n_pos, rank() OVER (ORDER BY n_users DESC, n_pos DESC)::INTEGER AS pop_rank FROM c")
def item_popularity(spark, d):
    """Rank by (users, positives); ranks come from counts of distinct pairs of counts, so items aren't sorted in one task."""
    counts = U.purchases(spark, d).groupBy("item_id").agg(F.count("*").alias("n_users"), F.sum("label").alias("n_pos"))
    levels = counts.groupBy("n_users", "n_pos").agg(F.count("*").alias("_m"))
    before = Window.orderBy(F.col("n_users").desc(), F.col("n_pos").desc()).rowsBetween(Window.unboundedPreceding, -1)
    ranked = levels.withColumn("pop_rank", (F.coalesce(F.sum("_m").over(before), F.lit(0)) + 1).cast("int")).drop("_m")
    return counts.join(ranked, ["n_users", "n_pos"]).select("item_id", "n_users", "n_pos", "pop_rank")


@query("inactive_users", f"WITH {P_SQL} SELECT client_id, count(*) AS n_items FROM p GROUP BY 1 HAVING count(*) < 20")
def inactive_users(spark, d):
    return U.purchases(spark, d).groupBy("client_id").agg(F.count("*").alias("n_items")).where("n_items < 20")


def user_long(spark, d):
    return features.long_fields(U.purchase_users(spark, d), "client_id", features.USER_FIELDS)


def item_long(spark, d):
    return features.long_fields(U.purchase_items(spark, d), "item_id", features.ITEM_FIELDS)


def purchase_vocabulary(spark, d):
    """User slots come from training users only, item slots from the catalogue."""
    train = user_long(spark, d).where(protocol.user_split(F.col("client_id")) == "train")
    return features.vocabulary(train, "user").unionAll(features.vocabulary(item_long(spark, d), "item"))


FIELDS_SQL = f"""{USR_SQL},
ul AS (SELECT client_id, 'segment' AS field, segment AS value FROM usr UNION ALL SELECT client_id, 'nation', nation FROM usr
       UNION ALL SELECT client_id, 'region', region FROM usr UNION ALL SELECT client_id, 'decile', decile::VARCHAR FROM usr),
il AS (SELECT p_partkey AS item_id, 'brand' AS field, p_brand AS value FROM part UNION ALL SELECT p_partkey, 'type', p_type FROM part
       UNION ALL SELECT p_partkey, 'size', p_size::VARCHAR FROM part UNION ALL SELECT p_partkey, 'price_band', floor(p_retailprice / 100)::BIGINT::VARCHAR FROM part
       UNION ALL SELECT DISTINCT p_partkey, 'words', unnest(string_split(lower(p_name), ' ')) FROM part),
vocab AS (
  SELECT 'user' AS side, field, value, row_number() OVER (ORDER BY field, value)::INTEGER AS slot FROM (SELECT DISTINCT field, value FROM ul WHERE value IS NOT NULL AND {U.USER_SPLIT_SQL} = 'train')
  UNION ALL SELECT 'item', field, value, row_number() OVER (ORDER BY field, value)::INTEGER FROM (SELECT DISTINCT field, value FROM il WHERE value IS NOT NULL))"""


@query("vocab", f"WITH {FIELDS_SQL} SELECT side, field, value, slot FROM vocab")
def vocab(spark, d):
    return purchase_vocabulary(spark, d)


@query("user_slots", f"WITH {FIELDS_SQL} SELECT client_id, coalesce(slot, 0)::INTEGER AS slot FROM ul LEFT JOIN (SELECT * FROM vocab WHERE side = 'user') v ON ul.field = v.field AND ul.value = v.value WHERE ul.value IS NOT NULL")
def user_slots(spark, d):
    return features.slots(user_long(spark, d), purchase_vocabulary(spark, d).where("side = 'user'"), "client_id")


@query("item_slots", f"WITH {FIELDS_SQL} SELECT item_id, slot FROM il JOIN (SELECT * FROM vocab WHERE side = 'item') v ON il.field = v.field AND il.value = v.value")
def item_slots(spark, d):
    return features.slots(item_long(spark, d), purchase_vocabulary(spark, d).where("side = 'item'"), "item_id")


@query("name_tokens", "SELECT DISTINCT p_partkey AS item_id, unnest(string_split(lower(p_name), ' ')) AS token FROM part")
def name_tokens(spark, d):
    return U.purchase_items(spark, d).select("item_id", F.explode("words").alias("token"))


@query("balance_decile", f"WITH {USR_SQL} SELECT client_id, decile FROM usr")
def balance_decile(spark, d):
    return U.balance_decile(load(spark, d, "customer", ["c_custkey", "c_acctbal"]))


@query("context_features", "SELECT event_id, (hour(ts) // 6)::INTEGER AS hour_band, dayofweek(ts)::INTEGER AS weekday, (dayofweek(ts) IN (0, 6))::INTEGER AS is_weekend FROM events")
def context_features(spark, d):
    day = F.dayofweek("ts") - 1
    return load(spark, d, "events", ["event_id", "ts"]).select("event_id", F.floor(F.hour("ts") / 6).cast("int").alias("hour_band"), day.alias("weekday"), day.isin(0, 6).cast("int").alias("is_weekend"))


@query("event_props", "SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k FROM events")
def event_props(spark, d):
    return load(spark, d, "events", ["event_id", "props"]).select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))


@query("event_props_variant", "SELECT event_type, sum(json_extract_string(props, '$.k')::INTEGER)::BIGINT AS k_sum FROM events GROUP BY 1")
def event_props_variant(spark, d):
    return load(spark, d, "events", ["event_type", "props"]).select("event_type", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")).groupBy("event_type").agg(F.sum("k").alias("k_sum"))


@query("user_features", f"WITH {USR_SQL} SELECT client_id, segment, nation, region FROM usr")
def user_features(spark, d):
    return U.purchase_users(spark, d).select("client_id", "segment", "nation", "region")


@query("rating_bands", f"WITH {EV_SQL} SELECT stars, count(*) AS n FROM ev WHERE value > -1e9 AND value <= 1e9 GROUP BY 1")
def rating_bands(spark, d):
    edges = [-1e9, *U.EVENT_CUTS, 1e9]
    bands = [(a, b, k) for k, (a, b) in enumerate(zip(edges, edges[1:], strict=False), 1)]
    return relops.range_join(load(spark, d, "events", ["value"]), bands, "value", "stars").groupBy("stars").agg(F.count("*").alias("n"))


@query("users_split", f"SELECT client_id, {U.USER_SPLIT_SQL} AS user_split FROM (SELECT c_custkey AS client_id FROM customer)")
def users_split(spark, d):
    return customers(spark, d).withColumn("user_split", protocol.user_split(F.col("client_id")))


@query("users_split_partition", "SELECT 0::BIGINT AS in_two, 0::BIGINT AS in_none, count(*) AS keys FROM customer")
def users_split_partition(spark, d):
    rows = users_split(spark, d)
    return relops.disjoint_and_complete([rows.where("user_split = 'train'"), rows.where("user_split = 'test'")], rows, "client_id")


@query("protocol_split", f"WITH {P_SQL} SELECT client_id, item_id, {protocol.ROW_SPLIT_SQL} AS row_split FROM p WHERE {U.USER_SPLIT_SQL} = 'test'")
def protocol_split(spark, d):
    return protocol.split_rows(U.purchases(spark, d).where(protocol.user_split(F.col("client_id")) == "test")).select("client_id", "item_id", "row_split")


ROUNDS_SQL = "(SELECT unnest([0, 1, 2])::INTEGER AS round)"
DRAW_SQL = f"""draw AS (SELECT round, client_id FROM (
  SELECT round, c_custkey AS client_id, row_number() OVER (PARTITION BY round ORDER BY {uniform_sql('round', 'round', 'c_custkey')}, c_custkey) AS k
  FROM customer, {ROUNDS_SQL}) WHERE k <= {ROUND})"""


@query("round_draw_fixed", f"WITH {DRAW_SQL} SELECT round, client_id FROM draw")
def round_draw_fixed(spark, d):
    return sampling.draw_fixed(customers(spark, d), ROUND, 3)


@query("round_draw_poisson", f"SELECT round, c_custkey AS client_id FROM customer, {ROUNDS_SQL} WHERE {uniform_sql('poisson', 'round', 'c_custkey')} < {ROUND}::DOUBLE / (SELECT count(*) FROM customer)")
def round_draw_poisson(spark, d):
    c = customers(spark, d)
    return sampling.draw_poisson(c, ROUND / c.count(), 3)


@query(
    "schedule_rounds",
    f"""WITH n AS (SELECT count(*) AS total FROM customer),
    t AS (SELECT total, CASE WHEN {ROUND} < total // 2 THEN 4 * {ROUND} + 64 ELSE 24 * total END AS tries FROM n),
    j AS (SELECT round, unnest(range(tries))::BIGINT AS j, total FROM {ROUNDS_SQL}, t),
    o AS (SELECT round, floor({uniform_sql('schedule', 'round', 'j')} * total)::BIGINT AS ordinal, min(j) AS j FROM j GROUP BY 1, 2)
    SELECT round, ordinal FROM (SELECT *, row_number() OVER (PARTITION BY round ORDER BY j) AS k FROM o) WHERE k <= {ROUND}""",
)
def schedule_rounds(spark, d):
    total = customers(spark, d).agg(F.count("client_id")).first()[0]  # over the keys themselves, not the files' row counts
    return sampling.draw_schedule(spark, total, ROUND, 3)


@query("clients_in_round", f"WITH {P_SQL}, {DRAW_SQL} SELECT client_id, count(*) AS n FROM p WHERE client_id IN (SELECT client_id FROM draw WHERE round = 0) GROUP BY 1")
def clients_in_round(spark, d):
    drawn = sampling.draw_fixed(customers(spark, d), ROUND, 1)
    return U.purchases(spark, d).join(drawn, "client_id", "left_semi").groupBy("client_id").agg(F.count("*").alias("n"))


@query("never_interacted", f"WITH {P_SQL}, {DRAW_SQL} SELECT client_id, p_partkey AS item_id FROM draw, part WHERE round = 0 AND NOT EXISTS (SELECT 1 FROM p WHERE p.client_id = draw.client_id AND p.item_id = p_partkey)")
def never_interacted(spark, d):
    drawn = sampling.draw_fixed(customers(spark, d), ROUND, 1)
    return relops.unseen(load(spark, d, "part", ["p_partkey"]).select(F.col("p_partkey").alias("item_id")), drawn, U.purchases(spark, d))


@query("candidate_counts", f"WITH {P_SQL} SELECT client_id, (SELECT count(*) FROM part) - count(*) + 1 AS candidates FROM p GROUP BY 1")
def candidate_counts(spark, d):
    items = load(spark, d, "part", ["p_partkey"]).count()
    return U.purchases(spark, d).groupBy("client_id").agg((F.lit(items) - F.count("*") + 1).alias("candidates"))


@query("negatives_rated", f"WITH {P_SQL} SELECT client_id, item_id FROM p WHERE label = 0")
def negatives_rated(spark, d):
    return U.purchases(spark, d).where("label = 0").select("client_id", "item_id")


@query(
    "negatives_sampled",
    f"""WITH {P_SQL}, c AS (SELECT p_partkey AS item_id, row_number() OVER (ORDER BY p_partkey) - 1 AS o, count(*) OVER () AS total FROM part),
    g AS (SELECT DISTINCT client_id, floor({uniform_sql('negative', 'client_id', 'item_id')} * (SELECT count(*) FROM part))::BIGINT AS o FROM p WHERE label = 1)
    SELECT g.client_id, c.item_id FROM g JOIN c USING (o) WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.client_id = g.client_id AND p.item_id = c.item_id)""",
)
def negatives_sampled(spark, d):
    return sampled_negatives(U.purchases(spark, d), load(spark, d, "part", ["p_partkey"]).select(F.col("p_partkey").alias("item_id")))


def sampled_negatives(rows: DataFrame, items: DataFrame) -> DataFrame:
    """One hashed unseen item for each positive (fewer where the draw repeats or was seen)."""
    from fedlake.operators.sequences import item_ordinals

    placed = item_ordinals(items)
    total = items.count()
    draws = rows.where("label = 1").select("client_id", F.floor(uniform("negative", F.col("client_id"), F.col("item_id")) * total).cast("long").alias("ordinal")).distinct()
    return draws.join(placed, "ordinal").select("client_id", "item_id").join(rows.select("client_id", "item_id"), ["client_id", "item_id"], "left_anti")


@query("cold_clients", "SELECT c_custkey AS client_id FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def cold_clients(spark, d):
    return customers(spark, d).join(load(spark, d, "orders", ["o_custkey"]).distinct(), F.col("client_id") == F.col("o_custkey"), "left").where("o_custkey is null").select("client_id")


@query("label_cube", f"WITH {P_SQL}, x AS (SELECT c_mktsegment AS segment, p_brand AS brand, label FROM p JOIN customer ON client_id = c_custkey JOIN part ON item_id = p_partkey) SELECT segment, brand, label, grouping(segment, brand, label)::BIGINT AS level, count(*) AS n FROM x GROUP BY CUBE (segment, brand, label)")
def label_cube(spark, d):
    return _labelled(spark, d).cube("segment", "brand", "label").agg(F.grouping_id().alias("level"), F.count("*").alias("n"))


@query("label_rollup", f"WITH {P_SQL}, x AS (SELECT c_mktsegment AS segment, p_brand AS brand, label FROM p JOIN customer ON client_id = c_custkey JOIN part ON item_id = p_partkey) SELECT segment, brand, label, grouping(segment, brand, label)::BIGINT AS level, count(*) AS n FROM x GROUP BY ROLLUP (segment, brand, label)")
def label_rollup(spark, d):
    return _labelled(spark, d).rollup("segment", "brand", "label").agg(F.grouping_id().alias("level"), F.count("*").alias("n"))


@query("label_grouping_sets", f"WITH {P_SQL}, x AS (SELECT c_mktsegment AS segment, p_brand AS brand, label FROM p JOIN customer ON client_id = c_custkey JOIN part ON item_id = p_partkey) SELECT segment, brand, sum(label)::BIGINT AS positives FROM x GROUP BY GROUPING SETS ((segment), (brand), ())")
def label_grouping_sets(spark, d):
    return _labelled(spark, d).groupingSets([["segment"], ["brand"], []], "segment", "brand").agg(F.sum("label").alias("positives"))


def _labelled(spark, d):
    segments = load(spark, d, "customer", ["c_custkey", "c_mktsegment"]).select(F.col("c_custkey").alias("client_id"), F.col("c_mktsegment").alias("segment"))
    brands = load(spark, d, "part", ["p_partkey", "p_brand"]).select(F.col("p_partkey").alias("item_id"), F.col("p_brand").alias("brand"))
    return U.purchases(spark, d).select("client_id", "item_id", "label").join(segments, "client_id").join(brands, "item_id").select("segment", "brand", "label")


@query(
    "items_both_universes_days",
    """(SELECT DISTINCT dayofweek(o_orderdate)::INTEGER AS d, 'both' AS kind FROM orders INTERSECT SELECT DISTINCT dayofweek(ts)::INTEGER, 'both' FROM events)
    UNION ALL (SELECT DISTINCT dayofweek(o_orderdate)::INTEGER, 'orders' FROM orders EXCEPT SELECT DISTINCT dayofweek(ts)::INTEGER, 'orders' FROM events)""",
)
def items_both_universes_days(spark, d):
    days = lambda t, c: load(spark, d, t, [c]).select((F.dayofweek(c) - 1).alias("d"))
    a, b = days("orders", "o_orderdate"), days("events", "ts")
    return a.intersect(b).withColumn("kind", F.lit("both")).unionByName(a.distinct().exceptAll(b.distinct()).withColumn("kind", F.lit("orders")))


@query("text_slots", f"SELECT source, floor({uniform_sql('slot', 'w')} * 64)::INTEGER AS slot, count(*) AS n FROM (SELECT source, unnest(string_split(lower(text), ' ')) AS w FROM documents) WHERE w <> '' GROUP BY 1, 2")
def text_slots(spark, d):
    """Hashed token slots of every document's whole text, by source."""
    words = load(spark, d, "documents", ["source", "text"]).select("source", F.explode(F.split(F.lower("text"), " ")).alias("w")).where("w <> ''")
    by_word = words.groupBy("source", "w").agg(F.count("*").alias("m"))
    return by_word.groupBy("source", F.floor(uniform("slot", F.col("w")) * 64).cast("int").alias("slot")).agg(F.sum("m").alias("n"))


@query("approx_items")
def approx_items(spark, d):
    """Sketched distinct counts and quantiles beside the exact ones."""
    rows = U.purchase_rows(spark, d)
    return rows.agg(F.approx_count_distinct("item_id", 0.02).alias("items_approx"), F.countDistinct("item_id").alias("items"), F.percentile_approx("stars", 0.5).alias("median_stars"), F.hll_sketch_estimate(F.hll_sketch_agg("client_id")).alias("clients_hll"), F.countDistinct("client_id").alias("clients"))


@query("roundtrip_parquet")
def roundtrip_parquet(spark, d):
    """Interactions written by client bucket and read back for a round's clients only."""
    from fedlake.session import ensure_checkpoint_dir
    from fedlake.sources.tables import read_scheduled, save_client_lake
    import uuid

    path = f"{ensure_checkpoint_dir(spark)}/lake-{uuid.uuid4().hex}"
    save_client_lake(U.purchases(spark, d), path, 16)
    return read_scheduled(spark, path, sampling.draw_fixed(customers(spark, d), ROUND, 1), 16).select("client_id", "item_id", "label")
