"""Ranking measures on given scores, popularity, and the attack's samples."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from fedlake.functions.hashing import uniform_sql
from fedlake.operators import metrics, protocol, relops, scoring
from fedlake.operators.protocol import shadow_split
from fedlake.queries.data import P_SQL, USR_SQL, customers
from fedlake.queries.registry import query
from fedlake.sources import universes as U
from fedlake.sources.tables import load

TEST_SQL = f"{P_SQL}, te AS (SELECT *, {protocol.ROW_SPLIT_SQL} AS row_split FROM p WHERE {U.USER_SPLIT_SQL} = 'test')"
RANK_SQL = f"""{TEST_SQL}, cs AS (SELECT client_id, item_id, {scoring.FIXED_SCORE_SQL} AS s FROM te WHERE row_split = 'rank' AND label = 1),
al AS (SELECT client_id, item_id, {scoring.FIXED_SCORE_SQL} AS s FROM (SELECT DISTINCT client_id FROM cs), (SELECT p_partkey AS item_id FROM part)),
un AS (SELECT al.* FROM al LEFT JOIN te USING (client_id, item_id) WHERE te.client_id IS NULL),
rk AS (SELECT cs.client_id, cs.item_id, 1 + count(un.item_id) AS rank FROM cs LEFT JOIN un ON un.client_id = cs.client_id AND (un.s > cs.s OR (un.s = cs.s AND un.item_id < cs.item_id)) GROUP BY 1, 2),
kk AS (SELECT unnest([5, 10, 20, 30])::INTEGER AS k),
us AS (SELECT client_id, k, avg((rank <= k)::INTEGER::DOUBLE) AS hits, avg(CASE WHEN rank <= k THEN 1 / log2(rank + 1) ELSE 0 END) AS ndcg FROM rk, kk GROUP BY 1, 2)"""


def test_rows(spark, d):
    return protocol.split_rows(U.purchases(spark, d).where(protocol.user_split(F.col("client_id")) == "test"))


def catalogue(spark, d):
    return load(spark, d, "part", ["p_partkey"]).select(F.col("p_partkey").alias("item_id"))


def fixed_ranks(spark, d):
    return scoring.ranks(scoring.test_cases(test_rows(spark, d)), catalogue(spark, d), scoring.fixed_score)


@query("rank_of_positive", f"WITH {RANK_SQL} SELECT client_id, item_id, rank FROM rk")
def rank_of_positive(spark, d):
    return fixed_ranks(spark, d)


@query("hits_at_k", f"WITH {RANK_SQL} SELECT client_id, k, round(hits, 6) AS value FROM us")
def hits_at_k(spark, d):
    return metrics.per_user(fixed_ranks(spark, d)).select("client_id", "k", F.round("hits", 6).alias("value"))


@query("hits_at_k_rows", f"WITH {RANK_SQL}, nr AS (SELECT client_id, count(*) AS n FROM te WHERE row_split = 'rank' GROUP BY 1) SELECT client_id, k, round(sum((rank <= k)::INTEGER) / any_value(n)::DOUBLE, 6) AS value FROM rk JOIN nr USING (client_id), kk GROUP BY 1, 2")
def hits_at_k_rows(spark, d):
    """The other reading of the denominator: all rows of the ranking half."""
    rows = test_rows(spark, d).where("row_split = 'rank'").groupBy("client_id").agg(F.count("*").alias("n_rows"))
    return metrics.per_user(fixed_ranks(spark, d).join(rows, "client_id"), denominator="rows").select("client_id", "k", F.round("hits", 6).alias("value"))


@query("ndcg_at_k", f"WITH {RANK_SQL} SELECT client_id, k, round(ndcg, 6) AS value FROM us")
def ndcg_at_k(spark, d):
    return metrics.per_user(fixed_ranks(spark, d)).select("client_id", "k", F.round("ndcg", 6).alias("value"))


@query("metric_summary", f"WITH {RANK_SQL} SELECT 'hits' AS metric, k, round(avg(hits), 6) AS value, count(*) AS users FROM us GROUP BY k UNION ALL SELECT 'ndcg', k, round(avg(ndcg), 6), count(*) FROM us GROUP BY k")
def metric_summary(spark, d):
    return metrics.summary(metrics.per_user(fixed_ranks(spark, d))).withColumn("value", F.round("value", 6))


@query("metric_pivot", f"WITH {RANK_SQL}, s AS (SELECT 'hits' AS metric, k, round(avg(hits), 6) AS value FROM us GROUP BY k UNION ALL SELECT 'ndcg', k, round(avg(ndcg), 6) FROM us GROUP BY k) SELECT metric, " + ", ".join(f"max(value) FILTER (k = {k}) AS k{k}" for k in metrics.KS) + " FROM s GROUP BY 1")
def metric_pivot(spark, d):
    return metrics.pivot_k(metric_summary(spark, d))


@query("metric_inactive", f"WITH {RANK_SQL}, ia AS (SELECT client_id FROM p GROUP BY 1 HAVING count(*) < 20) SELECT k, round(avg(hits), 6) AS value, count(*) AS users FROM us WHERE client_id IN (SELECT client_id FROM ia) GROUP BY k")
def metric_inactive(spark, d):
    """Hits of test users with fewer than 20 touched items."""
    few = U.purchases(spark, d).groupBy("client_id").agg(F.count("*").alias("n")).where("n < 20")
    users = metrics.per_user(fixed_ranks(spark, d)).join(few, "client_id", "left_semi")
    return users.groupBy("k").agg(F.round(F.avg("hits"), 6).alias("value"), F.count("*").alias("users"))


POP_SQL = f"{TEST_SQL}, pc AS (SELECT p_partkey AS item_id, count(p.item_id) AS n FROM part LEFT JOIN (SELECT * FROM p WHERE {U.USER_SPLIT_SQL} = 'train') p ON p.item_id = p_partkey GROUP BY 1)"


def popularity(spark, d):
    """(item_id, n): training users per item."""
    train = U.purchases(spark, d).where(protocol.user_split(F.col("client_id")) == "train").groupBy("item_id").agg(F.count("*").alias("n"))
    return catalogue(spark, d).join(train, "item_id", "left").select("item_id", F.coalesce("n", F.lit(0)).alias("n"))


@query("popularity_topk", f"WITH {POP_SQL} SELECT row_number() OVER (ORDER BY n DESC, item_id)::INTEGER AS rank, item_id FROM pc ORDER BY n DESC, item_id LIMIT 10")
def popularity_topk(spark, d):
    best = popularity(spark, d).orderBy(F.col("n").desc(), "item_id").limit(10)
    return relops.top_k(best.withColumn("_all", F.lit(1)), ["_all"], [F.col("n").desc(), F.col("item_id")], 10).select("rank", "item_id")


@query("topk_per_client", f"WITH {P_SQL} SELECT client_id, rank, item_id FROM (SELECT client_id, item_id, row_number() OVER (PARTITION BY client_id ORDER BY stars DESC, last_ts DESC, item_id)::INTEGER AS rank FROM p) WHERE rank <= 3")
def topk_per_client(spark, d):
    return relops.top_k(U.purchases(spark, d), ["client_id"], [F.col("stars").desc(), F.col("last_ts").desc(), F.col("item_id")], 3).select("client_id", "rank", "item_id")


def table_score(ids: np.ndarray, values: np.ndarray):
    """A score that looks item values up and ignores the client."""
    order = np.argsort(ids)
    names, scores = ids[order], values[order].astype(float)
    return lambda client, items: scores[np.searchsorted(names, items)]


@query(
    "popularity_hits",
    f"""WITH {POP_SQL}, cs AS (SELECT client_id, te.item_id, n FROM te JOIN pc USING (item_id) WHERE row_split = 'rank' AND label = 1),
    un AS (SELECT c.client_id, pc.item_id, pc.n FROM (SELECT DISTINCT client_id FROM cs) c CROSS JOIN pc LEFT JOIN te ON te.client_id = c.client_id AND te.item_id = pc.item_id WHERE te.client_id IS NULL),
    rk AS (SELECT cs.client_id, cs.item_id, 1 + count(un.item_id) AS rank FROM cs LEFT JOIN un ON un.client_id = cs.client_id AND (un.n > cs.n OR (un.n = cs.n AND un.item_id < cs.item_id)) GROUP BY 1, 2),
    us AS (SELECT client_id, k, avg((rank <= k)::INTEGER::DOUBLE) AS hits, avg(CASE WHEN rank <= k THEN 1 / log2(rank + 1) ELSE 0 END) AS ndcg FROM rk, (SELECT unnest([5, 10, 20, 30])::INTEGER AS k) GROUP BY 1, 2)
    SELECT k, round(avg(hits), 6) AS hits, round(avg(ndcg), 6) AS ndcg FROM us GROUP BY 1""",
)
def popularity_hits(spark, d):
    counts = popularity(spark, d).toArrow()  # one number per item of the catalogue, as the ranker's table
    score = table_score(np.asarray(counts.column("item_id")), np.asarray(counts.column("n")))
    found = scoring.ranks(scoring.test_cases(test_rows(spark, d)), catalogue(spark, d), score)
    return metrics.per_user(found).groupBy("k").agg(F.round(F.avg("hits"), 6).alias("hits"), F.round(F.avg("ndcg"), 6).alias("ndcg"))


SHADOW_SQL = f"""sh AS (SELECT client_id, CASE WHEN {uniform_sql('shadow', 'client_id')} < 1 / 6.0::DOUBLE THEN 'shadow' ELSE 'private' END AS part,
  CASE WHEN {uniform_sql('shadow', 'client_id')} < 1 / 6.0::DOUBLE THEN {uniform_sql('used', 'client_id')} < 0.8::DOUBLE ELSE {uniform_sql('used', 'client_id')} < 0.5::DOUBLE END AS used FROM (SELECT c_custkey AS client_id FROM customer))"""


@query("mia_shadow_split", f"WITH {SHADOW_SQL} SELECT client_id, part, used FROM sh")
def mia_shadow_split(spark, d):
    return shadow_split(customers(spark, d))


TOP_SQL = f"{SHADOW_SQL}, tl AS (SELECT client_id, item_id, row_number() OVER (PARTITION BY client_id ORDER BY {scoring.FIXED_SCORE_SQL} DESC, item_id)::INTEGER AS rank FROM (SELECT client_id FROM sh WHERE part = 'shadow'), (SELECT p_partkey AS item_id FROM part))"


@query("topk_lists", f"WITH {TOP_SQL} SELECT client_id, rank, item_id FROM tl WHERE rank <= 10")
def topk_lists(spark, d):
    return scoring.top_items(mia_shadow_split(spark, d).where("part = 'shadow'"), catalogue(spark, d), scoring.fixed_score, ordered=scoring.fixed_order)


@query("mia_samples", f"WITH {USR_SQL}, {TOP_SQL} SELECT client_id, used::INTEGER AS label, rank, item_id, segment, region, p_brand AS brand FROM tl JOIN sh USING (client_id) JOIN usr USING (client_id) JOIN part ON p_partkey = item_id WHERE rank <= 10")
def mia_samples(spark, d):
    """An attack sample per list entry: the client's features, the entry and whether the client was used."""
    brands = load(spark, d, "part", ["p_partkey", "p_brand"]).select(F.col("p_partkey").alias("item_id"), F.col("p_brand").alias("brand"))
    users = U.purchase_users(spark, d).select("client_id", "segment", "region")
    split = mia_shadow_split(spark, d).select("client_id", F.col("used").cast("int").alias("label"))
    return topk_lists(spark, d).join(split, "client_id").join(users, "client_id").join(brands, "item_id").select("client_id", "label", "rank", "item_id", "segment", "region", "brand")


@query("budget_fit", f"WITH {P_SQL}, b AS (SELECT ln(count(*)::DOUBLE) AS x, avg(label::DOUBLE) AS m FROM p GROUP BY client_id) SELECT round(regr_slope(m, x), 6) AS slope, round(regr_intercept(m, x), 6) AS intercept FROM b")
def budget_fit(spark, d):
    """The logarithmic fit over clients: what a client gives (its number of items) against its share of positives."""
    clients = U.purchases(spark, d).groupBy("client_id").agg(F.log(F.count("*").cast("double")).alias("x"), F.avg(F.col("label").cast("double")).alias("y"))
    return fit_budget(clients)


def fit_budget(points):
    """y = intercept + slope * x over (x = logarithm of the budget, y = metric)."""
    return points.agg(F.round(F.regr_slope("y", "x"), 6).alias("slope"), F.round(F.regr_intercept("y", "x"), 6).alias("intercept"))


@query("relative_gap", f"WITH {RANK_SQL}, h AS (SELECT k, avg(hits) AS a, avg(ndcg) AS b FROM us GROUP BY 1) SELECT k, round(CASE WHEN a = 0 THEN 0 ELSE (a - b) / a END, 6) + 0.0 AS gap FROM h")
def relative_gap(spark, d):
    """The share of one measure lost in another; here Hits@k against nDCG@k of the same ranks."""
    means = metrics.per_user(fixed_ranks(spark, d)).groupBy("k").agg(F.avg("hits").alias("a"), F.avg("ndcg").alias("b"))
    return means.select("k", (F.round(F.when(F.col("a") == 0, 0.0).otherwise((F.col("a") - F.col("b")) / F.col("a")), 6) + 0.0).alias("gap"))
