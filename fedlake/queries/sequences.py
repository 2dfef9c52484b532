"""Sessions, masked views, negatives and contrastive losses; windowed activity."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.functions.hashing import uniform, uniform_sql
from fedlake.functions.vectors import dot, logsumexp
from fedlake.operators import relops
from fedlake.operators import sequences as S
from fedlake.queries.data import EV_SQL, stamp, stamp_sql
from fedlake.queries.privacy import V_SQL, vectors
from fedlake.queries.registry import query
from fedlake.sources import universes as U
from fedlake.sources.tables import load

SESSION_SQL = f"""{EV_SQL},
s0 AS (SELECT *, date_diff('second', TIMESTAMP '2000-01-01', ts) AS s FROM ev),
s1 AS (SELECT *, CASE WHEN s - lag(s) OVER (PARTITION BY client_id ORDER BY s, event_id) > {S.GAP} THEN 1 ELSE 0 END AS nw FROM s0),
s2 AS (SELECT *, sum(nw) OVER (PARTITION BY client_id ORDER BY s, event_id ROWS UNBOUNDED PRECEDING)::BIGINT AS session_id FROM s1),
s3 AS (SELECT *, (row_number() OVER (PARTITION BY client_id, session_id ORDER BY s, event_id) - 1)::INTEGER AS pos FROM s2),
se AS (SELECT client_id, session_id, count(*) AS n, min(ts) AS start_ts, max(ts) AS end_ts, list(item_id ORDER BY pos) AS items FROM s3 GROUP BY 1, 2)"""
ITEMS_SQL = "it AS (SELECT item_id, row_number() OVER (ORDER BY item_id) - 1 AS o FROM (SELECT DISTINCT item_id FROM ev)), tot AS (SELECT count(*) AS total FROM it)"


def event_sessions(spark, d):
    return S.sessions(U.event_rows(spark, d))


def catalogue(spark, d):
    return U.event_rows(spark, d).select("item_id").distinct()


@query("sessions_gap", f"WITH {SESSION_SQL} SELECT client_id, session_id, n, {stamp_sql('start_ts')} AS start_ts, {stamp_sql('end_ts')} AS end_ts FROM se")
def sessions_gap(spark, d):
    return event_sessions(spark, d).select("client_id", "session_id", "n", stamp("start_ts").alias("start_ts"), stamp("end_ts").alias("end_ts"))


@query("session_items", f"WITH {SESSION_SQL} SELECT client_id, session_id, pos, item_id FROM s3")
def session_items(spark, d):
    return S.with_sessions(U.event_rows(spark, d)).select("client_id", "session_id", "pos", "item_id")


MASK_SQL = f"""{SESSION_SQL}, {ITEMS_SQL},
m0 AS (SELECT client_id, session_id, items, floor({uniform_sql('mask:pos', 'client_id', 'session_id')} * len(items))::INTEGER AS pos, floor({uniform_sql('mask', 'client_id', 'session_id')} * total)::BIGINT AS o, total FROM se, tot WHERE len(items) >= {S.MIN_VIEW}),
m AS (SELECT client_id, session_id, items, pos, items[pos + 1] AS target, CASE WHEN a.item_id = items[pos + 1] THEN b.item_id ELSE a.item_id END AS negative FROM m0 JOIN it a ON a.o = m0.o JOIN it b ON b.o = (m0.o + 1) % total)"""


@query("view_item_mask", f"WITH {MASK_SQL} SELECT client_id, session_id, pos, target AS item_id, negative AS masked, array_to_string(list_concat(list_concat(items[1:pos], [negative]), items[pos + 2:]), ',') AS view FROM m")
def view_item_mask(spark, d):
    return S.mask_item(event_sessions(spark, d), catalogue(spark, d)).select("client_id", "session_id", "pos", F.col("target").alias("item_id"), F.col("negative").alias("masked"), F.array_join("view", ",").alias("view"))


SEGMENT_SQL = f"""{SESSION_SQL},
g0 AS (SELECT *, coalesce(lead(items) OVER (PARTITION BY client_id ORDER BY session_id), first_value(items) OVER (PARTITION BY client_id ORDER BY session_id)) AS other FROM se WHERE len(items) >= {S.MIN_VIEW}),
g1 AS (SELECT *, least({S.SEGMENT[0]} + floor({uniform_sql('segment:len', 'client_id', 'session_id')} * {S.SEGMENT[1] - S.SEGMENT[0] + 1}), len(items) - 1)::INTEGER AS ln FROM g0),
g AS (SELECT *, floor({uniform_sql('segment:pos', 'client_id', 'session_id')} * (len(items) - ln + 1))::INTEGER AS pos FROM g1 WHERE len(other) >= ln)"""


@query("view_segment_mask", f"WITH {SEGMENT_SQL} SELECT client_id, session_id, pos, ln AS len, array_to_string(items[pos + 1:pos + ln], ',') AS item_id, array_to_string(list_concat(list_concat(items[1:pos], other[1:ln]), items[pos + ln + 1:]), ',') AS masked FROM g")
def view_segment_mask(spark, d):
    return S.mask_segment(event_sessions(spark, d)).select("client_id", "session_id", "pos", "len", F.array_join("target", ",").alias("item_id"), F.array_join("view", ",").alias("masked"))


@query("negative_items", f"WITH {MASK_SQL}, j AS (SELECT client_id, session_id, target, unnest(range({S.NEGATIVES}))::INTEGER AS j FROM m) SELECT client_id, session_id, j, item_id FROM (SELECT j.*, floor({uniform_sql('neg', 'client_id', 'session_id', 'j')} * total)::BIGINT AS q FROM j, tot) JOIN it ON it.o = q WHERE item_id <> target")
def negative_items(spark, d):
    items = catalogue(spark, d)
    return S.negative_items(S.mask_item(event_sessions(spark, d), items), items)


@query(
    "negative_segments",
    f"""WITH {SEGMENT_SQL}, l AS (SELECT client_id, session_id, len(items) AS n FROM se WHERE len(items) >= {S.MIN_VIEW}),
    r AS (SELECT g.client_id, g.session_id, l.session_id AS other_session, l.n, (row_number() OVER (PARTITION BY g.client_id, g.session_id ORDER BY l.session_id) - 1)::INTEGER AS j FROM g JOIN l ON g.client_id = l.client_id AND g.session_id <> l.session_id AND l.n >= g.ln)
    SELECT client_id, session_id, j, other_session, floor({uniform_sql('start', 'client_id', 'session_id', 'j')} * (n - 1))::INTEGER AS start_pos FROM r WHERE j < 2""",
)
def negative_segments(spark, d):
    sess = event_sessions(spark, d)
    return S.negative_segments(S.mask_segment(sess), sess)


NEGS = 4
LOSS_SQL = f"""{V_SQL}, n AS (SELECT vec_id, row_number() OVER (ORDER BY vec_id) - 1 AS o, e FROM v), tot AS (SELECT count(*) AS total FROM n),
q AS (SELECT vec_id, e, lead(e) OVER w AS p1, lead(e, 2) OVER w AS p2, lead(e, 3) OVER w AS p3 FROM v WINDOW w AS (PARTITION BY label ORDER BY vec_id)),
k AS (SELECT vec_id, unnest(range({NEGS}))::INTEGER AS j FROM v),
ng AS (SELECT k.vec_id, k.j, a.e AS a, b.e AS b FROM k JOIN n a ON a.o = floor({uniform_sql('cn', 'k.vec_id', 'k.j')} * (SELECT total FROM tot))::BIGINT JOIN n b ON b.o = (a.o + 1) % (SELECT total FROM tot)),
li AS (SELECT q.vec_id, -any_value(list_inner_product(q.e, q.p1)) + ln(sum(exp(list_inner_product(q.e, ng.a)))) AS loss FROM q JOIN ng USING (vec_id) WHERE q.p1 IS NOT NULL GROUP BY 1),
mp AS (SELECT vec_id, list_transform(range(1, len(e) + 1), lambda i: (e[i] + p1[i]) / 2) AS view, list_transform(range(1, len(e) + 1), lambda i: (p2[i] + p3[i]) / 2) AS target FROM q WHERE p3 IS NOT NULL),
ls AS (SELECT mp.vec_id, -any_value(list_inner_product(view, target)) + ln(sum(exp(list_inner_product(view, list_transform(range(1, len(a) + 1), lambda i: (a[i] + b[i]) / 2))))) AS loss FROM mp JOIN ng USING (vec_id) GROUP BY 1)"""


def _contrast(spark, d):
    """vec_id, its vector, the next three of its label, and drawn negatives with their successors."""
    rows = vectors(spark, d)
    order = Window.partitionBy("label").orderBy("vec_id")
    ahead = rows.select("vec_id", F.col("vec").alias("e"), *[F.lead("vec", k).over(order).alias(f"p{k}") for k in (1, 2, 3)])
    placed = S.item_ordinals(rows.select(F.col("vec_id").alias("item_id"))).join(rows.select(F.col("vec_id").alias("item_id"), "vec"), "item_id").select("ordinal", "vec")
    total = rows.count()
    draws = rows.select("vec_id", F.explode(F.sequence(F.lit(0), F.lit(NEGS - 1))).alias("j")).withColumn("ordinal", S.drawn_item(total, "cn", F.col("vec_id"), F.col("j")))
    first = draws.join(placed.withColumnRenamed("vec", "a"), "ordinal").withColumn("ordinal", (F.col("ordinal") + 1) % total)
    both = first.join(placed.withColumnRenamed("vec", "b"), "ordinal").groupBy("vec_id").agg(F.collect_list("a").alias("a"), F.collect_list("b").alias("b"))
    return ahead.join(both, "vec_id")


def _item_loss(rows):
    return -dot(F.col("e"), F.col("p1")) + logsumexp(F.transform("a", lambda x: dot(F.col("e"), x)))


def _mean(x, y):
    return F.zip_with(x, y, lambda s, t: (s + t) / 2)


def _segment_loss(rows):
    view, target = _mean(F.col("e"), F.col("p1")), _mean(F.col("p2"), F.col("p3"))
    pooled = F.zip_with("a", "b", _mean)
    return -dot(view, target) + logsumexp(F.transform(pooled, lambda x: dot(view, x)))


@query("contrastive_item_loss", f"WITH {LOSS_SQL} SELECT vec_id, round(loss, 6) + 0.0 AS loss FROM li")
def contrastive_item_loss(spark, d):
    rows = _contrast(spark, d).where("p1 is not null")
    return rows.select("vec_id", (F.round(_item_loss(rows), 6) + 0.0).alias("loss"))


@query("contrastive_segment_loss", f"WITH {LOSS_SQL} SELECT vec_id, round(loss, 6) + 0.0 AS loss FROM ls")
def contrastive_segment_loss(spark, d):
    rows = _contrast(spark, d).where("p3 is not null")
    return rows.select("vec_id", (F.round(_segment_loss(rows), 6) + 0.0).alias("loss"))


@query("ssl_loss_combined", f"WITH {LOSS_SQL} SELECT vec_id, round(0.5 * li.loss + 0.5 * ls.loss, 6) + 0.0 AS loss FROM li JOIN ls USING (vec_id)")
def ssl_loss_combined(spark, d):
    rows = _contrast(spark, d).where("p3 is not null")
    return rows.select("vec_id", (F.round(0.5 * _item_loss(rows) + 0.5 * _segment_loss(rows), 6) + 0.0).alias("loss"))


@query("daily_activity_tumbling", f"SELECT user_id AS client_id, {stamp_sql('date_trunc(' + chr(39) + 'day' + chr(39) + ', ts)')} AS w_start, count(*) AS n FROM events GROUP BY 1, 2")
def daily_activity_tumbling(spark, d):
    rows = load(spark, d, "events", ["user_id", "ts"])
    return rows.groupBy(F.col("user_id").alias("client_id"), F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")).select("client_id", stamp("w.start").alias("w_start"), "n")


@query("weekly_activity_sliding", f"SELECT client_id, {stamp_sql('w')} AS w_start, count(*) AS n FROM (SELECT user_id AS client_id, date_trunc('day', ts) - to_days(unnest(range(7))::INTEGER) AS w FROM events) GROUP BY 1, 2")
def weekly_activity_sliding(spark, d):
    rows = load(spark, d, "events", ["user_id", "ts"])
    return rows.groupBy(F.col("user_id").alias("client_id"), F.window("ts", "7 days", "1 day").alias("w")).agg(F.count("*").alias("n")).select("client_id", stamp("w.start").alias("w_start"), "n")


@query("rolling_activity", f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY date_diff('second', TIMESTAMP '2000-01-01', ts) RANGE BETWEEN {7 * 86400} PRECEDING AND CURRENT ROW) AS n FROM events")
def rolling_activity(spark, d):
    rows = load(spark, d, "events", ["event_id", "user_id", "ts"]).withColumn("s", S.seconds("ts"))
    return rows.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-7 * 86400, 0)).alias("n"))


@query("asof_last_view", f"WITH {EV_SQL}, b AS (SELECT * FROM ev WHERE event_type = 'purchase'), v AS (SELECT client_id, ts, max(event_id) AS view_id FROM ev WHERE event_type IN ('view', 'click') GROUP BY 1, 2) SELECT b.event_id, v.view_id FROM b ASOF LEFT JOIN v ON b.client_id = v.client_id AND b.ts >= v.ts")
def asof_last_view(spark, d):
    rows = U.event_rows(spark, d).select("event_id", "client_id", "ts", "event_type")
    bought = rows.where("event_type = 'purchase'").select("client_id", "ts", "event_id")
    seen = rows.where("event_type in ('view', 'click')").select("client_id", "ts", F.col("event_id").alias("view"))
    return relops.asof(bought, seen, "client_id", "ts", "view", "view_id", "view").select("event_id", "view_id")


@query("pairs_within_gap", f"WITH {EV_SQL}, s AS (SELECT client_id, event_id, date_diff('second', TIMESTAMP '2000-01-01', ts) AS s FROM ev), l AS (SELECT lag(event_id) OVER w AS a_id, event_id AS b_id, s - lag(s) OVER w AS g FROM s WINDOW w AS (PARTITION BY client_id ORDER BY s, event_id)) SELECT a_id, b_id FROM l WHERE a_id IS NOT NULL AND g <= 3600")
def pairs_within_gap(spark, d):
    return relops.within_gap(U.event_rows(spark, d), "client_id", S.seconds("ts"), "event_id", 3600)


@query("sparse_delta_merge", "WITH x AS (SELECT vec_id % 8 AS client_id, unnest(range(len(embedding)))::INTEGER AS slot, unnest(embedding)::DOUBLE AS v FROM embeddings) SELECT client_id, slot, round(sum(v), 6) + 0.0 AS value FROM x WHERE slot % 4 = client_id % 4 GROUP BY 1, 2")
def sparse_delta_merge(spark, d):
    """Sparse displacements (maps of touched slots) summed by client group."""
    rows = vectors(spark, d).withColumn("client_id", F.col("vec_id") % 8)
    slots = F.filter(F.sequence(F.lit(0), F.size("vec") - 1), lambda s: s % 4 == F.col("client_id") % 4)
    maps = rows.select("client_id", slots.alias("s"), "vec").select("client_id", F.map_from_arrays("s", F.transform("s", lambda s: F.element_at("vec", s + 1))).alias("delta"))
    return relops.merge_sparse(maps, "client_id", "delta").select("client_id", "slot", (F.round("value", 6) + 0.0).alias("value"))


@query("hash_uniform_draws", f"SELECT event_id, {uniform_sql('draw', 'event_id')} AS u FROM events")
def hash_uniform_draws(spark, d):
    return load(spark, d, "events", ["event_id"]).select("event_id", uniform("draw", F.col("event_id")).alias("u"))
