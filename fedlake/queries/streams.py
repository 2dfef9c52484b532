"""Streams run to the end of the available files."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.operators import protocol
from fedlake.queries.registry import REGISTRY, query
from fedlake.session import ensure_checkpoint_dir
from fedlake.sources import universes as U
from fedlake.streaming import streams as S

EV_SQL = U.EVENT_ROWS_SQL
HIT_KS = (5, 10, 20, 30)


def _finished(spark, frame, mode="append"):
    return S.run_once(frame, f"stream_{uuid.uuid4().hex}", ensure_checkpoint_dir(spark), mode)


@query("stream_sessions")
def stream_sessions(spark, d):
    """Sessions that the watermark has closed; the batch twin is sessions_gap."""
    return _finished(spark, S.sessions(S.event_stream(spark, d)))


@query("stream_activity", REGISTRY["daily_activity_tumbling"].sql)
def stream_activity(spark, d):
    """Daily counts in complete mode: equal to daily_activity_tumbling."""
    rows = S.event_stream(spark, d).groupBy("client_id", F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return _finished(spark, rows.select("client_id", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("w_start"), "n"), "complete")


@query("stream_dedup")
def stream_dedup(spark, d):
    """One event per client and item inside the watermark."""
    return _finished(spark, S.dedup(S.event_stream(spark, d), ["client_id", "item_id"]))


@query("stream_rounds")
def stream_rounds(spark, d):
    """Events as one-coordinate uploads, a day a round."""
    uploads = S.event_stream(spark, d).select("client_id", "ts", F.array(F.col("value") / 100).alias("vec"))
    return _finished(spark, S.rounds(uploads, "1 day", "1 hour", 20))


@query("stream_enrich", f"WITH {EV_SQL} SELECT event_id, client_id, item_id, event_type, (k // 10)::VARCHAR AS decade FROM ev")
def stream_enrich(spark, d):
    """Every event with the features of its item."""
    items = U.event_items(spark, d).select("item_id", "event_type", "decade")
    return _finished(spark, S.enrich(S.event_stream(spark, d), items).select("event_id", "client_id", "item_id", "event_type", "decade"))


@query("stream_tuning")
def stream_tuning(spark, d):
    """Every client's parameters after all its events, stepped micro-batch by micro-batch from a common start."""
    return _finished(spark, S.personalise(S.event_stream(spark, d), np.zeros(2)), "update")


@query(
    "stream_hits",
    f"""WITH {EV_SQL}, tr AS (SELECT item_id, rank() OVER (ORDER BY count(*) DESC) AS rank FROM ev WHERE {U.USER_SPLIT_SQL} = 'train' GROUP BY 1),
    rk AS (SELECT client_id, rank FROM ev LEFT JOIN tr USING (item_id) WHERE stars > {U.POSITIVE_ABOVE} AND {U.USER_SPLIT_SQL} = 'test'),
    pu AS (SELECT client_id, k, avg(coalesce(rank <= k, false)::INTEGER) AS hits FROM rk, (SELECT unnest({list(HIT_KS)}) AS k) GROUP BY 1, 2)
    SELECT 0 AS batch, k, round(avg(hits), 6) AS hits, count(*) AS users FROM pu GROUP BY 2""",
)
def stream_hits(spark, d):
    """Hits of the test clients' positives as they arrive, by the training clients' popularity; items of one popularity share a rank."""
    train = U.event_rows(spark, d).where(protocol.user_split(F.col("client_id")) == "train").groupBy("item_id").agg(F.count("*").alias("n"))
    levels = train.groupBy("n").agg(F.count("*").alias("items"))
    above = F.coalesce(F.sum("items").over(Window.orderBy(F.col("n").desc()).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # one row per popularity
    ranks = train.join(levels.select("n", (above + 1).alias("rank")), "n").select("item_id", "rank").persist()

    def score(batch):
        positives = batch.where((F.col("value") > U.EVENT_CUTS[U.POSITIVE_ABOVE - 1]) & (protocol.user_split(F.col("client_id")) == "test"))
        return positives.join(ranks, "item_id", "left").select("client_id", "item_id", F.coalesce("rank", F.lit(1 << 62)).alias("rank"))

    found: list[dict] = []
    state = f"{ensure_checkpoint_dir(spark)}/stream_{uuid.uuid4().hex}"
    S.prequential(S.event_stream(spark, d), score, found, HIT_KS).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    ranks.unpersist()
    rows = [(r["batch"], r["k"], round(r["hits"], 6), r["users"]) for r in found]
    return spark.createDataFrame(rows, "batch int, k int, hits double, users long")
