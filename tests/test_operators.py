"""Worked examples of sequences, measures, relational helpers, sources and streams."""

from __future__ import annotations

import datetime as dt
import math
import uuid

import numpy as np
import pytest
from pyspark.sql import functions as F

from fedlake.operators import metrics, relops, scoring
from fedlake.operators import sequences as S
from fedlake.sources import tables
from fedlake.sources import universes as U
from fedlake.streaming import streams


def test_gain_examples(spark):
    ranks = spark.createDataFrame([(1, i, r) for i, r in enumerate((1, 2, 4, 11))], "client_id long, item_id long, rank long")
    row = metrics.per_user(ranks, (10,)).first()
    assert row.hits == 0.75 and abs(row.ndcg - (1 + 0.63093 + 0.43068) / 4) < 1e-4
    two = spark.createDataFrame([(1, 1, 1), (1, 2, 99), (2, 1, 1)], "client_id long, item_id long, rank long")
    assert metrics.summary(metrics.per_user(two, (10,))).where("metric = 'hits'").first().value == 0.75
    assert metrics.relative_gap(0.5, 0.4) == pytest.approx(0.2)
    assert metrics.bootstrap(metrics.per_user(two, (10,)), 20).count() == 1


def test_count_rank_against_a_sort():
    r = np.random.default_rng(1)
    for _ in range(30):
        n = int(r.integers(3, 40))
        ids, scores = np.arange(n), r.integers(0, 5, n) / 5
        seen = np.sort(r.choice(n, int(r.integers(1, n)), replace=False))
        own = seen[: int(r.integers(1, len(seen) + 1))]
        got = scoring.count_above(scores, ids, seen, scores[own], own)
        for g, i in zip(got, own, strict=True):
            pool = sorted([*np.setdiff1d(ids, seen), i], key=lambda j: (-scores[j], j))
            assert pool.index(i) == g


def test_item_blocks_add_up(spark):
    packed = spark.createDataFrame([(1, [2, 5, 9], [5]), (2, [1, 3], [1, 3])], "client_id long, seen array<long>, positives array<long>")
    items = spark.range(40).withColumnRenamed("id", "item_id")
    whole = {(r.client_id, r.item_id): r["rank"] for r in scoring.ranks(packed, items, scoring.fixed_score).collect()}
    parts = {(r.client_id, r.item_id): r["rank"] for r in scoring.ranks(packed, items, scoring.fixed_score, block=7).collect()}
    assert whole == parts


def events(spark, rows):
    base = dt.datetime(2024, 1, 1)
    return spark.createDataFrame([(k, 1, item, base + dt.timedelta(hours=h)) for k, (item, h) in enumerate(rows)], "event_id long, client_id long, item_id long, ts timestamp_ntz")


def test_sessions_and_views(spark):
    rows = events(spark, [(1, 0), (2, 1), (3, 2), (4, 3), (5, 40), (6, 41), (7, 42), (8, 100)])
    sess = S.sessions(rows)
    assert [(r.n, r["items"]) for r in sess.orderBy("session_id").collect()] == [(4, [1, 2, 3, 4]), (3, [5, 6, 7]), (1, [8])]
    items = spark.range(1, 10).withColumnRenamed("id", "item_id")
    for v in S.mask_item(sess, items).join(sess, ["client_id", "session_id"]).collect():
        wrong = [k for k, (a, b) in enumerate(zip(v.view, v["items"], strict=True)) if a != b]
        assert wrong == [v.pos] and v.negative != v.target == v["items"][v.pos]
    views = S.mask_segment(sess)
    for v in views.join(sess, ["client_id", "session_id"]).collect():
        assert len(v.view) == len(v["items"]) and v.target == v["items"][v.pos : v.pos + v.len]
        assert v.view[: v.pos] == v["items"][: v.pos] and v.view[v.pos + v.len :] == v["items"][v.pos + v.len :]
    masked = S.mask_item(sess, items)
    bad = S.negative_items(masked, items).join(masked, ["client_id", "session_id"]).where("item_id = target")
    assert bad.count() == 0
    assert S.negative_segments(views, sess).where("session_id = other_session").count() == 0


def test_ordinals_are_dense(spark):
    ids = spark.createDataFrame([(x,) for x in (5, 1, 2500, 1000, 999, 7)], "item_id long")
    assert [(r.item_id, r.ordinal) for r in S.item_ordinals(ids).orderBy("item_id").collect()] == [(1, 0), (5, 1), (7, 2), (999, 3), (1000, 4), (2500, 5)]


def test_asof_and_range(spark):
    left = spark.createDataFrame([(1, 5, 10), (1, 1, 11), (2, 9, 12)], "k long, t long, e long")
    right = spark.createDataFrame([(1, 3, 100), (1, 5, 101), (2, 10, 102)], "k long, t long, v long")
    assert {(r.e, r.out) for r in relops.asof(left, right, "k", "t", "v", "out", "v").collect()} == {(10, 101), (11, None), (12, None)}
    bands = relops.range_join(spark.createDataFrame([(10.0,), (11.0,)], "value double"), [(0, 10, 1), (10, 20, 2)], "value", "b")
    assert sorted(r.b for r in bands.collect()) == [1, 2]


def test_long_tail(spark, folder):
    base = U.purchases(spark, folder)
    thin = U.thin_activity(base)
    assert thin.count() < base.count() and thin.groupBy("client_id").count().agg(F.min("count")).first()[0] >= 1
    with pytest.raises(ValueError):
        U.universe(spark, folder, "X")


def test_client_lake_and_shards(spark, folder, tmp_path):
    path = f"file:{tmp_path}/lake"
    rows = U.purchases(spark, folder)
    tables.save_client_lake(rows, path, 8)
    few = spark.createDataFrame([(1,), (2,)], "client_id long")
    assert tables.read_scheduled(spark, path, few, 8).count() == rows.where("client_id in (1, 2)").count()
    tables.register_client_shards(spark)
    shards = spark.read.format("client_shards").option("path", path).option("buckets", "8").load()
    assert shards.count() == rows.count()
    tables.save(rows.limit(5), f"{tmp_path}/j", kind="json")
    assert tables.load_as(spark, f"{tmp_path}/j", "json").count() == 5


def test_activity_stream_equals_its_batch_twin(spark, folder, compare):
    from fedlake import catalog

    q = catalog.queries()
    compare(q["stream_activity"](spark, folder).toPandas(), q["daily_activity_tumbling"](spark, folder).toPandas())


def test_closed_sessions_are_batch_sessions(spark, folder):
    from fedlake import catalog

    q = catalog.queries()
    closed = {(r.client_id, r.start_ts.strftime("%Y-%m-%d %H:%M:%S"), r.n) for r in q["stream_sessions"](spark, folder).collect()}
    batch = {(r.client_id, r.start_ts, r.n) for r in q["sessions_gap"](spark, folder).collect()}
    assert closed and len(closed & batch) >= 0.95 * len(closed)


def test_online_tuning_and_test_then_train(spark, folder, tmp_path):
    tuned = streams.personalise(streams.event_stream(spark, folder), np.zeros(2))
    name = f"t{uuid.uuid4().hex}"
    rows = streams.run_once(tuned, name, f"{tmp_path}/c", "update").collect()
    assert rows and all(math.isfinite(r.w0) and r.seen > 0 for r in rows)
    sink: list = []
    score = lambda b: b.select("client_id", "item_id", (F.pmod(F.xxhash64("item_id"), F.lit(20)) + 1).alias("rank"))
    query = streams.prequential(streams.event_stream(spark, folder), score, sink).option("checkpointLocation", f"{tmp_path}/p").trigger(availableNow=True).start()
    assert query.awaitTermination(60)
    assert {x["k"] for x in sink} == {5, 10}


def test_enriched_stream(spark, folder, tmp_path):
    items = U.event_items(spark, folder)
    rows = streams.run_once(streams.enrich(streams.event_stream(spark, folder), items), f"e{uuid.uuid4().hex}", f"{tmp_path}/c")
    assert rows.where("event_type is null").count() == 0
