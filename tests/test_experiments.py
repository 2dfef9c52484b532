"""Experiments: membership labels, attack samples, published settings, streams' results."""

from __future__ import annotations

from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from fedlake import catalog
from fedlake.plans import attack as A
from fedlake.plans import data as D
from fedlake.plans import experiments as X
from fedlake.plans import rounds as R
from fedlake.plans.baselines import central
from fedlake.plans.client import LocalPlan
from fedlake.sources import universes as U


@pytest.fixture(scope="module")
def events(spark, folder):
    return U.universe(spark, folder, "E")


@pytest.fixture(scope="module")
def prep(events):
    return D.prepare(events)


def test_attack_labels_are_the_schedule(prep):
    users = prep.rows.select("client_id").distinct()
    model = R.train_rounds(prep, R.build_net(prep), LocalPlan(epochs=1), R.ServerPlan(rounds=2, clients=3), prep.rows)
    inside = {r.client_id for r in model.members.collect()}
    labels = {r.client_id: r.label for r in A._labels(model, users).collect()}
    assert {c for c, y in labels.items() if y == 1} == inside and len(labels) == users.count() > len(inside)
    rows = A.samples(model, users).collect()
    assert len(rows) == users.count() and {len(r.features) for r in rows} == {3 * A.BUCKETS + 1}
    assert all(abs(sum(r.features[A.BUCKETS : 2 * A.BUCKETS]) - A.LIST) < 1e-9 for r in rows)


def test_attack_table(events):
    rows = X.mia(events, (5.0,), 2).collect()
    assert [r.target for r in rows] == ["metafed", "metafed_dp_5", "metafed_laplace_5"]
    assert len({r.users for r in rows}) == 1 and all(0.2 < r.member_share < 0.8 and 0 <= r.accuracy <= 1 for r in rows)


def test_published_settings_run(prep):
    full = X.published("E")
    assert (full["rounds"], full["clients"], full["local"].epochs, full["net"]["hidden"]) == (40, 30, 100, (128, 64, 32, 16))
    ranks = X.fit_ranks("metafed", prep, 1, 2, replace(full["local"], epochs=1), full["net"])
    assert ranks.count() > 0


def test_leaderboard_and_sweeps(events):
    board = X.wide(X.leaderboard(events, ("popularity", "random"), 1, 2), "E").collect()
    assert {(r.method, r.metric) for r in board} == {(m, x) for m in ("popularity", "random") for x in ("hits", "ndcg")}
    assert all(0 <= r.at_5 <= r.at_30 <= 1 for r in board if r.metric == "hits")
    swept = X.sweep(events, "rounds", (1, 2), {"clients": 2, "epochs": 1}).collect()
    assert [r.value for r in swept] == [1, 2]


def test_central_tasks_learn(spark, folder):
    base = U.universe(spark, folder, "P")
    alike = base.users.withColumn("segment", F.lit("any"))
    prep = D.prepare(replace(base, interactions=U.plant_preferences(base.interactions, alike, base.items, noise=0.0)))
    net = R.build_net(prep)
    observe = R.held_out_loss(prep, net, D.splits(prep)[1])
    model = central.fit(prep, net, 6, local=LocalPlan(epochs=10, rate=1.0))
    assert observe(model.theta) < observe(net.start()) - 0.02


@pytest.mark.parametrize("name", ["stream_dedup", "stream_rounds"])
def test_streams_end_in_files(name, spark, folder):
    first, again = (sorted(map(tuple, catalog.queries()[name](spark, folder).collect()), key=str) for _ in range(2))
    assert first and first == again


def test_tuned_stream_covers_every_client(spark, folder):
    rows = catalog.queries()["stream_tuning"](spark, folder).collect()
    events = {r.user_id: r.n for r in spark.read.parquet(f"{folder}/events.parquet").groupBy("user_id").count().withColumnRenamed("count", "n").collect()}
    assert {r.client_id: r.seen for r in rows} == events
    assert any(r.w0 or r.w1 for r in rows)
