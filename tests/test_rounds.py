"""Federated rounds on the smallest tables: identities between methods, determinism, learnability."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from fedlake.operators import metrics, sampling
from fedlake.plans import data as D
from fedlake.plans import pretrain, rounds as R
from fedlake.plans.client import LocalPlan
from fedlake.plans.nets import SequenceEncoder
from fedlake.sources import universes as U


@pytest.fixture(scope="module")
def prep(spark, folder):
    return D.prepare(U.universe(spark, folder, "P"))


@pytest.fixture(scope="module")
def net(prep):
    return R.build_net(prep)


SERVER = R.ServerPlan(rounds=2, clients=8)


def test_no_noise_and_no_bound_is_the_plain_method(prep, net):
    plain = R.train_rounds(prep, net, LocalPlan(epochs=1), SERVER)
    private = R.train_rounds(prep, net, LocalPlan(epochs=1, clip=1e9), replace(SERVER, noise="gaussian", z=0.0))
    assert np.array_equal(plain.theta, private.theta)
    assert private.epsilon(1e-6).epsilon == float("inf")


def test_sums_ignore_partitioning(prep, net, spark):
    from fedlake.plans.client import client_delta

    packed = D.pack(prep, D.splits(prep)[0]).limit(12)
    rows = packed.collect()
    same = spark.createDataFrame(rows, packed.schema)
    theta = net.start()
    kernel = lambda row: client_delta(net, theta, row, LocalPlan(epochs=1), 0)
    one, eight = (R.summed_deltas(same.repartition(n), kernel, net.size)[0] for n in (1, 8))
    assert np.array_equal(one, eight)


def test_noise_needs_a_bound_and_is_accounted(prep, net):
    with pytest.raises(ValueError):
        R.train_rounds(prep, net, LocalPlan(), replace(SERVER, noise="gaussian"))
    model = R.train_rounds(prep, net, LocalPlan(epochs=1, clip=1.0), replace(SERVER, noise="gaussian", budget=1e-3, rounds=3))
    assert len(model.costs) == 0  # the first round would already exceed the budget
    model = R.train_rounds(prep, net, LocalPlan(epochs=1, clip=1.0), replace(SERVER, noise="laplace"))
    s = model.epsilon(1e-6)
    assert 0 < s.epsilon < float("inf") and s.compositions == 2


def test_draws_are_exact(prep, spark):
    clients = D.splits(prep)[0].select("client_id").distinct()
    counts = {r["round"]: r["n"] for r in sampling.draw_fixed(clients, 8, 5).groupBy("round").agg(F.countDistinct("client_id").alias("n")).collect()}
    assert counts == dict.fromkeys(range(5), 8)
    assert {r["count"] for r in sampling.draw_schedule(spark, 100, 20, 4).groupBy("round").count().collect()} == {20}
    assert sampling.draw_schedule(spark, 10, 10, 2).count() == 20
    with pytest.raises(ValueError):
        sampling.draw_fixed(clients, 10**6, 1)


def test_measures_grow_with_k(prep, net):
    users = metrics.per_user(R.Model(prep, net, net.start()).rank(epochs=1))
    rows = {(r.client_id, r.k): r for r in users.collect()}
    for (c, k), r in rows.items():
        assert r.ndcg <= r.hits + 1e-12
        if k > 5:
            low = rows[(c, {10: 5, 20: 10, 30: 20}[k])]
            assert r.hits >= low.hits and r.ndcg >= low.ndcg


def test_planted_preferences_are_learned(spark, folder):
    base = U.universe(spark, folder, "P")
    alike = base.users.withColumn("segment", F.lit("any"))  # all clients share one taste over item types
    prep = D.prepare(replace(base, interactions=U.plant_preferences(base.interactions, alike, base.items, noise=0.0)))
    net = R.build_net(prep)
    train, test = D.splits(prep)
    observe = R.held_out_loss(prep, net, test)
    model = R.train_rounds(prep, net, LocalPlan(epochs=10, rate=1.0), R.ServerPlan(rounds=10, clients=30), train)
    assert observe(model.theta) < observe(net.start()) - 0.02


def test_round_trip_of_parameters(prep, net, spark, tmp_path):
    model = R.Model(prep, net, net.start(3))
    R.save_theta(model, f"file:{tmp_path}/theta")
    assert np.array_equal(R.load_theta(spark, f"file:{tmp_path}/theta", net), model.theta)


def test_pretraining_lowers_its_loss_on_planted_sequences(spark, folder):
    prep = D.prepare(U.universe(spark, folder, "E"))
    few = prep.items.orderBy("item_no").limit(6).select("item_id").collect()  # every session repeats a handful of items
    choice = F.element_at(F.array(*[F.lit(r.item_id) for r in few]), (F.col("event_id") % 6 + 1).cast("int"))
    rows = U.event_rows(spark, folder).withColumn("item_id", choice)
    sequences = pretrain.client_sequences(prep, rows, 24 * 3600, "event_id")
    encoder = SequenceEncoder(prep.n_item_slots, 8)
    _, losses = pretrain.fit_items(prep, encoder, sequences, 4, 12, epochs=15, rate=0.5, lam_segment=0.0)
    assert losses[-1] < losses[0] - 0.02


def test_joint_stage_gives_a_statement(spark, folder, prep, net):
    from fedlake.plans import experiments as X

    base = U.universe(spark, folder, "P")
    p, sequences, encoder = X.private_setup(spark, folder, "P", base)
    model = pretrain.fit_private(p, net, LocalPlan(clip=1.0, epochs=1, lam_item=0.5, lam_segment=0.5), replace(SERVER, noise="gaussian"), 2, sequences, encoder, 1)
    assert "stage 2" in model.epsilon(1e-6).covers


def test_early_stop(prep, net):
    model = R.train_rounds(prep, net, LocalPlan(rate=0.0), replace(SERVER, rounds=6, tolerance=1e-6, patience=1), observe=lambda theta: 1.0)
    assert len(model.costs) == 2
