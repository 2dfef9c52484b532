"""Kernels over the rows that a client names, and sums and ranks built on them, against the whole vectors."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pyarrow as pa
import pytest

from fedlake.operators import scoring
from fedlake.plans import pretrain, rounds as R
from fedlake.plans.baselines import ncf
from fedlake.plans.client import LocalPlan, client_batch, client_update, local_sgd, personalise, tune
from fedlake.plans.nets import Bags, NeuralCF, SequenceEncoder, TwoTower
from fedlake.plans.ranking import ItemTable, Scorer

RNG = np.random.default_rng(3)
#: Items with repeated side slots (fields 0, 0, 1) and their id (field 2) last; every fourth has a side slot less.
F = [[0, 0, 1, 2] if k % 4 else [0, 1, 2] for k in range(40)]
S = [[k % 3, 3 + k % 2, 5 + k % 4, 9 + k] if k % 4 else [k % 3, 5 + k % 4, 9 + k] for k in range(40)]
ROW = {"client_id": 5, "uf": [0, 1], "us": [2, 7], "items": [{"f": F[k], "s": S[k], "y": float(k % 2)} for k in range(0, 30, 3)]}


def net_of(hidden=(6, 5), act="relu"):
    net = TwoTower(12, 49, 2, 3, 4, hidden, act)
    return net, net.start(1) + RNG.standard_normal(net.size) * 0.1


@pytest.mark.parametrize("plan", [LocalPlan(rate=0.5, batch=4), LocalPlan(rate=0.5, clip=0.01), LocalPlan(method="one_step"), LocalPlan(method="maml"), LocalPlan(method="fomaml")])
def test_an_update_names_few_places(plan):
    net, theta = net_of()
    at, values = client_update(net, theta, ROW, plan, 1)
    assert len(at) < net.size and len(np.unique(at)) == len(at)
    if plan.method == "sgd" and plan.clip is None:
        whole = local_sgd(net, theta, client_batch(ROW), plan, 1, 5) - theta
        assert np.allclose(whole[at], values, rtol=0, atol=1e-12) and np.abs(np.delete(whole, at)).max() == 0


@pytest.mark.parametrize("hidden,act", [((6, 5), "relu"), ((6,), "sigmoid"), ((), "relu")])
def test_scores_of_the_catalogue(hidden, act):
    net, theta = net_of(hidden, act)
    table = ItemTable.of(np.arange(40), pa.array(F), pa.array(S))
    assert len(table.sides) < len(table)
    scorer, user, items = Scorer(net, theta, table), Bags.of([ROW["uf"]], [ROW["us"]]), Bags.of(F, S)
    for epochs in (0, 3, 0):  # the shared tables are as before after a user's rows were in them
        expected = net.item_scores(personalise(net, theta, ROW, epochs, 0.5), user, items)
        assert np.allclose(scorer.scores(user, tune(net, theta, ROW, epochs, 0.5)), expected, rtol=0, atol=1e-12)


@pytest.mark.parametrize("levels", [3, 50])
def test_counts_above(levels):
    scores, ids = RNG.integers(0, 40, 300) / 7, RNG.permutation(300)
    own = RNG.choice(300, levels, replace=False)
    seen = np.union1d(own, RNG.choice(300, 60))
    unseen = np.setdiff1d(np.arange(300), seen)
    expected = [sum(scores[j] > scores[o] or (scores[j] == scores[o] and ids[j] < ids[o]) for j in unseen) for o in own]
    assert scoring.count_above(scores, ids, seen, scores[own], ids[own]).tolist() == expected


def test_sums_take_places_in_one_job(spark, monkeypatch):
    rows = spark.createDataFrame([(k, [k]) for k in range(40)], "client_id long, items array<long>").repartition(8, "client_id")
    size = 3000
    kernel = lambda row: (np.array([row["client_id"], 2000 + row["client_id"]]), np.array([1.0, 0.5]))
    expected = np.zeros(size)
    expected[:40], expected[2000:2040] = 1, 0.5
    for gathered in (R.GATHERED, 1):
        monkeypatch.setattr(R, "GATHERED", gathered)
        spark.sparkContext.setJobGroup(f"sums-{gathered}", "sums")
        total, n, seen = R.summed_deltas(rows, kernel, size)
        jobs = spark.sparkContext.statusTracker().getJobIdsForGroup(f"sums-{gathered}")
        assert np.array_equal(total, expected) and (n, seen) == (40, 40)
        assert len(jobs) < 8  # partitions don't wait for each other
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def test_views_name_few_rows():
    encoder = SequenceEncoder(49, 4)
    phi = encoder.start(2)
    item = lambda k: {"item_no": k, "f": F[k], "s": S[k]}
    sessions = [{"session_id": n, "seq": [item((3 * n + j) % 40) for j in range(5)]} for n in range(4)]
    pool = pretrain.Pool(np.cumsum([len(s) for s in S]), np.concatenate(F), np.concatenate(S))
    one, whole = pretrain.ssl_gradient(encoder, phi, sessions, 0.5, 0.5, np.random.default_rng(1), [item(k) for k in range(40)])
    head = encoder.layout.at["Ev"].stop
    loss, slots, rows, rest = pretrain.ssl_update(encoder, encoder.layout.view(phi, "Ev"), phi[head:], sessions, 0.5, 0.5, np.random.default_rng(1), pool)
    again = np.zeros_like(phi)
    again[R.row_places(slots, 4)], again[head:] = rows, rest
    assert np.isclose(one, loss) and np.allclose(whole, again, rtol=0, atol=1e-12)
    drawn = pretrain._other_items(pool, 7, np.random.default_rng(4)), pretrain._other_items([item(k) for k in range(40)], 7, np.random.default_rng(4))
    assert drawn[0] == drawn[1]


def test_ncf_over_one_users_rows():
    net = NeuralCF(6, 30, 3, 4)
    theta, items, y = net.start(), np.array([2, 5, 11]), np.array([1.0, 0.0, 1.0])
    small, mine, at = ncf.compact(net, theta, 4, items)
    whole = np.zeros(net.size)
    whole[at] = small.gradient(mine, np.zeros(3, np.int64), np.arange(3), y)
    assert np.allclose(whole, net.gradient(theta, np.full(3, 4), items, y), rtol=0, atol=1e-12)
    expected = np.array([net.scores(theta, np.full(30, u), np.arange(30)) for u in (1, 4)])
    assert np.allclose(ncf.all_scores(net, theta, [1, 4]), expected, rtol=0, atol=1e-12)


def test_joint_update_touches_what_its_views_name():
    net, theta = net_of()
    extra = lambda t: (np.array([net.layout.at["Ev"].start]), np.array([0.25]))
    plan = LocalPlan(rate=0.5, epochs=1)
    at, values = client_update(net, theta, ROW, plan, 0, extra)
    plain = local_sgd(net, theta, client_batch(ROW), replace(plan), 0, 5) - theta
    plain[net.layout.at["Ev"].start] -= 0.5 * 0.25
    whole = np.zeros(net.size)
    whole[at] = values
    assert np.allclose(whole, plain, rtol=0, atol=1e-12)
