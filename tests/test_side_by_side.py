"""Clients trained side by side end where they end alone; rounds, tuning and ranking take them in groups."""

from __future__ import annotations

import numpy as np
import pytest

from fedlake.plans import client as C
from fedlake.plans import data as D
from fedlake.plans import rounds as R
from fedlake.plans.client import LocalPlan
from fedlake.plans.nets import TwoTower
from fedlake.sources import universes as U

RNG = np.random.default_rng(8)


def _row(client: int, n: int) -> dict:
    items = []
    for _ in range(n):
        k = int(RNG.integers(40))
        f, s = ([0, 0, 1, 2], [k % 3, 3 + k % 2, 5 + k % 4, 9 + k]) if k % 4 else ([0, 1, 2], [k % 3, 5 + k % 4, 9 + k])
        items.append({"f": f, "s": s, "y": float(RNG.integers(2))})
    return {"client_id": client, "uf": [0, 1, 1][: 2 + client % 2], "us": [client % 3, 4 + client % 5, 11][: 2 + client % 2], "items": items}


@pytest.mark.parametrize("hidden,act,out", [((6, 5), "relu", "sigmoid"), ((6,), "sigmoid", "linear"), ((), "relu", "sigmoid")])
def test_tuned_as_alone(hidden, act, out):
    net = TwoTower(12, 49, 2, 3, 4, hidden, act, out)
    theta = net.start(1) + RNG.standard_normal(net.size) * 0.1
    rows = [_row(k, n) for k, n in enumerate([1, 40, 7, 32, 33, 0, 3, 100, 12])]
    for epochs in (0, 1, 4):
        many = {r["client_id"]: mine for r, mine in C.tune_many(net, theta, rows, epochs, 0.3)}
        assert len(many) == len(rows)
        for row in rows:
            one, mine = C.tune(net, theta, row, epochs, 0.3), many[row["client_id"]]
            if one is None:
                assert mine is None
                continue
            whole, other = theta.copy(), theta.copy()
            for into, t in ((whole, one), (other, mine)):
                at = np.concatenate([C._places(net, "Eu", t.u_slots), C._places(net, "Ev", t.v_slots), np.arange(net.layout.at["Ev"].stop, net.size)])
                into[at] = t.theta
            assert np.allclose(whole, other, rtol=0, atol=1e-12)


@pytest.mark.parametrize("plan", [LocalPlan(batch=4), LocalPlan(clip=0.01), LocalPlan(clip=0.01, clip_norm="l1"), LocalPlan(clip=0.01, clip_each_step=True), LocalPlan(method="one_step"), LocalPlan(method="maml"), LocalPlan(lam_sup=0.5)])
def test_updates_as_alone(plan):
    net = TwoTower(12, 49, 2, 3, 4, (6, 5))
    theta = net.start(1) + RNG.standard_normal(net.size) * 0.1
    rows = [_row(k, n) for k, n in enumerate([1, 40, 7, 33, 12])]
    many = {r["client_id"]: found for r, found in C.client_updates(net, theta, rows, plan, 3)}
    for row in rows:
        whole, other = np.zeros(net.size), np.zeros(net.size)
        for into, (at, values) in ((whole, C.client_update(net, theta, row, plan, 3)), (other, many[row["client_id"]])):
            into[at] = values
        assert len(np.unique(many[row["client_id"]][0])) == len(many[row["client_id"]][0])
        assert np.allclose(whole, other, rtol=0, atol=1e-12)


def test_groups_hold_every_client():
    net = TwoTower(12, 49, 2, 3, 64, (128, 64))
    rows = [_row(k, 1 + k % 9) for k in range(150)]
    groups = list(C.in_groups(net, rows))
    assert sorted(r["client_id"] for g in groups for r in g) == list(range(150))
    assert 1 < max(map(len, groups)) <= C.TOGETHER and max(map(len, groups)) * (net.size - net.layout.at["Ev"].stop) <= C.HELD


def test_kept_cases_rank_alike(spark, folder):
    prep = D.prepare(U.universe(spark, folder, "P"))
    net = R.build_net(prep)
    model = R.Model(prep, net, net.start())
    before = sorted(map(tuple, model.rank(epochs=1).collect()))
    D.keep_cases(prep)
    assert prep.cases.is_cached and sorted(map(tuple, model.rank(epochs=1).collect())) == before
