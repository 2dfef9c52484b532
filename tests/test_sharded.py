"""Rounds over sharded embedding rows equal the dense rounds."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pytest

from fedlake.plans import data as D
from fedlake.plans import rounds as R
from fedlake.plans import sharded as S
from fedlake.plans.client import LocalPlan
from fedlake.sources import universes as U

SERVER = R.ServerPlan(rounds=2, clients=6)


@pytest.fixture(scope="module")
def prep(spark, folder):
    return D.prepare(U.universe(spark, folder, "P"))


def test_sharded_rounds_are_the_dense_rounds(spark, prep):
    net = R.build_net(prep)
    begin = net.start(SERVER.seed)
    dense = R.train_rounds(prep, net, LocalPlan(epochs=1), SERVER)
    model = S.train_sharded(prep, net, LocalPlan(epochs=1), SERVER, S.split_theta(spark, net, begin))
    assert not np.array_equal(dense.theta, begin)
    assert np.array_equal(model.dense().theta, dense.theta)
    assert model.table.count() == net.user_slots + net.item_slots
    assert [c["clients"] for c in model.costs] == [c["clients"] for c in dense.costs]
    assert all(0 < few["up_bytes"] < whole["up_bytes"] for few, whole in zip(model.costs, dense.costs, strict=True))


def test_a_bound_is_the_same_bound(spark, prep):
    net, plan, one = R.build_net(prep), LocalPlan(epochs=1, clip=0.01), replace(SERVER, rounds=1)
    dense = R.train_rounds(prep, net, plan, one)
    model = S.train_sharded(prep, net, plan, one, S.split_theta(spark, net, net.start(SERVER.seed)))
    assert np.allclose(model.dense().theta, dense.theta, rtol=0, atol=1e-9)


def test_noise_reaches_untouched_rows_and_is_accounted(spark, prep):
    net, one = R.build_net(prep), replace(SERVER, rounds=1, clients=1)
    plan = LocalPlan(epochs=1, clip=0.5)
    begin = S.start_table(spark, net)
    quiet, loud = (S.train_sharded(prep, net, plan, replace(one, noise=n), begin).dense() for n in ("none", "gaussian"))
    moved = loud.theta - quiet.theta
    assert (moved != 0).all()
    assert abs(moved.std() / (2 * plan.clip / one.clients) - 1) < 0.1
    assert 0 < loud.epsilon(1e-6).epsilon < float("inf") and quiet.epsilon(1e-6).epsilon == float("inf")


def test_what_sharded_rounds_refuse(prep):
    net = R.build_net(prep)
    for server, plan in ((replace(SERVER, noise="gaussian"), LocalPlan()), (replace(SERVER, aggregate="weighted"), LocalPlan()), (replace(SERVER, noise="laplace"), LocalPlan(clip=1.0))):
        with pytest.raises(ValueError):
            S.train_sharded(prep, net, plan, server)
