"""Ranks beyond the largest k that measures ask for are settled by chunks of the catalogue; measures stay exactly the same."""

from __future__ import annotations

import numpy as np
import pytest

from fedlake.operators import metrics, scoring
from fedlake.plans import data as D
from fedlake.plans import ranking
from fedlake.plans import rounds as R
from fedlake.plans.client import tune
from fedlake.plans.nets import Bags
from fedlake.sources import universes as U


@pytest.fixture(scope="module")
def prep(spark, folder):
    return D.prepare(U.universe(spark, folder, "P"))


def _users(prep):
    return D.ranking_users(prep, D.splits(prep)[1]).toArrow().to_pylist()


@pytest.mark.parametrize("act,hidden,scale", [("relu", (16,), 1.0), ("sigmoid", (16, 8), 3.0), ("relu", (), 1.0), ("relu", (16,), 0.0)])
def test_settled_users_have_no_rank_within_most(prep, monkeypatch, act, hidden, scale):
    monkeypatch.setattr(ranking, "CHUNK", 64)
    net = R.build_net(prep, hidden=hidden, act=act)
    theta = net.start(3)
    theta = theta * scale + scale * np.random.default_rng(5).standard_normal(len(theta)) * 0.3
    settled = 0
    for row in _users(prep):
        scorer = ranking.Scorer(net, theta, D.item_table(prep))
        for epochs in (0, 3):
            mine = tune(net, theta, row, epochs, 0.05)
            user, own, seen = Bags.of([row["uf"]], [row["us"]]), np.array(row["positives"]), np.array(row["seen"])
            scores = scorer.scores(user, mine)
            assert np.allclose(scorer._scorer(user, mine)(np.arange(len(scores))), scores, rtol=1e-12, atol=1e-12)
            for most in (1, 5, 20):
                if scorer.all_below(user, mine, own, seen, most):
                    settled += 1
                    assert (scoring.count_above(scores, scorer.table.ids, seen, scores[own], own) >= most).all()
    assert settled if scale else not settled  # equal scores settle nothing


def test_measures_stay_the_same(prep):
    net = R.build_net(prep)
    model = R.Model(prep, net, net.start())
    exact, short = (model.rank(epochs=1, most=m).toPandas().sort_values(["client_id", "item_id"]).reset_index(drop=True) for m in (None, 5))
    assert exact[["client_id", "item_id"]].equals(short[["client_id", "item_id"]])
    near = exact["rank"] <= 5
    assert (exact["rank"][near] == short["rank"][near]).all() and (short["rank"][~near] > 5).all()
    assert (exact["rank"] != short["rank"]).any()
    whole = metrics.summary(metrics.per_user(model.rank())).toPandas().sort_values(["metric", "k"]).reset_index(drop=True)
    now = model.summary().toPandas().sort_values(["metric", "k"]).reset_index(drop=True)
    assert np.allclose(whole["value"], now["value"], rtol=1e-12) and whole["users"].equals(now["users"])
