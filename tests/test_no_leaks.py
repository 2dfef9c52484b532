"""Baselines don't see what is ranked; noise has the sensitivity it is measured for; graphs cover all co-users."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from fedlake.operators import dp, scoring
from fedlake.operators.graph import co_user_means
from fedlake.plans import data as D
from fedlake.plans import rounds as R
from fedlake.plans.baselines import fcf, fedgraph
from fedlake.plans.client import LocalPlan
from fedlake.sources import universes as U


@pytest.fixture(scope="module")
def prep(spark, folder):
    return D.prepare(U.universe(spark, folder, "E"))


def without_ranked_labels(prep):
    """The same universe with every label of the ranking halves turned round."""
    ranked = D.splits(prep)[1].where("row_split = 'rank'").select("client_id", "item_no", F.lit(1).alias("_turned"))
    rows = prep.rows.join(ranked, ["client_id", "item_no"], "left").withColumn("label", F.when(F.col("_turned").isNull(), F.col("label")).otherwise(1 - F.col("label"))).drop("_turned")
    return replace(prep, rows=rows)


def test_graph_and_factors_ignore_the_ranking_halves(prep):
    other = without_ranked_labels(prep)
    assert {tuple(r) for r in fedgraph.graph_rows(prep).collect()} == {tuple(r) for r in fedgraph.graph_rows(other).collect()}
    assert np.array_equal(fedgraph.fit(prep, 1, 4)[0], fedgraph.fit(other, 1, 4)[0])
    assert np.array_equal(fcf.fit(prep, 1, 4), fcf.fit(other, 1, 4))


def test_row_weights_and_noise_are_refused(prep):
    with pytest.raises(ValueError):
        R.train_rounds(prep, R.build_net(prep), LocalPlan(clip=1.0), R.ServerPlan(rounds=1, clients=4, aggregate="weighted", noise="gaussian"))


def test_bounds_by_norm():
    v = np.full(100, 0.5)
    assert abs(np.abs(dp.clip_vector_l1(v, 1.0)).sum() - 1) < 1e-12 and np.abs(dp.clip_vector(v, 1.0)).sum() > 9  # the L2 bound leaves the L1 norm open


def test_members_are_the_drawn_clients(prep):
    model = R.train_rounds(prep, R.build_net(prep), LocalPlan(epochs=1), R.ServerPlan(rounds=2, clients=3))
    assert 3 <= model.members.count() <= 6


def test_co_user_means_cover_all_pairs(spark):
    r = np.random.default_rng(2)
    pairs = sorted({(int(c), int(i)) for c, i in zip(r.integers(0, 12, 60), r.integers(0, 9, 60), strict=True)} | {(99, 99)})
    vectors = {c: float(r.normal()) for c in {c for c, _ in pairs}}
    got = {x.client_id: x.v for x in co_user_means(spark.createDataFrame(pairs, "client_id long, item_id long"), spark.createDataFrame(list(vectors.items()), "client_id long, v double"), ["v"]).collect()}
    want = {}
    for c in vectors:
        means = [np.mean([vectors[u] for u, j in pairs if j == i and u != c]) for k, i in pairs if k == c and any(j == i and u != c for u, j in pairs)]
        if means:
            want[c] = float(np.mean(means))
    assert got.keys() == want.keys() and 99 not in got and all(abs(got[c] - want[c]) < 1e-9 for c in want)


def test_best_equals_a_sort():
    r = np.random.default_rng(3)
    for _ in range(50):
        n, k = int(r.integers(1, 40)), int(r.integers(1, 12))
        scores, ids = r.integers(0, 6, n) / 6, r.permutation(n)
        assert scoring.best_places(scores, ids, k).tolist() == np.lexsort((ids, -scores))[:k].tolist()
