"""Top lists of scalar products by falling norm: equal to scoring all pairs, without forming them."""

from __future__ import annotations

import numpy as np
import pytest

from fedlake.operators import scoring
from fedlake.plans import data as D
from fedlake.plans.baselines import fcf
from fedlake.sources import universes as U

SCHEMA = "id int, features array<float>"


def by_hand(u: np.ndarray, ids: np.ndarray, v: np.ndarray, k: int) -> list[list[int]]:
    scores = scoring.dots(u, v)
    return [ids[np.lexsort((ids, -s))[:k]].tolist() for s in scores]


def vectors(users: int = 300, items: int = 700) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Norms far apart, copies, zero vectors and opposite signs."""
    r = np.random.default_rng(3)
    u = r.standard_normal((users, 4)).astype(np.float32)
    v = (r.standard_normal((items, 4)) * r.pareto(2, items)[:, None]).astype(np.float32)
    v[5:25], v[40:60], u[7], u[9] = v[3], 0, 0, -np.abs(u[9])
    return u, r.permutation(items * 2)[:items].astype(np.int64), v


@pytest.mark.parametrize("parts", [1, 3])
def test_lists_equal_all_pairs(parts):
    u, ids, v = vectors()
    block = scoring.norm_order(ids, v)
    scores, found = np.full((len(u), 10), -np.inf), np.zeros((len(u), 10), np.int64)
    for at in np.array_split(np.arange(len(ids)), parts):
        scoring.best_by_norm(u, tuple(x[at] for x in block), scores, found)
    assert found.tolist() == by_hand(u, ids, v, 10)


def test_equal_norms_take_the_whole_catalogue():
    u, ids, v = vectors()
    v = v[60:] / np.linalg.norm(v[60:], axis=1)[:, None]
    scores, found = np.full((len(u), 10), -np.inf), np.zeros((len(u), 10), np.int64)
    scoring.best_by_norm(u, scoring.norm_order(ids[60:], v), scores, found)
    assert found.tolist() == by_hand(u, ids[60:], v, 10)


def test_few_products():
    u, ids, v = vectors(100, 50_000)
    scores, found = np.full((98, 10), -np.inf), np.zeros((98, 10), np.int64)
    u = np.delete(u, [7, 9], axis=0)
    assert scoring.best_by_norm(u, scoring.norm_order(ids, v), scores, found) < 0.05 * len(u) * len(ids)


@pytest.mark.parametrize("block", [1 << 20, 200])
def test_frames_equal_all_pairs(spark, block):
    u, ids, v = vectors(120)
    users, items = (spark.createDataFrame([(int(i), x.tolist()) for i, x in zip(names, rows, strict=True)], SCHEMA) for names, rows in ((np.arange(len(u)), u), (ids, v)))
    found = scoring.top_by_norm(users, items, 10, block).toPandas().sort_values(["client_id", "rank"])
    assert found["item_id"].to_numpy().reshape(-1, 10).tolist() == by_hand(u, ids, v, 10)


def test_fewer_items_than_asked(spark):
    users = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 0.0])], SCHEMA)
    items = spark.createDataFrame([(4, [1.0, 1.0]), (3, [2.0, 0.0])], SCHEMA)
    assert sorted(map(tuple, scoring.top_by_norm(users, items, 10).collect())) == [(1, 1, 3), (1, 2, 4), (2, 1, 3), (2, 2, 4)]


def test_als_without_all_pairs(spark, folder, monkeypatch):
    """Every client of the model gets its ten items, and the library's pairing of all users with all items isn't called."""
    from pyspark.ml.recommendation import ALSModel

    def refuse(*_):
        raise AssertionError("users times items")

    monkeypatch.setattr(ALSModel, "recommendForAllUsers", refuse)
    prep = D.prepare(U.universe(spark, folder, "P"))
    model = fcf.als_model(prep)
    users, items = model.userFactors.orderBy("id").collect(), model.itemFactors.orderBy("id").collect()
    u, v = (np.array([r.features for r in rows], np.float32) for rows in (users, items))
    found = fcf.central_als(prep).toPandas().sort_values(["client_id", "rank"])
    assert found["client_id"].tolist() == [r.id for r in users for _ in range(10)]
    assert found["item_id"].to_numpy().reshape(-1, 10).tolist() == by_hand(u, np.array([r.id for r in items]), v, 10)
