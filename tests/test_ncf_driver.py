"""Long sums reach the driver a part at a time; users beyond the largest k are settled by a chunk, with the same measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from fedlake.plans import data as D
from fedlake.plans import rounds as R
from fedlake.plans.baselines import ncf
from fedlake.sources import universes as U


def test_long_sums_come_in_parts(spark, monkeypatch):
    monkeypatch.setattr(R, "GATHERED", 1)
    monkeypatch.setattr(DataFrame, "toArrow", lambda self: (_ for _ in ()).throw(AssertionError("the whole sum at once")))
    rows = spark.createDataFrame([(k, [k]) for k in range(40)], "client_id long, items array<long>").repartition(8, "client_id")
    total, n, seen = R.summed_deltas(rows, lambda row: (np.array([row["client_id"], 2999]), np.array([-1.5, 0.5])), 3000)
    expected = np.zeros(3000)
    expected[:40], expected[2999] = -1.5, 20
    assert np.array_equal(total, expected) and (n, seen) == (40, 40)


def test_settled_users_have_no_rank_within_most(spark, folder):
    prep = D.prepare(U.universe(spark, folder, "P"))
    exact, short = ({(r.client_id, r.item_id): r["rank"] for r in ncf.fit(prep, 1, most=m).collect()} for m in (None, 5))
    assert exact.keys() == short.keys() and exact != short
    assert all(short[k] == r if r <= 5 else short[k] > 5 for k, r in exact.items())
