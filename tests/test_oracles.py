"""Every query with an SQL twin gives the same rows in both engines; the others run."""

from __future__ import annotations

import pytest

from fedlake import catalog

SQL = catalog.oracle_sql()
LIGHT = ("approx_items", "roundtrip_parquet", "personalised_ranks", "popularity_metrics", "random_metrics")


@pytest.mark.parametrize("name", sorted(SQL))
def test_twin(name, spark, folder, duck, compare):
    compare(catalog.queries()[name](spark, folder).toPandas(), duck.execute(SQL[name]).df())


@pytest.mark.parametrize("name", LIGHT)
def test_runs(name, spark, folder):
    assert catalog.queries()[name](spark, folder).count() > 0


def test_names_and_aliases():
    assert set(SQL) <= set(catalog.queries())
    assert len(catalog.queries()) > 120


def test_pruned_scan(spark, folder):
    plan = catalog.queries()["scan_pruned"](spark, folder)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,30.0)]" in plan
    assert "ReadSchema: struct<l_partkey:bigint,l_quantity:double>" in plan


def test_entry(spark):
    import __spark_entry__

    rows = __spark_entry__.entry(spark).collect()
    assert len(rows) == 8 and {r.metric for r in rows} == {"hits", "ndcg"}
