"""Queries whose numbers come from a given table read it in Spark's tasks."""

from __future__ import annotations

import pytest

from fedlake import catalog

NAMES = ("budget_fit", "epsilon_grid_published", "epsilon_grid_rounds", "gaussian_noise_draws", "laplace_noise_draws", "privacy_ledger", "rdp_curve_fixed", "rdp_curve_plain", "rdp_curve_poisson", "recursive_steps")


@pytest.mark.parametrize("name", NAMES)
def test_a_scan_with_columns(name, spark, folder):
    plan = catalog.queries()[name](spark, folder)._jdf.queryExecution().optimizedPlan().toString()
    assert "parquet" in plan


def test_the_schedule_counts_keys(spark, folder, monkeypatch):
    from fedlake.queries import data

    kept = []
    real = data.customers
    monkeypatch.setattr(data, "customers", lambda s, d: kept.append(real(s, d)) or Keys(kept[-1]))
    assert catalog.queries()["schedule_rounds"](spark, folder).count() > 0


class Keys:
    """A table that refuses to be counted by its files' row counts."""

    def __init__(self, df):
        self.agg = df.agg

    def count(self):
        raise AssertionError("no column is read")
