"""Clipping, sensitivity, noise and the accountant."""

from __future__ import annotations

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from fedlake.functions import hashing, vectors
from fedlake.operators import accountant as A
from fedlake.operators import dp
from fedlake.queries.privacy import PUBLISHED_CELLS, PUBLISHED_DELTAS


def test_published_cells():
    for (n, m), values in PUBLISHED_CELLS.items():
        curve = A.rdp_fixed(m / n, 1.0, range(2, 65))
        for delta, eps in zip(PUBLISHED_DELTAS, values, strict=True):
            assert abs(A.epsilon(curve, 1000 * m, delta) - eps) < 2e-4
    assert A.epsilon(curve, 1000, 0) == math.inf


def test_golden_curves():
    fixed, poisson = A.rdp_fixed(0.01, 1.0, range(2, 6)), A.rdp_poisson(0.01, 1.0, range(2, 6))
    assert np.allclose(list(fixed.values()), [0.0005435086, 0.0008348727, 0.0011416066, 0.0014664463], atol=1e-9)
    assert np.allclose(list(poisson.values()), [0.0001718134, 0.0002646376, 0.0003631540, 0.0004686672], atol=1e-9)
    assert abs(A.epsilon(A.rdp_gaussian(1.0), 1, 1e-6) - 5.7631021) < 1e-6
    assert abs(A.epsilon(A.rdp_fixed(30 / 4800, 1.0), 80, 1e-6) - 1.7042) < 1e-4


def test_monotone():
    eps = lambda q=0.01, z=1.0, t=100, d=1e-6: A.epsilon(A.rdp_fixed(q, z), t, d)
    assert eps(q=0.02) > eps() > eps(q=0.005)
    assert eps(t=200) > eps() and eps(d=1e-8) > eps() and eps(z=2.0) < eps()
    assert all(A.rdp_poisson(0.01, 1.0)[a] <= A.rdp_fixed(0.01, 1.0)[a] for a in (2, 5, 20))
    assert A.rdp_fixed(1.0, 1.0) == A.rdp_gaussian(1.0)


def test_solve_round_trip():
    z = A.solve(3.0, 1e-6, 1000, "z", size=20, rounds=50)
    assert A.epsilon(A.rdp_fixed(0.02, z), 50, 1e-6) <= 3.0 < A.epsilon(A.rdp_fixed(0.02, z * 0.99), 50, 1e-6)
    m = A.solve(3.0, 1e-6, 1000, "M", rounds=50)
    assert A.epsilon(A.rdp_fixed(m / 1000, 1.0), 50, 1e-6) <= 3.0 < A.epsilon(A.rdp_fixed((m + 1) / 1000, 1.0), 50, 1e-6)
    r = A.solve(3.0, 1e-6, 1000, "R", size=20)
    assert A.epsilon(A.rdp_fixed(0.02, 1.0), r, 1e-6) <= 3.0 < A.epsilon(A.rdp_fixed(0.02, 1.0), r + 1, 1e-6)


@given(st.lists(st.floats(-1e6, 1e6), min_size=1, max_size=20), st.floats(1e-3, 1e3))
@settings(max_examples=100, deadline=None)
def test_clip_vector(values, bound):
    v = np.array(values)
    c = dp.clip_vector(v, bound)
    assert np.linalg.norm(c) <= bound * (1 + 1e-12)
    assert np.allclose(dp.clip_vector(c, bound), c)
    assert np.allclose(np.cross(c[:2], v[:2]) if len(v) > 1 else 0, 0, atol=1e-3 * max(1, np.abs(v).max()))


def test_clip_examples(spark):
    df = spark.createDataFrame([([3.0, 4.0],), ([0.0, 0.0],)], "v array<double>")
    for bound, want in ((2.5, [1.5, 2.0]), (5.0, [3.0, 4.0]), (10.0, [3.0, 4.0])):
        rows = [r[0] for r in df.select(vectors.clip_l2(F.col("v"), bound)).collect()]
        assert np.allclose(rows[0], want) and rows[1] == [0.0, 0.0]
    assert np.array_equal(dp.clip_vector(np.array([np.nan, 1.0]), 1.0), [0.0, 0.0])


def test_sensitivity_of_bounded_mean():
    r = np.random.default_rng(0)
    for _ in range(50):
        batch = [dp.clip_vector(r.standard_normal(5) * 3, 2.0) for _ in range(4)]
        other = [dp.clip_vector(r.standard_normal(5) * 3, 2.0), *batch[1:]]
        assert np.linalg.norm(np.mean(batch, 0) - np.mean(other, 0)) <= dp.sensitivity(2.0, 4) + 1e-12
    assert dp.sensitivity(2.0, 4) == 1.0 and dp.sigma(2.0, 4, 1.0) == 1.0


def test_noise_moments(spark):
    n = 40_000
    row = spark.range(n).select(hashing.normal("t", F.col("id")).alias("x"), hashing.laplace(0.5, "t", F.col("id")).alias("y")).agg(F.avg("x"), F.var_samp("x"), F.avg("y"), F.var_samp("y")).first()
    assert abs(row[0]) < 4 / math.sqrt(n) and abs(row[1] - 1) < 4 * math.sqrt(2 / n)
    assert abs(row[2]) < 4 * math.sqrt(0.5 / n) and abs(row[3] - 0.5) < 0.05
    shares = np.mean([dp.gaussian_distributed(2000, 0.1, 25, 1, k) for k in range(25)], axis=0)
    assert abs(shares.std() - 0.1) < 0.01
    assert np.array_equal(dp.gaussian(5, 1.0, 3, 4), dp.gaussian(5, 1.0, 3, 4))


def test_audit_stays_under_the_bound():
    seen = dp.audit(shift=1.0, scale=3.0, trials=200_000)
    assert 0 < seen["epsilon_seen"] < A.epsilon(A.rdp_gaussian(3.0), 1, 1e-4) + 0.3


def test_fixed_point_mean_ignores_partitioning(spark):
    df = spark.range(50).select(F.array(*[F.rand(k) for k in range(4)]).alias("vec")).collect()
    one = spark.createDataFrame(df, "vec array<double>")
    a = {r.pos: r.value for r in dp.bounded_mean(one.coalesce(1), 50, True).collect()}
    b = {r.pos: r.value for r in dp.bounded_mean(one.repartition(7), 50, True).collect()}
    assert a == b


def test_sql_functions(spark):
    names = vectors.register_sql_functions(spark)
    assert len(names) == 6
    row = spark.sql("SELECT dot(array(1D, 2D), array(3D, 4D)) a, clip_l2(array(3D, 4D), 2.5D) b, logsumexp(array(0D, 0D)) c, sigmoid(0D) d, hash_uniform('x') e, gaussian('x', 0D) f").first()
    assert row.a == 11.0 and np.allclose(row.b, [1.5, 2.0]) and abs(row.c - math.log(2)) < 1e-12 and row.d == 0.5 and 0 <= row.e < 1 and row.f == 0.0


def test_unknown_options():
    with pytest.raises(ValueError):
        dp.sensitivity(1.0, 2, "other")
    with pytest.raises(ValueError):
        A.solve(1.0, 1e-6, 10, "q")
