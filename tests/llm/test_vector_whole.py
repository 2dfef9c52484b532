"""The vector join with repeated ids and long vectors."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from fedlake.llm import vector_join

SCHEMA = "vec_id long, embedding array<float>"


def found(spark, rows, k):
    frame = spark.createDataFrame(rows, SCHEMA).coalesce(1)
    return {(x.query_id, x["rank"]): x.vec_id for x in vector_join.nearest(frame, F.col("vec_id") % 50 == 0, k=k).collect()}


def test_repeated_ids_leave_room_for_other_ids(spark):
    rows = [(50, [1.0, 0.0]), (50, [1.0, 0.01]), (3, [0.0, 1.0])]
    assert found(spark, rows, 1) == {(50, 1): 3}
    rows = [(50, [1.0, 0.0])] + [(7, [1.0, 0.01 * j]) for j in range(6)] + [(8, [0.0, 1.0])]
    assert found(spark, rows, 2) == {(50, 1): 7, (50, 2): 8}


@pytest.mark.parametrize("size", [1536, 16384])
def test_bounds_hold_for_long_vectors(size):
    r = np.random.default_rng(size)
    a, b = vector_join.Codes(np.sign(r.standard_normal((4, size)))), vector_join.Codes(np.sign(r.standard_normal((6, size))))
    near, off = vector_join.tile_bounds(a, b)
    exact = (a.vectors / a.norms[:, None]) @ (b.vectors / b.norms[:, None]).T
    assert (np.abs(near - exact) <= off).all()
    whole = (a.codes.astype(np.int64) @ b.codes.astype(np.int64).T) * a.scale[:, None] * b.scale[None, :]
    assert np.allclose(near, whole, rtol=0, atol=1e-13)


def test_extra_columns_and_nulls(spark):
    schema = SCHEMA + ", query_id long, rank int, score double"
    rows = [(50, [1.0, 0.0], None, None, None), (None, None, 1, 1, 1.0), (3, [1.0, 1.0], 1, 1, 1.0)]
    frame = spark.createDataFrame(rows, schema)
    assert [(r.query_id, r.vec_id) for r in vector_join.nearest(frame, F.col("vec_id") % 50 == 0).collect()] == [(50, 3)]
