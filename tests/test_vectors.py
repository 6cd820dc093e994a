"""Vectors against numpy."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from gridmin.vectors import concat, from_long, layout, ops, stack, zeros


def vec(spark, a, block=4):
    return from_long(spark.createDataFrame([(i, float(x)) for i, x in enumerate(a)], "idx long, value double"), len(a), block)


def back(v):
    return [r["value"] for r in v.to_long().orderBy("idx").collect()]


A, C = np.array([1.0, -2, 3, 0, 5, 6, -7, 8, 9, 10]), np.arange(1.0, 11.0)


def test_short_last_block(spark):
    v = vec(spark, A)
    assert [r[0] for r in v.df.select(F.size("values")).orderBy("block_id").collect()] == [4, 4, 2]
    assert back(v) == A.tolist()


def test_empty_and_tiny(spark):
    assert ops.norm(zeros(spark, 0, 4)) == 0.0
    assert back(zeros(spark, 2, 4)) == [0.0, 0.0]


def test_arithmetic(spark):
    a, b = vec(spark, A), vec(spark, C)
    assert np.allclose(back(ops.add(a, b)), A + C)
    assert np.allclose(back(ops.div(a, b)), A / C)
    assert np.allclose(back(ops.lincomb([2, -1], [a, b])), 2 * A - C)
    assert np.isclose(ops.dot(a, b), A @ C)
    assert np.allclose(ops.gram([a, b]), [[A @ A, A @ C], [A @ C, C @ C]])
    assert ops.nnz(a) == 9
    for p in (1, 2, 3, float("inf")):
        assert np.isclose(ops.norm(a, p), np.linalg.norm(A, p))
    with pytest.raises(ValueError):
        ops.norm(a, 0.5)
    with pytest.raises(ValueError):
        ops.add(a, vec(spark, A, 8))


def test_division_by_zero(spark):
    a, b = vec(spark, C), vec(spark, A)
    assert np.isnan(back(ops.div(a, b, "nan"))[3])
    with pytest.raises(Exception, match="DIVIDE_BY_ZERO"):
        back(ops.div(a, b))


def test_keyed_zip_and_views(spark):
    a, b = vec(spark, A), vec(spark, C)
    assert back(ops.keyed_zip(a, b, lambda i, x, y: x + y * i)) == (A + C * np.arange(10)).tolist()
    assert back(stack([a, b]).row(1)) == C.tolist()
    assert back(a.as_stacked(2).as_dense()) == A.tolist()
    both = concat([("u", a), ("v", b)])
    assert back(both.segment("v")) == C.tolist()
    assert np.isclose(ops.dot(both, both), A @ A + C @ C)


def test_norm_does_not_overflow(spark):
    assert np.isclose(ops.norm(vec(spark, [3e200, 4e200])), 5e200)


@settings(max_examples=30, deadline=None)
@given(st.integers(0, 10**6), st.integers(1, 5000))
def test_layout_round_trip(i, size):
    assert (i // size) * size + i % size == i
    assert layout.n_blocks(i, size) == (i + size - 1) // size
