from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from tallymill.functions import counters as c
from tallymill.functions.keyed import draw, mixed, uniform, uniform_py


def test_law_by_hand():
    assert c.counter_pmf(0, 2).tolist() == [1]
    assert c.counter_pmf(2, 2).tolist() == [0, 0.5, 0.5]
    assert c.counter_pmf(3, 2).tolist() == [0, 0.25, 0.625, 0.125]
    assert c.reads(1.08, 3) == pytest.approx([0, 1, 2.08, 3.2464])


@pytest.mark.parametrize("base", [1.08, 1.5, 2.0])
def test_moments(base):
    for n in (0, 1, 7, 40):
        p, r = c.counter_pmf(n, base), np.array(c.reads(base, n))
        assert p @ r == pytest.approx(n) and p @ r**2 - (p @ r) ** 2 == pytest.approx((base - 1) / 2 * (n * n - n), abs=1e-6)


def histogram(states, size):
    return np.bincount(states, minlength=size)[:size] / len(states)


def test_bulk_advance_keeps_the_law():
    n, ids = 30, np.arange(60_000)
    got = c.advance(np.zeros(len(ids), int), np.full(len(ids), n), 1.4, 255, 1, ids)
    law = c.counter_pmf(n, 1.4)
    assert np.abs(histogram(got, n + 1) - law).max() < 0.01
    assert c.advance(np.zeros(3, int), np.array([0, 1, 10**6]), 1.0001, 5, 1, np.arange(3)).tolist() == [0, 1, 5]


def test_exact_merge_keeps_the_law():
    ids = np.arange(60_000)
    x = c.advance(np.zeros(len(ids), int), np.full(len(ids), 30), 1.3, 255, 1, ids)
    y = c.advance(np.zeros(len(ids), int), np.full(len(ids), 12), 1.3, 255, 2, ids)
    got = c.merge_exact(x, y, 1.3, 255, 3, ids)
    assert np.abs(histogram(got, 43) - c.counter_pmf(42, 1.3)).max() < 0.01


def test_rounded_merge_keeps_the_mean():
    ids = np.arange(60_000)
    got = c.merge_round(np.full(len(ids), 7), np.full(len(ids), 5), mixed(4, ids), 1.3, 255)
    r = np.array(c.reads(1.3, 255))
    assert r[got].mean() == pytest.approx(r[7] + r[5], rel=0.01)
    assert c.merge_round(np.array([0, 9]), np.array([4, 0]), np.array([0.5, 0.5]), 1.3, 255).tolist() == [4, 9]


def test_columns_agree_with_numpy(spark):
    df = spark.range(300).select((F.col("id") % 20).cast("int").alias("x"), (F.col("id") % 7).cast("int").alias("y"), uniform("t", 1, F.col("id")).alias("u"), "id")
    rows = df.select("*", c.counter_step(F.col("x"), F.col("u"), 1.3, 18).alias("step"), c.counter_read(F.col("x"), 1.3).alias("read"), c.merge_round_col(F.col("x"), F.col("y"), F.col("u"), 1.3).alias("merged"), c.merge_exact_col(F.col("x"), F.col("y"), lambda j: uniform("m", F.col("id"), j), 1.3).alias("exact")).collect()
    for r in rows:
        assert r.u == uniform_py("t", 1, r.id)
        assert r.step == r.x + (r.u < 1.3**-r.x and r.x < 18)
        assert r.read == pytest.approx((1.3**r.x - 1) / 0.3)
        assert r.merged == c.merge_round(np.array([r.x]), np.array([r.y]), np.array([r.u]), 1.3, 255)[0]
        big = max(r.x, r.y)
        for j in range(min(r.x, r.y)):
            big += uniform_py("m", r.id, j) < 1.3 ** (j - big)
        assert r.exact == big


def test_no_decrement():
    with pytest.raises(TypeError):
        c.counter_decrement(1)


def test_draw(spark):
    w = F.array(F.lit(1.0), F.lit(0.0), F.lit(3.0))
    got = spark.createDataFrame([(0.0,), (0.2,), (0.25,), (0.9,)], "u double").select(draw(w, F.col("u")).alias("k")).collect()
    assert [r.k for r in got] == [0, 0, 2, 2]
