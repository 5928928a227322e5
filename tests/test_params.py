from __future__ import annotations

import math

import pytest

from tallymill import evaluation
from tallymill.params import SketchParams, consistent_sequence, counter_moments, counter_range, dense_bytes, expected_cell, is_consistent_prefix, plan_base, plan_bits, plan_budget, plan_delta, plan_error, smoothed

# fixed values: published sizes in 1e5 bytes for 100 components and 291,000 types
PUBLISHED = {(3, 15, 4): 393.2, (3, 16, 4): 786.43, (3, 17, 4): 1572.9, (4, 15, 4): 524.3, (4, 16, 4): 1048.6, (4, 17, 4): 2097.2, (5, 15, 4): 655.4, (5, 16, 4): 1310.7, (5, 17, 4): 2621.4, (3, 15, 1): 98.3, (3, 16, 1): 196.6, (3, 17, 1): 393.22}


def test_published_sizes():
    assert dense_bytes(100, 291_000) / 1e5 == pytest.approx(1164.0)
    for (rows, bits, width), size in PUBLISHED.items():
        base = {} if width == 4 else {"base": 1.08, "counter": "independent"}
        assert SketchParams(rows, 1 << bits, bits=8 * width, **base).size_bytes(100) / 1e5 == pytest.approx(size, abs=0.06)
        assert evaluation.size_table(100, 291_000, [(rows, bits)], width)[0][2] == pytest.approx(size, abs=0.06)


def test_sizing():
    assert plan_error(0.01, 2, 5) == (200, 1 / 32)
    rows, w = plan_delta(0.01, 0.01)
    assert w == math.ceil(math.e / 0.01) and math.e**-rows <= 0.01
    assert expected_cell(10, 110, 20) == 15
    assert plan_budget(100 * 3 * 1024, 100, 3, 8) == 1024
    assert counter_range(1.08, 8) == pytest.approx(4.168383e9, rel=1e-6)
    assert counter_range(plan_base(8, 2**32), 8) == pytest.approx(2**32, rel=1e-6)
    assert plan_bits(1.08, 2**31) == 8 and plan_bits(1.0005, 2**31) == 16
    assert counter_moments(3, 2) == (3, 3)


def test_consistent_sequences():
    seq = consistent_sequence(5)
    assert is_consistent_prefix(seq, 3) and not is_consistent_prefix(seq[::-1], 3) and not is_consistent_prefix(seq, 2)


@pytest.mark.parametrize(
    "bad",
    [
        lambda: SketchParams(0, 4),
        lambda: SketchParams(1, 0),
        lambda: SketchParams(1, 4, 1.0, counter="independent"),
        lambda: SketchParams(1, 4, 1.1, counter="independent", rule="conservative"),
        lambda: SketchParams(1, 4, query="other"),
        lambda: smoothed(0, 1),
        lambda: smoothed(1, -1),
        lambda: plan_error(0, 2, 1),
        lambda: plan_delta(0.1, 1),
        lambda: plan_budget(1, 10, 3, 8),
    ],
)
def test_rejected(bad):
    with pytest.raises(ValueError):
        bad()
    SketchParams(1, 4, 1.1, counter="independent", rule="conservative", unsafe=True)
