"""Approximate counters: a state k advances with chance base^-k and reads (base^k - 1)/(base - 1)."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from tallymill.functions.keyed import mixed


def thresholds(base: float, cap: int) -> list[float]:
    return [base**-j for j in range(cap + 1)]


def reads(base: float, cap: int) -> list[float]:
    return [(base**j - 1) / (base - 1) for j in range(cap + 1)]


def doubles(values: list[float]) -> Column:
    return F.array(*[F.lit(float(v)) for v in values])


def counter_step(state: Column, u: Column, base: float, cap: int = 255) -> Column:
    """Advances a state; at cap it stays."""
    accepted = u < F.get(doubles(thresholds(base, cap)), state)
    return F.when(accepted & (state < cap), state + 1).otherwise(state)


def counter_read(state: Column, base: float, cap: int = 255) -> Column:
    return F.get(doubles(reads(base, cap)), state)


def counter_decrement(*_: object) -> None:
    raise TypeError("approximate counters cannot go down; use exact counts")


def counter_pmf(n: int, base: float, states: int | None = None) -> np.ndarray:
    """Exact law of the state after n increments from 0."""
    states = n if states is None else min(n, states)
    p = np.zeros(states + 1)
    p[0] = 1.0
    up = np.array(thresholds(base, states))
    up[-1] = 0.0 if states < n else up[-1]
    for _ in range(n):
        move = p * up
        p = p - move
        p[1:] += move[:-1]
        p[-1] += move[-1]
    return p


@lru_cache(maxsize=64)
def stays(base: float, cap: int) -> np.ndarray:
    """Logarithm of the chance that a draw leaves a state as it is, by state."""
    return np.log1p(-np.minimum(base ** -np.arange(cap + 1.0), 1 - 1e-16))


def advance(states: np.ndarray, n: np.ndarray, base: float, cap: int, seed: int, ids: np.ndarray) -> np.ndarray:
    """n increments at once: geometric waits from state to state until n is spent."""
    s, left = states.astype(np.int64), n.astype(np.int64).copy()
    # state 0 always advances
    first = (left > 0) & (s == 0) & (cap > 0)
    left -= first
    s += first
    live = np.flatnonzero((left > 0) & (s < cap))
    slow = stays(base, cap) if cap <= 4095 else None
    while len(live):
        here = s[live]
        u = mixed(seed, ids[live], here)
        wait = np.ceil(np.log(u) / (slow[here] if slow is not None else np.log1p(-np.minimum(base ** -here.astype(float), 1 - 1e-16))))
        go = wait <= left[live]
        left[live] -= np.where(go, wait, left[live]).astype(np.int64)
        s[live] += go
        live = live[go & (left[live] > 0) & (s[live] < cap)]
    return s


def merge_exact(x: np.ndarray, y: np.ndarray, base: float, cap: int, seed: int, ids: np.ndarray) -> np.ndarray:
    """The law of one counter fed both streams: the successes of the smaller, level by level,
    are offered to the larger, which is always at that level or above."""
    big, small = np.maximum(x, y).astype(np.int64), np.minimum(x, y)
    chance, live = base ** -np.arange(cap + 1.0) if cap <= 4095 else None, np.arange(len(big))
    for j in range(int(small.max(initial=0))):
        live = live[small[live] > j]
        now = big[live]
        u = mixed(seed, ids[live], j)
        big[live] += (u < (chance[now - j] if chance is not None else base ** (j - now.astype(float)))) & (now < cap)
    return big


def round_up(value: np.ndarray, u: np.ndarray, base: float, cap: int) -> np.ndarray:
    """A neighbouring state of a read value, at random so that the mean is kept."""
    table = np.array(reads(base, cap))
    low = np.clip(np.searchsorted(table, value, "right") - 1, 0, cap)
    high = np.minimum(low + 1, cap)
    gap = np.where(high > low, table[high] - table[low], 1.0)
    return low + ((u * gap < value - table[low]) & (high > low))


def merge_round(x: np.ndarray, y: np.ndarray, u: np.ndarray, base: float, cap: int) -> np.ndarray:
    table = np.array(reads(base, cap))
    return np.where(np.minimum(x, y) == 0, np.maximum(x, y), round_up(table[x] + table[y], u, base, cap))


def merge_exact_col(x: Column, y: Column, u, base: float, cap: int = 255) -> Column:
    """merge_exact as an expression; u maps a level to its uniform."""
    small, big = F.least(x, y), F.greatest(x, y)
    table = doubles(thresholds(base, cap))
    levels = F.when(small > 0, F.sequence(F.lit(0), small - 1)).otherwise(F.expr("cast(array() as array<int>)"))
    return F.aggregate(levels, big, lambda s, j: F.when((u(j) < F.get(table, s - j)) & (s < cap), s + 1).otherwise(s))


def merge_round_col(x: Column, y: Column, u: Column, base: float, cap: int = 255) -> Column:
    table = doubles(reads(base, cap))
    value = F.get(table, x) + F.get(table, y)
    low = F.size(F.filter(table, lambda r: r <= value)) - 1
    part = (value - F.get(table, low)) / (F.get(table, F.least(low + 1, F.lit(cap))) - F.get(table, low))
    return F.when(F.least(x, y) == 0, F.greatest(x, y)).when(low >= cap, F.lit(cap)).otherwise(low + (u < part).cast("int"))
