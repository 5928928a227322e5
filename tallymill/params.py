"""Parameters of sketches and counters: validation, sizing, sequences."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class SketchParams:
    """l hash rows of range w; counter 'exact', 'independent' or 'correlated'; rule 'plain' or
    'conservative'. hash_scope 'shared' lets all components use the same l functions."""

    l: int  # noqa: E741
    w: int
    base: float | None = None
    bits: int = 32
    rule: str = "plain"
    counter: str = "exact"
    seed: int = 42
    hash_scope: str = "shared"
    query: str = "min"
    unsafe: bool = False

    def __post_init__(self) -> None:
        if self.l < 1 or self.w < 1:
            raise ValueError("l and w must be positive")
        if self.counter not in ("exact", "independent", "correlated") or self.rule not in ("plain", "conservative"):
            raise ValueError("unknown counter or rule")
        if self.hash_scope not in ("shared", "per_component") or self.query not in ("min", "mean_min", "mean_clip"):
            raise ValueError("unknown hash scope or query rule")
        if self.counter != "exact" and (self.base is None or self.base <= 1):
            raise ValueError("approximate counters need a base above 1")
        if self.bits not in (8, 16, 32, 64):
            raise ValueError("bits must be 8, 16, 32 or 64")
        if self.counter == "independent" and self.rule == "conservative" and not self.unsafe:
            raise ValueError("independent counters may underestimate, so raising only the least is not justified")

    @property
    def cap(self) -> int:
        """Largest cell value or counter state."""
        return (1 << self.bits) - 1 if self.counter != "exact" else (1 << (self.bits - 1)) - 1

    def size_bytes(self, components: int) -> int:
        return components * self.l * self.w * self.bits // 8


def dense_bytes(components: int, types: int, width: int = 4) -> int:
    return components * types * width


def plan_error(eps: float, k: float, rows: int) -> tuple[int, float]:
    """(w, chance of an overshoot of eps N or more) for w = k / eps and so many rows."""
    if eps <= 0 or k <= 1 or rows < 1:
        raise ValueError("eps must be positive, k above 1, rows at least 1")
    return math.ceil(k / eps), k**-rows


def plan_delta(eps: float, delta: float, k: float = math.e) -> tuple[int, int]:
    """(l, w) whose overshoot of eps N has a chance of delta or less."""
    if not 0 < delta < 1:
        raise ValueError("delta must lie between 0 and 1")
    return max(1, math.ceil(math.log(1 / delta) / math.log(k))), plan_error(eps, k, 1)[0]


def plan_budget(budget: int, components: int, rows: int, bits: int) -> int:
    """Largest power of two w for which the sketches of all components fit in budget bytes."""
    w = budget * 8 // (components * rows * bits)
    if w < 1:
        raise ValueError("the budget holds no column")
    return 1 << (w.bit_length() - 1)


def expected_cell(f: float, n: float, w: int) -> float:
    return f + (n - f) / w


def counter_range(base: float, bits: int) -> float:
    """Largest count that a counter of so many bits reads."""
    if base <= 1:
        raise ValueError("base must be above 1")
    return (base ** ((1 << bits) - 1) - 1) / (base - 1)


def plan_base(bits: int, most: float) -> float:
    """Least base whose range reaches most, by bisection."""
    low, high = 1 + 1e-12, 2.0
    while counter_range(high, bits) < most:
        high *= 2
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (low, mid) if (1 << bits) * math.log(mid) > 700 or counter_range(mid, bits) >= most else (mid, high)
    return high


def plan_bits(base: float, most: float) -> int:
    """Bits of a counter of this base that reads up to most."""
    states = math.log1p(most * (base - 1)) / math.log(base)
    return next(b for b in (8, 16, 32, 64) if states <= (1 << b) - 1)


def counter_moments(n: int, base: float) -> tuple[float, float]:
    """Mean and variance of the read after n increments."""
    return float(n), (base - 1) / 2 * (n * n - n)


def consistent_sequence(steps: int, base: float = 1.5, w: int = 8, rows: int = 3, growth: int = 2, like: SketchParams | None = None) -> list[SketchParams]:
    """Bases that fall to 1 and widths that grow without bound, with a fixed number of rows."""
    like = like or SketchParams(rows, w, base, 32, counter="correlated")
    return [replace(like, l=rows, w=w * growth**n, base=1 + (base - 1) / growth**n) for n in range(steps)]


def is_consistent_prefix(seq: list[SketchParams], most_rows: int) -> bool:
    return all(p.l <= most_rows for p in seq) and all(a.base > b.base and a.w < b.w for a, b in zip(seq, seq[1:]))


def smoothed(alpha: float, beta: float) -> None:
    """Positive smoothing makes every state reachable in one step."""
    if alpha <= 0 or beta <= 0:
        raise ValueError("smoothing must be positive")
