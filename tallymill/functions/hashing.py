"""A 2-universal family: affine maps of a key's two 31-bit limbs modulo a prime, then modulo w."""

from __future__ import annotations

from functools import lru_cache
from hashlib import md5

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from tallymill.params import SketchParams

PRIME = (1 << 31) - 1


@lru_cache(maxsize=4096)
def coefficients(seed: int, row: int) -> tuple[int, int, int, int]:
    """(high limb, low limb, component, shift) of one hash row."""
    out = [int(md5(f"h|{seed}|{row}|{part}".encode()).hexdigest()[:8], 16) % PRIME for part in ("a1", "a2", "a0", "b")]
    return out[0] or 1, out[1] or 1, out[2] or 1, out[3]


def hash_sql(key: str, row: int, p: SketchParams, component: str | None = None) -> str:
    """The column of key in a hash row, as SQL that Spark and DuckDB both read."""
    a1, a2, a0, b = coefficients(p.seed, row)
    limbs = f"{a1} * ((({key}) >> 31) % {PRIME}) + {a2} * ((({key}) & {PRIME}) % {PRIME})"
    if component is None:
        return f"((({limbs} + {b}) % {PRIME}) % {p.w})"
    return f"(((({limbs}) % {PRIME} + {a0} * CAST({component} AS BIGINT) + {b}) % {PRIME}) % {p.w})"


def hash_col(key: str, row: int, p: SketchParams, component: str | None = None) -> Column:
    return F.expr(hash_sql(f"CAST({key} AS BIGINT)", row, p, component)).cast("int")


def hash_np(key: np.ndarray, row: int, p: SketchParams, component: np.ndarray | int | None = None) -> np.ndarray:
    a1, a2, a0, b = coefficients(p.seed, row)
    x = np.asarray(key, np.int64)
    limbs = a1 * ((x >> 31) % PRIME) + a2 * ((x & PRIME) % PRIME)
    if component is None:
        return (limbs + b) % PRIME % p.w
    return (limbs % PRIME + a0 * np.asarray(component, np.int64) + b) % PRIME % p.w


def word_key(word: Column) -> Column:
    """60-bit id of a word without a dictionary: 15 hexadecimal digits of its md5."""
    return F.conv(F.substring(F.md5(word.cast("binary")), 1, 15), 16, 10).cast("long")


WORD_KEY_SQL = "('0x' || substr(md5({0}), 1, 15))::BIGINT"
