"""Representations of the K x V count matrix that a sampler reads: dense, sparse, counters only,
a sketch for each row, for the whole matrix or for blocks of columns.

A representation is a flat array that partial results are merged in, by blocks, and that is
small enough to broadcast; `planner` checks that.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallymill.functions.counters import advance, merge_exact, reads
from tallymill.functions.hashing import hash_np
from tallymill.operators.combined import built, joined
from tallymill.params import SketchParams


@dataclass(frozen=True)
class Dense:
    """Exact counts [V, K] in 4-byte integers."""

    types: int
    components: int

    def size_bytes(self) -> int:
        return 4 * self.types * self.components

    def build(self, counts: np.ndarray, keys: np.ndarray, component: np.ndarray, seed: int) -> np.ndarray:
        return np.bincount(keys * self.components + component, counts, self.types * self.components).astype(np.int32)

    def join(self, a: np.ndarray, b: np.ndarray, seed: int, step: int, offset: int) -> np.ndarray:
        return a + b

    def estimates(self, flat: np.ndarray, keys: np.ndarray) -> np.ndarray:
        return flat.reshape(self.types, self.components)[keys].astype(np.float64)


@dataclass(frozen=True)
class Counters(Dense):
    """An approximate counter for each entry of the matrix, without hashing."""

    base: float = 1.08
    bits: int = 8

    def size_bytes(self) -> int:
        return self.bits * self.types * self.components // 8

    def build(self, counts: np.ndarray, keys: np.ndarray, component: np.ndarray, seed: int) -> np.ndarray:
        exact = super().build(counts, keys, component, seed)
        some = np.flatnonzero(exact)
        out = np.zeros(len(exact), np.uint8 if self.bits == 8 else np.int32)
        out[some] = advance(np.zeros(len(some), np.int64), exact[some], self.base, (1 << self.bits) - 1, seed, some)
        return out

    def join(self, a: np.ndarray, b: np.ndarray, seed: int, step: int, offset: int) -> np.ndarray:
        both, out = np.flatnonzero((a > 0) & (b > 0)), np.maximum(a, b)
        out[both] = merge_exact(a[both], b[both], self.base, (1 << self.bits) - 1, seed + step, both + offset)
        return out

    def estimates(self, flat: np.ndarray, keys: np.ndarray) -> np.ndarray:
        own = flat.reshape(self.types, self.components)[keys].astype(np.float64)
        return (self.base**own - 1) / (self.base - 1)


@dataclass(frozen=True)
class RowSketches:
    """A sketch for each component, all with the same hash functions: cells [l, w, K], so that one
    address of a word serves all components. With hash_scope per_component the functions differ."""

    params: SketchParams
    components: int

    def size_bytes(self) -> int:
        return self.params.size_bytes(self.components)

    def build(self, counts: np.ndarray, keys: np.ndarray, component: np.ndarray, seed: int) -> np.ndarray:
        return built(counts, keys, component, self.components, self.params, seed)

    def join(self, a: np.ndarray, b: np.ndarray, seed: int, step: int, offset: int) -> np.ndarray:
        return joined(a, b, self.params, seed, step + (offset if self.params.counter == "independent" else 0), self.components)

    def estimates(self, flat: np.ndarray, keys: np.ndarray) -> np.ndarray:
        p = self.params
        cells = flat.reshape(p.l, p.w, self.components)
        if p.hash_scope == "per_component":
            k = np.arange(self.components)
            least = np.min([cells[i, hash_np(keys[:, None], i, p, k[None, :]), k[None, :]] for i in range(p.l)], axis=0)
        else:
            least = cells[0, hash_np(keys, 0, p)]
            for i in range(1, p.l):
                least = np.minimum(least, cells[i, hash_np(keys, i, p)])
        if p.counter == "exact":
            return least.astype(np.float64)
        if p.cap <= 4095:
            return np.array(reads(p.base, p.cap))[least]
        return (p.base ** least.astype(np.float64) - 1) / (p.base - 1)


@dataclass(frozen=True)
class WholeMatrix:
    """One sketch for all entries: the component is a limb of the key. Cells [l, w]."""

    params: SketchParams
    components: int

    def size_bytes(self) -> int:
        return self.params.size_bytes(1)

    def build(self, counts: np.ndarray, keys: np.ndarray, component: np.ndarray, seed: int) -> np.ndarray:
        p = self.params
        if p.counter != "exact":
            raise ValueError("the whole-matrix form holds exact cells")
        out = np.zeros(p.l * p.w, np.int64)
        for i in range(p.l):
            out += np.bincount(i * p.w + hash_np(keys, i, p, component), counts, p.l * p.w).astype(np.int64)
        return out.astype(np.int32)

    def join(self, a: np.ndarray, b: np.ndarray, seed: int, step: int, offset: int) -> np.ndarray:
        return a + b

    def estimates(self, flat: np.ndarray, keys: np.ndarray) -> np.ndarray:
        p, k = self.params, np.arange(self.components)
        cells = flat.reshape(p.l, p.w)
        return np.min([cells[i, hash_np(keys[:, None], i, p, k[None, :])] for i in range(p.l)], axis=0).astype(np.float64)


@dataclass(frozen=True)
class Blocks:
    """Row sketches for each of `columns` blocks of keys (key modulo columns)."""

    params: SketchParams
    components: int
    columns: int

    def _rows(self) -> RowSketches:
        return RowSketches(self.params, self.components)

    def size_bytes(self) -> int:
        return self.columns * self._rows().size_bytes()

    def build(self, counts: np.ndarray, keys: np.ndarray, component: np.ndarray, seed: int) -> np.ndarray:
        own = keys % self.columns
        return np.concatenate([self._rows().build(counts[own == c], keys[own == c], component[own == c], seed + c) for c in range(self.columns)])

    def join(self, a: np.ndarray, b: np.ndarray, seed: int, step: int, offset: int) -> np.ndarray:
        return self._rows().join(a, b, seed, step, offset)

    def estimates(self, flat: np.ndarray, keys: np.ndarray) -> np.ndarray:
        out, own = np.empty((len(keys), self.components)), keys % self.columns
        for c, part in enumerate(flat.reshape(self.columns, -1)):
            out[own == c] = self._rows().estimates(part, keys[own == c])
        return out


CountMatrix = Dense | Counters | RowSketches | WholeMatrix | Blocks


def sparse(df: DataFrame, component: str = "k", key: str = "key") -> DataFrame:
    """Exact non-zero triples (k, v, n)."""
    return df.groupBy(F.col(component).alias("k"), F.col(key).alias("v")).agg(F.count("*").alias("n"))


def sparse_lookup(counts: DataFrame, keys: DataFrame) -> DataFrame:
    """(k, v, est) of keys(k, v): a join for every sweep, which arrays avoid."""
    return keys.join(counts, ["k", "v"], "left").select("k", "v", F.coalesce("n", F.lit(0)).alias("est"))
