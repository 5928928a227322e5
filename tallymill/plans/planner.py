"""Choices made when a plan is composed: representation, lookup, blocks, which cells to read."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallymill.functions.hashing import hash_np
from tallymill.operators.matrix import CountMatrix, Dense, RowSketches
from tallymill.params import SketchParams, plan_budget

#: Bytes of a representation that each worker may hold.
BROADCAST_BYTES = 512 << 20


def choose_counts(types: int, components: int, budget: int, base: float = 1.08, rows: int = 3) -> CountMatrix:
    """Dense if it fits; else one-byte sketches of the widest power of two that fits."""
    dense = Dense(types, components)
    if dense.size_bytes() <= budget:
        return dense
    return RowSketches(SketchParams(rows, plan_budget(budget, components, rows, 8), base, 8, counter="independent"), components)


def choose_lookup(matrix: CountMatrix, budget: int = BROADCAST_BYTES) -> str:
    """'broadcast' the representation, or 'join' its word vectors when it outgrows a worker."""
    return "broadcast" if matrix.size_bytes() <= budget else "join"


def sketches_documents(components: int, p: SketchParams) -> bool:
    """Whether a sketch of topics per document would save anything."""
    return p.size_bytes(1) < 4 * components


def component_blocks(components: int, bytes_each: int, budget: int) -> list[range]:
    """Blocks of components whose partial sketches fit a worker together."""
    size = max(1, budget // max(1, bytes_each))
    return [range(a, min(components, a + size)) for a in range(0, components, size)]


def cells_for(cells: DataFrame, keys: Iterable[int], p: SketchParams) -> DataFrame:
    """Only the cells that a few keys address: a filter that reaches the scan."""
    keys = np.array(list(keys), np.int64)
    wanted = None
    for i in range(p.l):
        own = (F.col("i") == i) & F.col("col").isin([int(c) for c in sorted(set(hash_np(keys, i, p).tolist()))])
        wanted = own if wanted is None else wanted | own
    return cells.where(wanted)
