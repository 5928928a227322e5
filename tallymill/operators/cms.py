"""Count-min sketches as relations of cells (group..., i, col, cell); absent cells are zero."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tallymill.functions.hashing import hash_col, hash_np
from tallymill.params import SketchParams


def addresses(key: str, p: SketchParams, component: str | None = None) -> Column:
    """The l cells (i, col) of a key."""
    return F.array(*[F.struct(F.lit(i).alias("i"), hash_col(key, i, p, component).alias("col")) for i in range(p.l)])


def _scoped(p: SketchParams, group: Sequence[str]) -> str | None:
    return group[0] if p.hash_scope == "per_component" and group else None


def cm_build(df: DataFrame, key: str, p: SketchParams, group: Sequence[str] = (), weight: str | None = None, component: str | None = None) -> DataFrame:
    """Exact plain cells of the increments of df. Partial sums come before the one shuffle, which
    moves at most l * w cells for each group and task. component adds a limb to the key."""
    n = F.col(weight) if weight else F.lit(1)
    cell = F.explode(addresses(key, p, component or _scoped(p, group))).alias("at")
    spread = df.select(*group, n.cast("long").alias("n"), cell)
    return spread.groupBy(*group, F.col("at.i").alias("i"), F.col("at.col").alias("col")).agg(F.sum("n").alias("cell"))


def cm_update(cells: DataFrame, increments: DataFrame, key: str, p: SketchParams, group: Sequence[str] = (), weight: str | None = None) -> DataFrame:
    return cm_merge(cells, cm_build(increments, key, p, group, weight), group=group)


def cm_merge(*cells: DataFrame, group: Sequence[str] = ()) -> DataFrame:
    """Componentwise sum."""
    every = cells[0]
    for c in cells[1:]:
        every = every.unionByName(c)
    return every.groupBy(*group, "i", "col").agg(F.sum("cell").alias("cell"))


def looked_up(cells: DataFrame, keys: DataFrame, key: str, p: SketchParams, group: Sequence[str] = (), value: str = "cell", component: str | None = None) -> DataFrame:
    """keys(group..., key) with a row for each hash row and its cell, zero where absent."""
    at = keys.select(*group, key, F.explode(addresses(key, p, component or _scoped(p, group))).alias("at")).select(*group, key, "at.i", "at.col")
    return at.join(cells.select(*group, "i", "col", value), [*group, "i", "col"], "left").withColumn(value, F.coalesce(value, F.lit(0)))


def cm_query(cells: DataFrame, keys: DataFrame, key: str, p: SketchParams, group: Sequence[str] = (), rule: str | None = None, component: str | None = None) -> DataFrame:
    """(group..., key, est). Rules: the least cell; the median of the cells less their expected
    collisions, no more than the least; or the mean of such cells, no less than zero."""
    rule = rule or p.query
    at = looked_up(cells, keys, key, p, group, component=component)
    if rule == "min":
        return at.groupBy(*group, key).agg(F.min("cell").alias("est"))
    total = cells.where("i = 0").groupBy(*group).agg(F.sum("cell").alias("total"))
    at = at.join(total, list(group)) if group else at.crossJoin(F.broadcast(total))
    free = F.col("cell") - (F.col("total") - F.col("cell")) / F.lit(float(max(1, p.w - 1)))
    if rule == "mean_clip":
        return at.groupBy(*group, key).agg(F.greatest(F.avg(free), F.lit(0.0)).alias("est"))
    sorted_free = F.array_sort(F.collect_list(free))  # l values
    middle = (F.get(sorted_free, F.lit((p.l - 1) // 2)) + F.get(sorted_free, F.lit(p.l // 2))) / 2
    return at.groupBy(*group, key).agg(F.greatest(F.least(middle, F.min("cell").cast("double")), F.lit(0.0)).alias("est"))


def row_totals(cells: DataFrame, group: Sequence[str] = ()) -> DataFrame:
    """Every hash row of exact plain cells adds up to the number of increments."""
    return cells.groupBy(*group, "i").agg(F.sum("cell").alias("total"))


def whole_matrix(df: DataFrame, component: str, key: str, p: SketchParams) -> DataFrame:
    """One sketch for the whole matrix: the component is part of the key."""
    return cm_build(df, key, p, component=component)


def block_sketches(df: DataFrame, component: str, key: str, p: SketchParams, row_block: int, col_block: int) -> DataFrame:
    """One sketch for each block of row_block components and of keys modulo col_block."""
    blocks = df.withColumn("rb", F.floor(F.col(component) / row_block).cast("int")).withColumn("cb", F.pmod(F.col(key), F.lit(col_block)).cast("int"))
    return cm_build(blocks, key, p, ["rb", "cb"], component=component)


def builtin(df: DataFrame, key: str, eps: float, confidence: float, seed: int) -> DataFrame:
    """Spark's own count-min aggregate, as a peer of equal bounds."""
    return df.agg(F.count_min_sketch(F.col(key), F.lit(eps), F.lit(confidence), F.lit(seed)).alias("payload"))


def ordered(df: DataFrame, by: Sequence[str], order: Sequence[str]) -> DataFrame:
    """Rows of a group together and in order, streamed: no group is held in memory."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = df.repartition(parts, *by) if by else df.coalesce(1)
    return dealt.sortWithinPartitions(*by, *order)


def folded(df: DataFrame, group: Sequence[str], order: Sequence[str], columns: Sequence[str], shape: tuple[int, int], step, value: str = "cell") -> DataFrame:
    """Cells of an ordered fold in each group: step(matrix, batch of columns) changes one
    l x w matrix, the only state that is held."""
    fields = [f for f in df.schema.fields if f.name in group]
    schema = T.StructType([df.schema[g] for g in group] + [T.StructField("i", T.IntegerType()), T.StructField("col", T.IntegerType()), T.StructField(value, T.LongType())])
    assert len(fields) == len(group)
    types = [pa.int32(), pa.int32(), pa.int64()]

    def out(key: tuple, m: np.ndarray, kinds: list[pa.DataType]) -> pa.RecordBatch:
        i, col = np.nonzero(m)
        same = [pa.array([k] * len(i), t) for k, t in zip(key, kinds)]
        return pa.record_batch([*same, pa.array(i, types[0]), pa.array(col, types[1]), pa.array(m[i, col].astype(np.int64))], names=schema.names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, m, kinds = None, None, []
        for b in batches:
            kinds = [b.column(g).type for g in group]
            keys = list(zip(*[b.column(g).to_pylist() for g in group])) if group else [()] * b.num_rows
            cols = [b.column(c).to_numpy(zero_copy_only=False) for c in columns]
            cut = [0, *[k for k in range(1, len(keys)) if keys[k] != keys[k - 1]], len(keys)]
            for x, y in zip(cut, cut[1:]):
                if x == y:
                    continue
                if m is None or keys[x] != now:
                    if m is not None:
                        yield out(now, m, kinds)
                    now, m = keys[x], np.zeros(shape, np.int64)
                step(m, *[c[x:y] for c in cols])
        if m is not None:
            yield out(now, m, kinds)

    return ordered(df.select(*group, *order, *[c for c in columns if c not in order]), group, order).mapInArrow(run, schema)


def cm_build_conservative(df: DataFrame, key: str, p: SketchParams, order: Sequence[str], group: Sequence[str] = ()) -> DataFrame:
    """Exact cells under the conservative rule, a fold in the given order: only cells at the
    key's minimum rise."""

    def step(m: np.ndarray, keys: np.ndarray) -> None:
        rows, cols = np.arange(p.l), np.stack([hash_np(keys, i, p) for i in range(p.l)], 1)
        for at in cols:
            own = m[rows, at]
            least = own.min()
            m[rows[own == least], at[own == least]] = least + 1

    return folded(df, group, order, [key], (p.l, p.w), step)


def to_packed(cells: DataFrame, p: SketchParams, component: str = "k", value: str = "cell") -> DataFrame:
    """(component, payload): l * w values row by row, of p.bits each, little-endian."""
    kind = {8: "<u1", 16: "<u2", 32: "<u4", 64: "<u8"}[p.bits]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, m = None, None
        for b in batches:
            k, at, v = b.column(0).to_numpy(), b.column(1).to_numpy().astype(np.int64) * p.w + b.column(2).to_numpy(), b.column(3).to_numpy()
            for x in np.unique(k):
                if x != now:
                    if m is not None:
                        yield pa.record_batch([pa.array([now], pa.int64()), pa.array([m.tobytes()], pa.binary())], names=["component", "payload"])
                    now, m = x, np.zeros(p.l * p.w, kind)
                m[at[k == x]] = v[k == x]
        if m is not None:
            yield pa.record_batch([pa.array([now], pa.int64()), pa.array([m.tobytes()], pa.binary())], names=["component", "payload"])

    rows = cells.select(F.col(component).cast("long").alias("component"), "i", "col", F.col(value).cast("long").alias("v"))
    return ordered(rows, ["component"], ["i", "col"]).mapInArrow(run, "component long, payload binary").withColumnRenamed("component", component)


def from_packed(packed: DataFrame, p: SketchParams, component: str = "k", value: str = "cell") -> DataFrame:
    kind = {8: "<u1", 16: "<u2", 32: "<u4", 64: "<u8"}[p.bits]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k, raw in zip(b.column(0).to_pylist(), b.column(1)):
                m = np.frombuffer(raw.as_py(), kind)
                at = np.flatnonzero(m)
                yield pa.record_batch([pa.array(np.full(len(at), k)), pa.array((at // p.w).astype(np.int32)), pa.array((at % p.w).astype(np.int32)), pa.array(m[at].astype(np.int64))], names=["component", "i", "col", "v"])

    out = packed.select(F.col(component).cast("long").alias("component"), "payload").mapInArrow(run, "component long, i int, col int, v long")
    return out.withColumnsRenamed({"component": component, "v": value})


def topic_vectors(cells: DataFrame, components: int, component: str = "k", value: str = "cell") -> DataFrame:
    """(i, col, states): the cells of all components at one address side by side."""
    pairs = F.map_from_entries(F.collect_list(F.struct(F.col(component).cast("int").alias("key"), F.col(value).alias("value"))))
    grouped = cells.groupBy("i", "col").agg(pairs.alias("m"))
    zero = F.lit(0).cast(cells.schema[value].dataType)
    return grouped.select("i", "col", F.transform(F.sequence(F.lit(0), F.lit(components - 1)), lambda k: F.coalesce(F.col("m")[k], zero)).alias("states"))
