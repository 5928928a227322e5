"""Reading tables, taking batches in slices, connected components."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallymill.plans.lineage import cut, drop, modest, shared_dir

__all__ = ["components", "cut", "drop", "hot_join", "modest", "shared_dir", "sliced", "table", "unused"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    modest(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Bytes of text, or four times as many list items, that a Python worker takes at a time.
SLICE = 1 << 21


def sliced(batches: Iterator[pa.RecordBatch], column: str, most: int = SLICE) -> Iterator[pa.RecordBatch]:
    """The rows of batches in parts whose values of a column add up to about most, one row at least."""
    for batch in batches:
        col = batch.column(column)
        size = pc.fill_null(pc.list_value_length(col) if pa.types.is_list(col.type) else pc.binary_length(col), 0)
        group = np.cumsum(size.to_numpy(zero_copy_only=False).astype(np.int64)) // most
        edge = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), batch.num_rows]
        for a, b in zip(edge, edge[1:]):
            if b > a:
                yield batch.slice(a, b - a)
    # idle workers give back what they no longer use
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):
        ctypes.CDLL(None).malloc_trim(0)


#: A key is hot with this share of all rows, so at most 1 / HOT keys are; each is dealt to SALTS tasks.
HOT, SALTS = 0.001, 64


def hot_join(left: DataFrame, right: DataFrame, key: str, weight: str, how: str = "inner") -> DataFrame:
    """left joined with right on key, which is unique in right and not null; weight is the number of
    rows of left that have it. Rows of a hot key are dealt to SALTS tasks, each with a copy of its one
    row of right. right is read twice, so it should be a written table."""
    total = right.agg(F.sum(weight)).first()[0] or 0
    hot = F.broadcast(right.where(F.col(weight) >= HOT * total).select(key, F.lit(True).alias("is_hot")))
    salt = F.when(F.col("is_hot"), F.pmod(F.xxhash64(*left.columns), F.lit(SALTS)).cast("int")).otherwise(0)
    dealt = left.join(hot, key, "left").withColumn("salt", salt).drop("is_hot")
    every = F.when(F.col("is_hot"), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))
    copied = right.join(hot, key, "left").withColumn("salt", F.explode(every)).drop("is_hot", weight)
    return dealt.join(copied, [key, "salt"], how).drop("salt")


def unused(df: DataFrame, name: str) -> str:
    """name, lengthened until no column of df has it."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def components(edges: DataFrame, most_rounds: int = 50) -> DataFrame:
    """Connected components of edges(a long, b long): rows (node, label), label the least
    node of the component. Nodes without an edge do not appear.

    Each round lets every node point its larger neighbours, then its smaller ones, at the
    least node it sees. The links stay in the cluster; the driver reads two numbers a round.
    """
    a, b = F.col("a"), F.col("b")
    links = cut(
        edges.where(a != b).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(),
        "links",
    )
    state = None
    for _ in range(most_rounds):
        both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(least, "u").where("v > u AND v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            large.join(low, "u")
            .where("v <> m")
            .select(F.col("v").alias("u"), F.col("m").alias("v"))
            .unionByName(low.select("u", F.col("m").alias("v")))
            .distinct()
        )
        links, former = cut(small, "links"), links
        drop(former)
        now = links.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        if now == state:
            break
        state = now
    else:
        raise RuntimeError("components did not settle")
    return links.select(F.col("u").alias("node"), F.col("v").alias("label")).unionByName(
        links.select(F.col("v").alias("node"), F.col("v").alias("label")).distinct()
    )
