"""Sharding by a hierarchical weighted hash tree, in DataFrame functions only.

A row descends region, rack and shard. At each level every child draws a number by hash of
the row's key and the child's name, divided by the child's weight as an exponential; the least
wins. A child whose weight grows takes rows from its siblings and gives none away, so a change
of weight moves rows only at the levels above it. A new shard comes as a region of its own:
then only itself gains.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Blocks of a shard that are numbered on their own: 2 x 10^5 rows each at 10^10 rows and 8 shards.
SLOT_BLOCKS = 8192


@dataclass(frozen=True)
class Shard:
    region: int
    rack: int
    shard: int
    weight: float = 1.0


def layout(shards: int, base: int = 8) -> list[Shard]:
    """Shards below base in racks of two and regions of two racks; any further one a region of its own."""
    inner = [Shard(s // 4, s // 2, s) for s in range(min(shards, base))]
    return inner + [Shard(base + s, base + s, s) for s in range(base, shards)]


def _uniform(key: Column, level: str, child: int) -> Column:
    """From 0, exclusive, to 1: 13 hexadecimal digits of an md5, half a step up."""
    digits = F.substring(F.md5(F.concat_ws("|", F.lit(level), F.lit(str(child)), key).cast("binary")), 1, 13)
    return (F.conv(digits, 16, 10).cast("double") + F.lit(0.5)) / F.lit(float(1 << 52))


def _draw(key: Column, level: str, children: Sequence[tuple[int, float]]) -> Column:
    if len(children) == 1:
        return F.lit(children[0][0])
    scored = [F.struct((-F.log(_uniform(key, level, c)) / F.lit(float(w))).alias("score"), F.lit(c).alias("child")) for c, w in children]
    return F.least(*scored)["child"]


def shard_of(key: Column, tree: Sequence[Shard]) -> Column:
    """The shard of key (a string), from the tree's shards of positive weight."""
    tree = [s for s in tree if s.weight > 0]
    if not tree:
        raise ValueError("no shard of positive weight")

    def sums(rows: Sequence[Shard], of: str) -> list[tuple[int, float]]:
        total: dict[int, float] = {}
        for s in rows:
            total[getattr(s, of)] = total.get(getattr(s, of), 0.0) + s.weight
        return sorted(total.items())

    region = _draw(key, "region", sums(tree, "region"))
    out = F.lit(None).cast("int")
    for r, _ in sums(tree, "region"):
        inside = [s for s in tree if s.region == r]
        racks = F.lit(None).cast("int")
        for k, _ in sums(inside, "rack"):
            racks = F.when(_draw(key, "rack", sums(inside, "rack")) == k, _draw(key, "shard", sums([s for s in inside if s.rack == k], "shard"))).otherwise(racks)
        out = F.when(region == r, racks).otherwise(out)
    return out


def sharded(docs: DataFrame, shards: int = 8, tree: Sequence[Shard] | None = None, slot_blocks: int = SLOT_BLOCKS) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) of every row of docs(doc_id, text).

    The law is `key`: doc_id and the number of shards decide. size is the text's UTF-8 bytes
    (null: none) plus one; a null doc_id is a key of its own. Slots number a shard's rows from 0
    without a gap, by block of key, then doc_id, checksum and size; equal rows take slots in any
    order. Other columns are ignored.
    """
    tree = list(tree or layout(shards))
    grown = [*tree, Shard(1 + max(s.region for s in tree), 1 + max(s.rack for s in tree), 1 + max(s.shard for s in tree))]
    key = F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))
    block = F.pmod(F.conv(F.substring(F.md5(F.concat(F.lit("slot|"), key).cast("binary")), 1, 13), 16, 10).cast("long"), F.lit(slot_blocks))
    placed = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"),
        F.crc32(F.coalesce("text", F.lit("")).cast("binary")).alias("text_crc32"),
        shard_of(key, tree).alias("shard"),
        shard_of(key, grown).alias("grown_shard"),
        block.cast("int").alias("block"),
    )
    from pyspark.sql import Window

    # a block's first slot: at most shards x slot_blocks rows, whatever the number of documents
    count = docs.select(shard_of(key, tree).alias("s"), block.cast("int").alias("b")).groupBy("s", "b").agg(F.count("*").alias("n"))
    before = F.sum("n").over(Window.partitionBy("s").orderBy("b").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("n")
    first = F.broadcast(count.select("s", "b", before.alias("first")))
    inside = F.row_number().over(Window.partitionBy("shard", "block").orderBy("doc_id", "text_crc32", "size"))
    return (
        placed.withColumn("inside", inside)
        .join(first, (F.col("shard") == F.col("s")) & (F.col("block") == F.col("b")))
        .select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", (F.col("first") + F.col("inside") - 1).cast("long").alias("slot"), "grown_shard")
    )
