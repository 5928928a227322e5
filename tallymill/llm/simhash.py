"""SimHash near-duplicate detection through a segment-popcount embedding.

A 64-bit fingerprint is mapped to the bit counts of its sixteen 4-bit segments. Flipping a
bit moves one count by one, so the Manhattan distance of two such vectors is at most the
Hamming distance of the fingerprints. Vectors at distance 2 or less share a lattice point at
distance 1 or less from both: every fingerprint visits the grid cells of its own vector and
of the neighbours one step away, and meets there all that can link to it. Each cell then
verifies exactly. Within a cell fingerprints at 2 bits or fewer share a word at 1 bit or
less from both, so links are found by sorting such words, linear in the cell, and come out
as chains, never as all pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tallymill.llm.shared import components, cut, sliced, unused

SHINGLE = 3
SEED = 42
RADIUS = 2
BLOCK = 1 << 16
_ONE = np.uint64(1)
_NEAR = np.concatenate([[np.uint64(0)], _ONE << np.arange(64, dtype=np.uint64)])


def fingerprint(text: bytes | None) -> int:
    """Majority bits of the XXH64 of all word shingles; 0 without a word."""
    words = (text or b"").lower().split()
    if not words:
        return 0
    if len(words) <= SHINGLE:
        return xxhash.xxh64_intdigest(b" ".join(words), SEED)
    line, digest = b" ".join(words), xxhash.xxh64_intdigest
    size = np.fromiter(map(len, words), np.int64, len(words))
    end = np.cumsum(size + 1) - 1
    start, end = (end - size)[: 1 - SHINGLE].tolist(), end[SHINGLE - 1 :].tolist()
    ones = np.zeros(64, np.int64)
    for k in range(0, len(start), BLOCK):
        part = np.array([digest(line[i:j], SEED) for i, j in zip(start[k : k + BLOCK], end[k : k + BLOCK])], np.uint64)
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    return int(np.packbits(2 * ones > len(start), bitorder="little").view(np.uint64)[0])


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in sliced(batches, "text"):
        found = [fingerprint(t.as_py()) for t in b.column(1).cast(pa.binary())]
        yield pa.record_batch([b.column(0), pa.array(np.array(found, np.uint64).view(np.int64))], names=["doc_id", "fp"])


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp) of every row of docs(doc_id, text). Null and wordless texts get 0."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_fingerprints, "doc_id long, fp long")


def bit_counts(fp: Column) -> Column:
    """The bit counts of the sixteen segments, four bits of a long each."""
    ones = F.lit(0x1111111111111111)
    first, second, third, fourth = (F.shiftrightunsigned(fp, k).bitwiseAND(ones) for k in range(4))
    return first + second + third + fourth


def cells(fp: Column) -> Column:
    """The grid cells at Manhattan distance 1 or less from the vector of fp."""
    at = bit_counts(fp)
    near = [at]
    for k in range(16):
        step = F.lit(1 << (4 * k))
        count = F.shiftrightunsigned(at, 4 * k).bitwiseAND(F.lit(15))
        near += [F.when(count < 4, at + step), F.when(count > 0, at - step)]
    return F.array_compact(F.array(*near))


def _linked(cell: np.ndarray, fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Links among fingerprints of equal cells, all cells complete and sorted."""
    first = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]])
    size = np.diff(np.r_[first, len(cell)])
    two = first[size == 2]
    near = two[np.bitwise_count(fp[two] ^ fp[two + 1]) <= RADIUS]
    a, b = [fp[near]], [fp[near + 1]]
    which = np.repeat(np.arange(len(first)), size)
    more = np.flatnonzero((size > 2)[which])
    bound = np.searchsorted(which[more], np.arange(len(first) + 1))
    k = 0
    while k < len(first):  # blocks of whole cells, some 10,000 rows each
        j = max(k + 1, int(np.searchsorted(bound, bound[k] + 10_000, "right")) - 1)
        rows = more[bound[k] : bound[j]]
        k = j
        if not len(rows):
            continue
        word = (fp[rows][:, None] ^ _NEAR).ravel()
        group, member = np.repeat(which[rows], len(_NEAR)), np.repeat(fp[rows], len(_NEAR))
        order = np.lexsort((member, word, group))
        word, group, member = word[order], group[order], member[order]
        same = (word[1:] == word[:-1]) & (group[1:] == group[:-1])
        a.append(member[:-1][same])
        b.append(member[1:][same])
    link = np.unique(np.stack([np.concatenate(a), np.concatenate(b)], 1), axis=0)
    return link[:, 0], link[:, 1]


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links from rows (cell, fp) sorted by cell; the open cell is held in parts until it ends."""
    parts: list[tuple[np.ndarray, np.ndarray]] = []

    def out() -> pa.RecordBatch:
        cell, fp = (np.concatenate(c) for c in zip(*parts)) if parts else (np.empty(0, np.int64), np.empty(0, np.uint64))
        a, b = _linked(cell, fp) if len(cell) > 1 else (fp[:0], fp[:0])
        return pa.record_batch([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

    for batch in batches:
        if not batch.num_rows:
            continue
        cell, fp = batch.column(0).to_numpy(), batch.column(1).to_numpy().view(np.uint64)
        last = int(np.searchsorted(cell, cell[-1]))
        if last or (parts and parts[-1][0][-1] != cell[0]):
            parts.append((cell[:last], fp[:last]))
            yield out()
            parts = []
        parts.append((cell[last:], fp[last:]))
    yield out()


def links(prints: DataFrame) -> DataFrame:
    """Links (a, b) whose components are those of all pairs of distinct fingerprints of
    prints(fp) that differ in RADIUS bits or fewer."""
    parts = int(prints.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    # dealt anew, as a handful of partitions of bare fingerprints become 33 times as many rows
    visits = prints.select("fp").distinct().repartition(parts, F.xxhash64("fp")).select(F.explode(cells(F.col("fp"))).alias("cell"), "fp")
    met = visits.repartition(parts, "cell").sortWithinPartitions("cell", "fp")
    return met.mapInArrow(_verify, "a long, b long").distinct()


def near_duplicates(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint, component_id) of every row of docs(doc_id, text), other columns
    ignored. Texts that are null, empty or without a word share fingerprint zero. Repeated rows
    come out as often as they come in; a component's id is its least non-null doc_id."""
    prints = cut(fingerprints(docs), "simhash")
    label = components(links(prints))
    named = (
        prints.groupBy("fp")
        .agg(F.min("doc_id").alias("rep"))
        .join(label.withColumnRenamed("node", "fp"), "fp", "left")
        .withColumn("label", F.coalesce("label", "fp"))
    )
    named = cut(named, "simhash-named")
    least = named.groupBy("label").agg(F.min("rep").alias("component_id"))
    by_print = named.join(least, "label").select("fp", "component_id")
    return prints.join(by_print, "fp").select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in sliced(batches, "text"):
        found = [fingerprint(t.as_py()) for t in b.column("text").cast(pa.binary())]
        yield pa.record_batch([b.column("doc_id"), b.column("row_hash"), pa.array(np.array(found, np.uint64).view(np.int64))], names=["doc_id", "row_hash", "fp"])


def one_row(docs: DataFrame) -> DataFrame:
    """docs without all but one row of each group, a row being known by doc_id and text: the one of
    least doc_id, null last, and text hash, and one of rows equal in both. Rows of different groups
    stay, though they share a doc_id or have none."""
    doc, text_hash = unused(docs, "kept_id"), unused(docs, "row_hash")
    rows = docs.select("doc_id", F.xxhash64("text").alias("row_hash"), "text")
    prints = cut(rows.mapInArrow(_rows, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, row_hash long, fp long"), "simhash-rows")
    label = components(links(prints)).withColumnRenamed("node", "fp")
    row = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row_hash")
    kept = prints.join(label, "fp", "left").groupBy(F.coalesce("label", "fp")).agg(F.min(row).alias("row"))
    kept = kept.select(F.col("row.doc_id").alias(doc), F.col("row.row_hash").alias(text_hash + "_"))
    same = (F.col(text_hash) == F.col(text_hash + "_")) & F.col("doc_id").eqNullSafe(F.col(doc))
    out = docs.withColumn(text_hash, F.xxhash64("text")).join(kept, same, "left_semi")
    return out.dropDuplicates(["doc_id", text_hash]).drop(text_hash)
