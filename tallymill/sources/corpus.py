"""Corpora and increments from the given tables."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable, Iterator
from hashlib import md5

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tallymill.functions.hashing import word_key
from tallymill.functions.text import page_text, spaced, words
from tallymill.sources.tables import load

HELD_OUT = ("src18", "src19")


def tokens(docs: DataFrame) -> DataFrame:
    """(doc_id, pos, w) of docs(doc_id, text); empty and null texts have none."""
    return docs.select("doc_id", F.posexplode(words(F.col("text"))).alias("pos", "w"))


def vocabulary(toks: DataFrame) -> DataFrame:
    """(w, df, tf)."""
    per_doc = toks.groupBy("w", "doc_id").agg(F.count("*").alias("n"))
    return per_doc.groupBy("w").agg(F.count("*").alias("df"), F.sum("n").alias("tf"))


def filtered(vocab: DataFrame, least_df: int = 3, stop: DataFrame | None = None) -> DataFrame:
    """Without rare words and stop words."""
    kept = vocab.where(F.col("df") >= least_df)
    return kept.join(F.broadcast(stop), "w", "left_anti") if stop is not None else kept


def stop_words(toks: DataFrame, langs: DataFrame, top: int = 10) -> DataFrame:
    """The top most frequent words of each language, ties by word; the text is invented, so no list is given."""
    return commonest(toks.join(langs, "doc_id").groupBy("lang", "w").agg(F.count("*").alias("n")), top)


def commonest(freq: DataFrame, top: int = 10) -> DataFrame:
    """The top words of each language of freq(lang, w, n), ties by word."""
    rank = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "w"))
    return freq.withColumn("r", rank).where(F.col("r") <= top).select("w").distinct()


def numbered(vocab: DataFrame) -> DataFrame:
    """vocab with v, the rank of w in string order: counts of range partitions, then ranks inside."""
    spark = vocab.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    head = F.substring(F.hex(F.encode("w", "utf-8")), 1, 8)
    keyed = vocab.withColumn("head", head)
    # words that share their first bytes are ranked together
    start = keyed.groupBy("head").agg(F.count("*").alias("m"))
    block = F.substring("head", 1, 2)
    inside = start.withColumn("skip", F.sum("m").over(Window.partitionBy(block).orderBy("head")) - F.col("m")).withColumn("b", block)
    blocks = start.groupBy(block.alias("b")).agg(F.sum("m").alias("bm"))  # at most 256
    blocks = blocks.select("b", (F.sum("bm").over(Window.orderBy("b")) - F.col("bm")).alias("bskip"))
    ranked = keyed.repartition(parts, "head").withColumn("r", F.row_number().over(Window.partitionBy("head").orderBy("w")) - 1)
    out = ranked.join(inside.join(F.broadcast(blocks), "b").select("head", (F.col("skip") + F.col("bskip")).alias("skip")), "head")
    return out.withColumn("v", (F.col("skip") + F.col("r")).cast("long")).drop("head", "r", "skip")


def documents(toks: DataFrame, vocab: DataFrame) -> DataFrame:
    """(doc_id, vs): a document row of its in-vocabulary ids, in order."""
    kept = toks.join(vocab.select("w", "v"), "w")
    return kept.groupBy("doc_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "v"))), lambda x: x["v"]).alias("vs"))


def one_row_each(docs: DataFrame) -> bool:
    """Whether no doc_id is null or has several rows."""
    return docs.groupBy("doc_id").count().where("count > 1 OR doc_id IS NULL").isEmpty()


#: Rows, and elements of their lists, that a Python worker takes at a time; a longer list is taken alone.
ROWS, ELEMENTS = 2048, 1 << 18


def parts_of(batches: Iterator[pa.RecordBatch], lists: str = "vs", rows: int = ROWS, elements: int = ELEMENTS) -> Iterator[pa.RecordBatch]:
    for b in batches:
        ends = np.cumsum(pc.fill_null(pc.list_value_length(b.column(lists)), 0).to_numpy(zero_copy_only=False))
        a = 0
        while a < b.num_rows:
            full = np.searchsorted(ends, (ends[a - 1] if a else 0) + elements, "right")
            stop = min(a + rows, max(a + 1, int(full)), b.num_rows)
            yield b.slice(a, stop - a)
            a = stop
    give_back()


def give_back() -> None:
    """Idle workers give back what they no longer use."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):
        ctypes.CDLL(None).malloc_trim(0)


#: Words of a row of coded().
CODED = 1 << 19
_CODED = "ids binary, sizes binary, codes binary, words array<string>, lang string, w string, df long, n long"


def _cut_texts(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "lang", spaced(F.col("text")).alias("text"))


def coded(docs: DataFrame) -> DataFrame:
    """docs(doc_id, lang, text), a row a document, cut into words once: rows of many documents, with their ids in 8 bytes,
    lengths in 4 and words as places, in 4, in the words of the row; and rows (lang, w, df, n) that count them."""
    return _cut_texts(docs).mapInArrow(_coding(), _CODED)


def _coding(counts: bool = True) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def split() -> Iterator[pa.RecordBatch]:
            for b in batches:
                yield pa.record_batch([b.column("doc_id"), b.column("lang"), pc.split_pattern(b.column("text"), " ")], names=["doc_id", "lang", "ws"])

        for b in parts_of(split(), "ws", elements=CODED):
            flat, lang = b.column("ws").flatten().dictionary_encode(), b.column("lang").dictionary_encode("encode")
            u, codes = max(1, len(flat.dictionary)), flat.indices.to_numpy(zero_copy_only=False)
            doc = np.repeat(np.arange(b.num_rows), pc.list_value_length(b.column("ws")).to_numpy(zero_copy_only=False))
            # before a first and after a last separator stands no word
            word = codes != pc.index(flat.dictionary, "").as_py()
            doc, codes = doc[word], codes[word]
            packed = (b.column("doc_id").fill_null(0).to_numpy(zero_copy_only=False), np.bincount(doc, minlength=b.num_rows).astype(np.int32), codes.astype(np.int32))
            own = [*(pa.array([x.tobytes()], pa.binary()) for x in packed), pa.array([flat.dictionary], pa.list_(pa.string()))]
            yield pa.record_batch([*own, *(pa.nulls(1, x) for x in kinds)], names=names)
            if counts:
                each, n = np.unique(doc * u + codes, return_counts=True)
                key = lang.indices.to_numpy(zero_copy_only=False).astype(np.int64)[each // u] * u + each % u
                df, tf = (np.bincount(key, x, u * len(lang.dictionary)).astype(np.int64) for x in (None, n))
                at = np.flatnonzero(df)
                told = [lang.dictionary.take(pa.array(at // u)), flat.dictionary.take(pa.array(at % u)), pa.array(df[at]), pa.array(tf[at])]
                yield pa.record_batch([*(pa.nulls(len(at), x.type) for x in own), *told], names=names)

    names, kinds = [x.split()[0] for x in _CODED.split(", ")], (pa.string(), pa.string(), pa.int64(), pa.int64())
    return run


def counted(rows: DataFrame) -> DataFrame:
    """(lang, w, df, n) of coded() rows: what vocabulary() and stop_words() count."""
    return rows.where("w IS NOT NULL").groupBy("lang", "w").agg(F.sum("df").alias("df"), F.sum("n").alias("n"))


def row_counts(docs: DataFrame) -> DataFrame:
    """counted() of docs(doc_id, lang, text), a row a document. Tokens are summed before the shuffle."""
    return counted(coded(docs))


#: Words of a vocabulary that each worker may hold.
HELD_WORDS = 4_000_000


def placed(rows: DataFrame, held: Broadcast) -> DataFrame:
    """(ids, sizes, vs), packed, of coded() rows, from the words of a vocabulary in order of v; documents without such words go."""
    return rows.where("w IS NULL").select(*_PLACED).mapInArrow(_placing(held), "ids binary, sizes binary, vs binary")


_PLACED = ["ids", "sizes", "codes", "words"]


def _placing(held: Broadcast) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = {w: v for v, w in enumerate(held.value)}
        for b in batches:
            for ids, sizes, codes, ws in zip(*(b.column(n) for n in _PLACED)):
                place = np.array([known.get(w, -1) for w in ws.values.to_pylist()], np.int32)
                v, doc = place[np.frombuffer(codes.as_buffer(), np.int32)], np.repeat(np.arange(len(ids.as_buffer()) // 8), np.frombuffer(sizes.as_buffer(), np.int32))
                size = np.bincount(doc[v >= 0], minlength=len(ids.as_buffer()) // 8)
                some, v = size > 0, v[v >= 0]
                ids, ends = np.frombuffer(ids.as_buffer(), np.int64)[some], np.concatenate([[0], np.cumsum(size[some])])
                lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(v))
                for part in parts_of(iter([pa.record_batch([pa.array(ids), lists], names=["doc_id", "vs"])])):
                    own = (part.column("doc_id").to_numpy(), pc.list_value_length(part.column("vs")).to_numpy(), part.column("vs").flatten().to_numpy())
                    yield pa.record_batch([pa.array([x.tobytes()], pa.binary()) for x in own], names=["ids", "sizes", "vs"])

    return run


def unpacked(rows: DataFrame) -> DataFrame:
    """(doc_id, vs), a row a document, of placed() rows."""
    return rows.mapInArrow(_unpacking, "doc_id long, vs array<long>")


def _unpacking(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for row in zip(*b.columns):
            ids, sizes, v = (np.frombuffer(x.as_buffer(), kind) for x, kind in zip(row, (np.int64, np.int32, np.int32)))
            vs = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32()), pa.array(v.astype(np.int64)))
            yield pa.record_batch([pa.array(ids), vs], names=["doc_id", "vs"])


def looked_up(docs: DataFrame, held: Broadcast) -> DataFrame:
    """documents() of docs(doc_id, text), a row a document, from the words of a vocabulary in order of v."""
    coding, placing = _coding(counts=False), _placing(held)
    # one worker a task does all three
    return _cut_texts(docs.select("doc_id", F.lit("").alias("lang"), "text")).mapInArrow(lambda batches: _unpacking(placing(coding(batches))), "doc_id long, vs array<long>")


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, vs): word_key() of the words of docs(doc_id, text), in order. A row stays a row; those without words go."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in parts_of(batches, "ws"):
            ws, size = b.column("ws").flatten().dictionary_encode(), pc.list_value_length(b.column("ws")).to_numpy(zero_copy_only=False)
            keys = np.frombuffer(b"".join(md5(w.encode()).digest()[:8] for w in ws.dictionary.to_pylist()), ">u8").astype(np.uint64) >> np.uint64(4)
            vs = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size)]), pa.int32()), pa.array(keys.astype(np.int64)[ws.indices.to_numpy(zero_copy_only=False)]))
            yield pa.record_batch([b.column("doc_id"), vs], names=["doc_id", "vs"]).filter(pa.array(size > 0))

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), words(F.col("text")).alias("ws")).mapInArrow(run, "doc_id long, vs array<long>")


def ranked(rows: DataFrame, held: Broadcast) -> DataFrame:
    """rows(doc_id, vs) with the places of the fingerprints in held, which has every one of them in order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in parts_of(batches):
            own, size = b.column("vs").flatten().dictionary_encode(), pc.list_value_length(b.column("vs")).to_numpy(zero_copy_only=False)
            at = np.searchsorted(held.value, own.dictionary.to_numpy(zero_copy_only=False))[own.indices.to_numpy(zero_copy_only=False)]
            vs = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size)]), pa.int32()), pa.array(at.astype(np.int32)))
            yield pa.record_batch([b.column("doc_id"), vs], names=["doc_id", "vs"])

    return rows.select("doc_id", "vs").mapInArrow(run, "doc_id long, vs array<int>")


def training(docs: DataFrame) -> DataFrame:
    return docs.where(~F.col("source").isin(*HELD_OUT))


def held_out(docs: DataFrame) -> DataFrame:
    """Held-out documents whose text does not occur in training."""
    seen = training(docs).select(F.md5(F.col("text").cast("binary")).alias("m")).distinct()
    return docs.where(F.col("source").isin(*HELD_OUT)).withColumn("m", F.md5(F.col("text").cast("binary"))).join(seen, "m", "left_anti").drop("m")


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, text): the turns of a conversation, joined."""
    turns = F.array_sort(F.collect_list(F.struct("turn", "role", "text")))
    return load(spark, sf_dir, "conversations").groupBy(F.col("conv_id").alias("doc_id")).agg(F.array_join(F.transform(turns, lambda t: t["text"]), " ").alias("text"))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), page_text(F.col("html")).alias("text"))


def benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("doc_id"), "text")


def order_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Increments (k, key, event): k of a line's flag and status, key its part, event its full identity."""
    flag = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2)
    lines = load(spark, sf_dir, "lineitem").select(
        (flag * 2 + F.when(F.col("l_linestatus") == "F", 0).otherwise(1)).alias("k"),
        F.col("l_partkey").alias("key"),
        F.concat_ws(",", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("event"),
        "l_suppkey",
    )
    return lines


def clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Increments (k, key, event): the type and user of an event."""
    return load(spark, sf_dir, "events").select(F.col("event_type").alias("k"), F.col("user_id").alias("key"), F.col("event_id").alias("event"))


def word_increments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Increments (k, key, event): quality label, word fingerprint, document and place."""
    toks = tokens(load(spark, sf_dir, "documents"))
    labels = load(spark, sf_dir, "labels").select("doc_id", F.col("quality").alias("k"))
    return toks.join(labels, "doc_id").select("k", word_key(F.col("w")).alias("key"), F.concat_ws(",", "doc_id", "pos").alias("event"))


def word_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Increments (key, event) of all documents, labelled or not: word fingerprint, document and place."""
    rows = fingerprints(load(spark, sf_dir, "documents")).select("doc_id", F.posexplode("vs").alias("pos", "key"))
    return rows.select("key", F.concat_ws(",", "doc_id", "pos").alias("event"))
