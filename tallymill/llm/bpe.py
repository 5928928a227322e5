"""Byte-level BPE encoding and decoding with overlapping chunks.

A long text is cut into chunks that overlap. Each is pre-tokenised on its own, in parallel.
Where the pre-token boundaries of two neighbours agree inside their overlap, the later stream
has fallen into step with the earlier one, and the text may be cut there: what follows a
boundary does not depend on what precedes it, and what precedes it does not depend on what
follows unless it ends in whitespace, which looks ahead; there no cut is made. The pieces between such cuts are encoded in
parallel and put together in order. If a seam never falls into step the text stays whole from
the last cut on. Decoding concatenates the bytes of the ids.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator
from functools import lru_cache
from hashlib import sha256

import numpy as np
import pyarrow as pa
import regex
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallymill.llm.shared import sliced

#: Characters of a chunk, and of its overlap with the next one.
CHUNK, OVERLAP = 1 << 15, 1 << 10
#: No alternative of the pattern looks farther than this past a match.
LOOK = 8


@lru_cache(maxsize=4)
def encoding(ranks_path: str, pattern: str) -> tiktoken.Encoding:
    with open(ranks_path, "rb") as f:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
    return tiktoken.Encoding("held", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


def listed(rows: list[list[int]]) -> pa.Array:
    ends = np.cumsum([0, *map(len, rows)]).astype(np.int32)
    flat = np.concatenate([np.empty(0, np.int32), *(np.fromiter(r, np.int32, len(r)) for r in rows)])
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))


def boundaries(text: str, pattern: str, last: bool) -> list[int]:
    """Starts of the pre-tokens of text; without the unsure ones at the end unless it is the last chunk."""
    found = [m.start() for m in regex.finditer(pattern, text)]
    return found if last else [p for p in found if p <= len(text) - LOOK]


def chunks(length: int, chunk: int, overlap: int) -> list[tuple[int, int]]:
    starts = range(0, max(1, length), chunk)
    return [(s, min(length, s + chunk + overlap)) for s in starts]


def stitch(streams: list[tuple[int, int, list[int]]]) -> list[int]:
    """Cuts of a text from the (start, end, boundaries) of its chunks, in order, all in its positions."""
    cuts = [0]
    for (_, end, before), (start, _, after) in zip(streams, streams[1:]):
        agreed = set(p for p in before if start < p < end).intersection(after)
        if not agreed:
            break
        cuts.append(min(agreed))
    return cuts


def _seams(pattern: str, overlap: int):
    """From a chunk only the boundaries in its two overlaps are passed on, and none after whitespace."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = b.to_pylist()
            for r in rows:
                text = r.pop("text")
                at = [p + r["start"] for p in boundaries(text, pattern, r["last"]) if p and not text[p - 1].isspace()]
                end = r["start"] + len(text)
                r["end"] = end
                r["at"] = [p for p in at if p < r["start"] + overlap or p >= end - overlap]
            yield pa.RecordBatch.from_pylist(rows, schema=_SEAM)

    return run


_SEAM = pa.schema([("doc_id", pa.int64()), ("text_hash", pa.int64()), ("start", pa.int64()), ("last", pa.bool_()), ("end", pa.int64()), ("at", pa.list_(pa.int64()))])


def _cuts(pattern: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            doc, text_hash = b.column("doc_id"), b.column("text_hash")
            cuts = []
            for seams in b.column("seams").to_pylist():
                once = {s["start"]: s for s in seams}
                cuts.append(stitch([(s["start"], s["end"], s["at"]) for _, s in sorted(once.items())]))
            yield pa.record_batch([doc, text_hash, pa.array(cuts, pa.list_(pa.int64()))], names=["doc_id", "text_hash", "cuts"])

    return run


def _encoder(ranks_path: str, pattern: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoding(ranks_path, pattern)
        for b in sliced(batches, "text"):
            ids = listed([coder.encode_ordinary(t or "") for t in b.column("text").to_pylist()])
            names = [n for n in b.schema.names if n != "text"]
            yield pa.record_batch([*[b.column(n) for n in names], ids], names=[*names, "ids"])

    return run


def encode(docs: DataFrame, ranks_path: str, pattern: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """(doc_id, ids) of every row of docs(doc_id, text), the ids that encoding the whole text gives.
    Null is empty; an empty text has no ids; repeated rows come out each; other columns are ignored."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    run = _encoder(ranks_path, pattern)
    size = F.length("text")
    short = docs.where(size <= chunk).mapInArrow(run, "doc_id long, ids array<int>")
    long = docs.where(size > chunk).withColumn("text_hash", F.xxhash64("text"))
    starts = F.explode(F.sequence(F.lit(0), F.length("text") - 1, F.lit(chunk))).alias("start")
    parts = long.select("doc_id", "text_hash", "text", starts)
    parts = parts.select(
        "doc_id",
        "text_hash",
        F.col("start").cast("long").alias("start"),
        (F.col("start") + chunk + overlap >= size).alias("last"),
        F.substring("text", F.col("start") + 1, F.lit(chunk + overlap)).alias("text"),
    )
    seams = parts.mapInArrow(_seams(pattern, overlap), "doc_id long, text_hash long, start long, last boolean, end long, at array<long>")
    cuts = (
        seams.groupBy("doc_id", "text_hash")
        .agg(F.collect_list(F.struct("start", "end", "at")).alias("seams"))
        .mapInArrow(_cuts(pattern), "doc_id long, text_hash long, cuts array<long>")
        .withColumnsRenamed({"doc_id": "d", "text_hash": "h"})
    )
    # repeated rows of one text are cut and encoded once, and come out as often as they came in
    same = F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("text_hash") == F.col("h"))
    whole = long.groupBy("doc_id", "text_hash").agg(F.first("text").alias("text"), F.count("*").alias("copies"))
    pieces = whole.join(cuts, same).select(
        "doc_id",
        "text_hash",
        "copies",
        F.posexplode(
            F.transform(
                "cuts",
                lambda c, k: F.substring(F.col("text"), (c + 1).cast("int"), F.coalesce(F.try_element_at("cuts", k + 2), F.length("text").cast("long")).cast("int") - c.cast("int")),
            )
        ).alias("n", "text"),
    )
    coded = pieces.mapInArrow(run, "doc_id long, text_hash long, copies long, n int, ids array<int>")
    joined = coded.groupBy("doc_id", "text_hash", "copies").agg(F.array_sort(F.collect_list(F.struct("n", "ids"))).alias("parts"))
    joined = joined.select("doc_id", F.flatten("parts.ids").alias("ids"), F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy")).drop("copy")
    return short.unionByName(joined)


def decode(ids: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """ids(doc_id, ids) with decoded, the bytes of the ids one after another; null ids are none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoding(ranks_path, pattern)
        for b in sliced(batches, "ids"):
            out = [coder.decode_bytes(x.values.to_numpy().tolist() if x.is_valid else []) for x in b.column("ids")]
            yield pa.record_batch([b.column("doc_id"), b.column("ids"), pa.array(out, pa.binary())], names=["doc_id", "ids", "decoded"])

    return ids.select("doc_id", "ids").mapInArrow(run, "doc_id long, ids array<int>, decoded binary")


class _Spelt(dict):
    """Decimal numerals, each made once."""

    def __missing__(self, number: int) -> str:
        self[number] = out = str(number)
        return out


def digests(decoded: DataFrame, keep_ids: bool = False) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of decoded(doc_id, ids, decoded), and ids if wanted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spelt = _Spelt()
        for b in sliced(batches, "ids"):
            n, left, right = [], [], []
            for ids, raw in zip(b.column("ids"), b.column("decoded")):
                ids = ids.values.to_numpy().tolist() if ids.is_valid else []
                n.append(len(ids))
                left.append(sha256(",".join(map(spelt.__getitem__, ids)).encode()).hexdigest())
                right.append(sha256(raw.as_py() or b"").hexdigest())
            columns = [b.column("doc_id"), pa.array(n, pa.int64()), pa.array(left, pa.string()), pa.array(right, pa.string())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            yield pa.record_batch(columns + [b.column("ids")] * keep_ids, names=names + ["ids"] * keep_ids)

    kept = ", ids array<int>" if keep_ids else ""
    return decoded.select("doc_id", "ids", "decoded").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + kept)
