"""Benchmark decontamination as a prefix-filtered set join of word windows.

An item's windows are its runs of `width` words. Containment is whole, so one token is the
necessary prefix of a window: the one that is rarest over all documents. A document position
that holds it fixes where the window would have to start; windows that would pass either end
of the document go by length and position, and the rest are compared word for word.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallymill.llm.shared import cut, sliced, unused

WIDTH = 13
#: Item words that are held at once; more items are taken in blocks of about this size.
BLOCK_WORDS = 4_000_000
_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def words(text: bytes | None) -> list[bytes]:
    return text.translate(_TABLE).split() if text else []


def windows(item: list[bytes], width: int = WIDTH) -> list[tuple[bytes, ...]]:
    if not item:
        return []
    return [tuple(item[k : k + width]) for k in range(max(1, len(item) - width + 1))]


def _frequency(docs: DataFrame, wanted: set[bytes]) -> Counter:
    """How often each wanted word stands in docs, over all of them."""
    spark = docs.sparkSession
    held = spark.sparkContext.broadcast(wanted)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of, seen = held.value, Counter()
        for b in sliced(batches, "text"):
            for t in b.column(0).cast(pa.binary()):
                seen.update(filter(of.__contains__, words(t.as_py())))
        yield pa.record_batch([pa.array(list(seen), pa.binary()), pa.array(list(seen.values()), pa.int64())], names=["w", "n"])

    counted = docs.select("text").mapInArrow(run, "w binary, n long").groupBy("w").agg(F.sum("n").alias("n"))
    return Counter({bytes(r[0]): r[1] for r in counted.collect()})


def _anchors(items: list[tuple[str, list[bytes]]], often: Counter, width: int) -> dict[bytes, list[tuple[int, tuple[bytes, ...], tuple[str, ...]]]]:
    """rarest word of a window -> (its place, the window, the items that have it)."""
    owners: dict[tuple[bytes, ...], set[str]] = {}
    for name, item in items:
        for w in windows(item, width):
            owners.setdefault(w, set()).add(name)
    out: dict[bytes, list] = {}
    for w, names in owners.items():
        place = min(range(len(w)), key=lambda k: (often[w[k]], w[k], k))
        out.setdefault(w[place], []).append((place, w, tuple(sorted(names))))
    return out


def _hits(text: list[bytes], anchors: dict) -> tuple[list[tuple[int, int]], list[str]]:
    spans: set[tuple[int, int]] = set()
    found: set[str] = set()
    for at in [k for k, w in enumerate(text) if w in anchors]:
        for place, window, names in anchors[text[at]]:
            start = at - place
            if start >= 0 and start + len(window) <= len(text) and tuple(text[start : start + len(window)]) == window:
                spans.add((start, start + len(window)))
                found.update(names)
    return merged(spans), sorted(found)


def merged(spans: Any) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


_SCHEMA = "doc_id long, text_hash long, n_words long, hit_spans array<struct<start:long,stop:long>>, item_ids array<string>"


def _screen(docs: DataFrame, anchors: dict) -> DataFrame:
    held = docs.sparkSession.sparkContext.broadcast(anchors)
    span = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of = held.value
        for b in sliced(batches, "text"):
            size, spans, names = [], [], []
            for t in b.column(2).cast(pa.binary()):
                text = words(t.as_py())
                found = _hits(text, of)
                size.append(len(text))
                spans.append([{"start": x, "stop": y} for x, y in found[0]])
                names.append(found[1])
            yield pa.record_batch(
                [b.column(0), b.column(1), pa.array(size, pa.int64()), pa.array(spans, span), pa.array(names, pa.list_(pa.string()))],
                names=["doc_id", "text_hash", "n_words", "hit_spans", "item_ids"],
            )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_hash"), "text").mapInArrow(run, _SCHEMA)


def overlaps(docs: DataFrame, items: DataFrame, width: int = WIDTH, block_words: int = BLOCK_WORDS, hashed: bool = False) -> DataFrame:
    """For every row of docs(doc_id, text): n_words, hit_spans (disjoint runs of word positions
    inside a window of an item of items(item_id, text)) and item_ids, sorted as strings. Null and
    empty texts have no words; a null item_id stands as an empty string; other columns are ignored.

    One block of items, up to about block_words words, is broadcast at a time. Several blocks
    each scan the documents, and what they find is merged by document. With hashed, text_hash
    comes too.
    """
    items = items.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item_id"), "text")
    # 2 bytes a word at least, so this is no less than the number of words
    room = (items.agg(F.sum(F.octet_length("text") / 2 + 1)).first()[0] or 0) + 1
    blocks = max(1, -(-int(room) // block_words))
    found = []
    for k in range(blocks):
        own = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k) if blocks > 1 else items
        held = [(r[0], words((r[1] or "").encode())) for r in own.collect()]
        often = _frequency(docs, {w for _, item in held for w in item})
        found.append(_screen(docs, _anchors(held, often, width)))
    if blocks == 1:
        return found[0] if hashed else found[0].drop("text_hash")
    base = found[0].select("doc_id", "text_hash", "n_words")
    parts = [cut(f.where(F.size("item_ids") > 0).distinct(), "hits") for f in found]
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    joined = F.aggregate(
        F.array_sort(F.flatten(F.collect_list("hit_spans"))),
        F.expr("cast(array() as array<struct<start:bigint,stop:bigint>>)"),
        lambda acc, s: F.when((F.size(acc) == 0) | (s["start"] > F.try_element_at(acc, F.lit(-1))["stop"]), F.concat(acc, F.array(s))).otherwise(
            F.concat(
                F.slice(acc, F.lit(1), F.greatest(F.size(acc) - 1, F.lit(0))),
                F.array(F.struct(F.try_element_at(acc, F.lit(-1))["start"].alias("start"), F.greatest(F.try_element_at(acc, F.lit(-1))["stop"], s["stop"]).alias("stop"))),
            )
        ),
    )
    some = every.groupBy("doc_id", "text_hash").agg(joined.alias("hit_spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("item_ids")))).alias("item_ids"))
    some = some.withColumnsRenamed({"doc_id": "d", "text_hash": "t"})
    return base.join(some, F.col("doc_id").eqNullSafe(F.col("d")) & F.col("text_hash").eqNullSafe(F.col("t")), "left").select(
        "doc_id",
        *["text_hash"] * hashed,
        "n_words",
        F.coalesce("hit_spans", F.expr("cast(array() as array<struct<start:bigint,stop:bigint>>)")).alias("hit_spans"),
        F.coalesce("item_ids", F.expr("cast(array() as array<string>)")).alias("item_ids"),
    )


def judged(found: DataFrame) -> DataFrame:
    """found with n_hit and contaminated: a hit, and a twentieth of the words at least."""
    n_hit = F.aggregate("hit_spans", F.lit(0).cast("long"), lambda n, s: n + s["stop"] - s["start"])
    return found.withColumn("n_hit", n_hit).withColumn("contaminated", F.expr("n_hit > 0 AND 20 * n_hit >= n_words"))


def clean(docs: DataFrame, items: DataFrame) -> DataFrame:
    """docs without the contaminated ones, known by doc_id and text."""
    own, text_hash = unused(docs, "bad_id"), unused(docs, "bad_text")
    found = judged(overlaps(docs, items, hashed=True)).where("contaminated")
    held = cut(found.select(F.col("doc_id").alias(own), F.col("text_hash").alias(text_hash)).distinct(), "contaminated")
    return docs.join(held, (F.xxhash64("text") == F.col(text_hash)) & F.col("doc_id").eqNullSafe(F.col(own)), "left_anti")


_WORDS_SQL = r"""list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '')"""
OVERLAPS_SQL = f"""
WITH d AS (SELECT doc_id, row_number() OVER () AS r, {_WORDS_SQL} AS ws FROM documents),
b AS (SELECT coalesce(item_id::VARCHAR, '') AS item, {_WORDS_SQL} AS ws FROM benchmark),
bw AS (SELECT DISTINCT item, size, array_to_string(ws[s + 1:s + size], ' ') AS gram FROM (
  SELECT item, ws, least(len(ws), {WIDTH}) AS size, unnest(range(greatest(len(ws) - {WIDTH - 1}, 1))) AS s FROM b WHERE len(ws) > 0)),
dw AS (SELECT r, p, size, array_to_string(ws[p + 1:p + size], ' ') AS gram FROM (
  SELECT r, ws, size, unnest(range(greatest(len(ws) - size + 1, 0))) AS p FROM d CROSS JOIN (SELECT DISTINCT size FROM bw))),
h AS (SELECT r, p, size, item FROM dw JOIN bw USING (size, gram)),
n AS (SELECT r, count(DISTINCT w) AS n_hit FROM (SELECT r, unnest(range(p, p + size)) AS w FROM h) GROUP BY r),
i AS (SELECT r, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT r, item FROM h) GROUP BY r)
SELECT doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated
FROM d LEFT JOIN n USING (r) LEFT JOIN i USING (r)
"""
