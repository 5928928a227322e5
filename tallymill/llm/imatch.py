"""I-Match document fingerprints from several randomised lexicons.

The lexicon holds the terms whose document frequency, over all documents, lies in a band.
Every randomised lexicon keeps each of its terms with a probability of its own tier; a
document's component for it is the hash of its kept terms, distinct and sorted. Rich lexicons
tell short texts apart, poor ones leave long texts components that an edit need not touch.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterable, Iterator
from hashlib import blake2b, sha256
from operator import itemgetter

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallymill.llm.shared import cut, drop, sliced

#: Share of all documents a lexicon term stands in. There are at most (distinct terms of a
#: document, on average) / LOW such terms, however many documents there are.
LOW, HIGH = 0.0005, 0.3
#: The first component keeps the whole lexicon; then come tiers that keep 1/4, 1/8, ... of it.
TIERS, EACH = 9, 7
COMPONENTS = 1 + TIERS * EACH
RATES = [1.0] + [0.5 ** (2 + t) for t in range(TIERS) for _ in range(EACH)]
_WORD = re.compile(r"[^\W_]+")
#: Distinct terms that a worker counts before it hands them on.
HELD = 200_000


def terms(text: str) -> set[str]:
    return set(_WORD.findall(text.lower()))


def kept(term: str) -> tuple[int, ...]:
    """The components whose lexicons have term, if the whole lexicon has it."""
    raw = term.encode()
    draw = np.frombuffer(b"".join(blake2b(raw, digest_size=64, salt=bytes([k])).digest() for k in range(4)), np.uint32)
    return tuple(np.flatnonzero(draw[:COMPONENTS] < np.array(RATES) * 2**32).tolist())


def named(some: Iterable[str]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, some), np.uint64)


def masked(some: Iterable[str]) -> np.ndarray:
    """kept() of terms, as bits."""
    return np.fromiter((sum(1 << k for k in kept(t)) for t in some), np.uint64)


class Lexicon:
    """64-bit hashes of terms, sorted, and the components that keep each, as the bits of a mask."""

    def __init__(self, hashes: np.ndarray, masks: np.ndarray) -> None:
        self.hashes, at = np.unique(hashes, return_index=True)
        self.masks = masks[at]

    def masks_of(self, own: set[str]) -> dict[str, int]:
        """Those of own that are in the lexicon, with their masks."""
        if not len(self.hashes) or not own:
            return {}
        listed, names = list(own), named(own)
        at = np.minimum(self.hashes.searchsorted(names), len(self.hashes) - 1)
        hit = np.flatnonzero(self.hashes[at] == names)
        return dict(zip([listed[k] for k in hit.tolist()], self.masks[at[hit]].tolist()))


def fingerprint(inside: dict[str, int], own: Iterable[set[str]]) -> bytes:
    """COMPONENTS hashes of two bytes, zero where no term is kept, of a text with the lexicon terms
    inside, or without any, of all its terms, the union of own."""
    if inside:
        order = sorted(inside)
        masks = np.array([inside[t] for t in order], "<u8")
    else:
        order = sorted(set().union(*own))
        masks = masked(order).astype("<u8")
    out = np.zeros(COMPONENTS, "<u2")
    bits = np.unpackbits(masks.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    part, at = np.nonzero(bits.T)
    if len(at) > 1:
        taken = itemgetter(*at.tolist())(order)
    else:
        taken = tuple(order[k] for k in at)
    edge = np.searchsorted(part, np.arange(COMPONENTS + 1)).tolist()
    for k, (a, b) in enumerate(zip(edge, edge[1:])):
        if b > a:
            out[k] = 1 + xxhash.xxh32_intdigest(" ".join(taken[a:b]), k) % 65535
    return out.tobytes()


def likeness(a: list[bytes], b: list[bytes]) -> np.ndarray:
    """Pair by pair, the share of equal components among those that either text has, over the tiers that
    keep so few of its terms that a quarter of a text's components are empty: there the share nears
    that of the lexicon terms that both texts have. 1 for equal fingerprints."""
    x, y = (np.frombuffer(b"".join(m), "<u2").reshape(-1, COMPONENTS) for m in (a, b))
    some, has_x, has_y = (x != 0) | (y != 0), x != 0, y != 0
    share = np.minimum(*(h[:, 1:].reshape(-1, TIERS, EACH).mean(2) for h in (has_x, has_y)))
    empty = share <= 0.75
    some[:, 1:] &= np.repeat(empty, EACH, axis=1)
    some[:, 0] &= ~empty.any(1)
    used, same = some.sum(1), ((x == y) & some).sum(1)
    return np.where((x == y).all(1), 1.0, same / np.maximum(used, 1))


def lexicon(docs: DataFrame, low: float = LOW, high: float = HIGH) -> Lexicon:
    """The terms of docs(text) whose document frequency is a share of all rows from low to high: 16
    bytes for each of at most (distinct terms of a row, on average) / low terms, so 32 MB at 1,000 a
    row, however many rows there are. Terms are counted by their hashes."""
    def counted(seen: Counter) -> pa.RecordBatch:
        hashes = named(seen).view(np.int64)
        return pa.record_batch([pa.array(hashes), pa.array(seen.keys(), pa.string()), pa.array(seen.values(), pa.int64())], names=["h", "term", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()
        for b in sliced(batches, "text"):
            for t in b.column(0).to_pylist():
                seen.update(terms(t or ""))
            if len(seen) > HELD:
                yield counted(seen)
                seen = Counter()
        yield counted(seen)

    total = docs.count()
    found = docs.select("text").mapInArrow(run, "h long, term string, n long").groupBy("h").agg(F.sum("n").alias("n"), F.min("term").alias("term"))
    # written, so that the shuffle of all terms is gone before texts are dealt
    band = cut(found.where((F.col("n") >= low * total) & (F.col("n") <= high * total)).select("h", "term"), "lexicon")

    def draw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.record_batch([b.column(0), pa.array(masked(b.column(1).to_pylist()).view(np.int64))], names=["h", "mask"])

    rows = band.mapInArrow(draw, "h long, mask long").toArrow()
    drop(band)
    hashes, masks = (rows.column(c).to_numpy().view(np.uint64) for c in ("h", "mask"))
    return Lexicon(hashes, masks)


def _neighbours(docs: DataFrame, blocks: int) -> DataFrame:
    """(block, copy, doc_id, text), sorted by block, then copy, doc_id and text: the rows of docs
    in blocks of ascending doc_id, each followed by a copy (copy 1) of the row that comes next."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    share = [k / blocks for k in range(1, blocks)]
    bounds = rows.agg(F.percentile_approx("doc_id", share, 10 * blocks).alias("b")).first()[0] if share else []
    bounds = sorted(set(bounds or []))
    spread = [int(b) for b in bounds]

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cuts = np.array(spread, np.int64)
        for b in batches:
            ids = b.column(0)
            block = np.searchsorted(cuts, ids.fill_null(-(2**63)).to_numpy(zero_copy_only=False), "left").astype(np.int32)
            yield pa.record_batch([pa.array(block), *b.columns], names=["block", *b.schema.names])

    ids = rows.select("doc_id").mapInArrow(place, "block int, doc_id long")
    # a null id comes before all others
    least = {r[0]: (r[1], r[2]) for r in ids.groupBy("block").agg(F.min("doc_id"), F.max(F.col("doc_id").isNull())).collect()}
    order = sorted(least)
    if not order:
        return rows.sparkSession.createDataFrame([], "block int, copy int, doc_id long, text string")
    first = {b: None if null else low for b, (low, null) in least.items()}
    before = {first[b]: a for a, b in zip([order[-1], *order[:-1]], order)}
    wanted = [v for v in before if v is not None]
    heads = rows.where(F.col("doc_id").isin(wanted) | (F.col("doc_id").isNull() if None in before else F.lit(False)))
    heads = heads.groupBy("doc_id").agg(F.min("text").alias("text")).collect()
    heads = [(before[r[0]], 1, r[0], r[1]) for r in heads]
    copies = rows.sparkSession.createDataFrame(heads, "block int, copy int, doc_id long, text string")
    placed = rows.mapInArrow(place, "block int, doc_id long, text string").select("block", F.lit(0).alias("copy"), "doc_id", "text")
    return placed.unionByName(copies).repartitionById(order[-1] + 1, F.col("block")).sortWithinPartitions("block", "copy", "doc_id", "text")


def edited(text: str, following: str) -> str:
    """text with its last half, rounded down, replaced by as many first characters of following."""
    n = len(text) // 2
    return text[: len(text) - n] + following[:n]


def fingerprints(docs: DataFrame, low: float = LOW, high: float = HIGH, blocks: int | None = None) -> DataFrame:
    """For every row of docs(doc_id, text): n_chars, edited_sha256, fingerprint, edited_fingerprint,
    near_edited, near_next. The next document is that of the next row by (doc_id, text), for the
    last row the first; a null id comes first, a null text is empty, a single row follows itself.
    Other columns are ignored."""
    spark = docs.sparkSession
    band = lexicon(docs, low, high)
    held_terms = spark.sparkContext.broadcast((band.hashes, band.masks))
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of, held = Lexicon(*held_terms.value), None

        def taken(text: str) -> tuple:
            # no term spans a space: the part before the last one of the half that stays is read
            # once for the text and its edited form
            cut = text.rfind(" ", 0, len(text) - len(text) // 2) + 1
            head, tail = terms(text[:cut]), terms(text[cut:])
            first = of.masks_of(head)
            return text, cut, head, first, fingerprint(first | of.masks_of(tail), (head, tail))

        for b in sliced(batches, "text"):
            out: list[tuple] = []
            marks: list[tuple[bytes, bytes, bytes]] = []
            for block, copy, doc, text in zip(*(b.column(n).to_pylist() for n in ("block", "copy", "doc_id", "text"))):
                now = taken(text)
                if held and held[0] == block:
                    before, cut, head, first, mark = held[2]
                    change = edited(before, text)
                    tail = terms(change[cut:])
                    changed = fingerprint(first | of.masks_of(tail), (head, tail))
                    out.append((held[1], len(before), sha256(change.encode()).hexdigest(), mark.hex(), changed.hex()))
                    marks.append((mark, changed, now[-1]))
                held = None if copy else (block, doc, now)
            own, changed, following = ([m[k] for m in marks] for k in range(3))
            near = [pa.array(likeness(own, other)) for other in (changed, following)]
            yield pa.record_batch([*(pa.array(c, k) for c, k in zip(zip(*out) if out else [()] * 5, kinds)), *near], names=names)

    blocks = blocks or int(spark.conf.get("spark.sql.shuffle.partitions"))
    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    return _neighbours(docs, blocks).mapInArrow(run, schema)
