"""Substring deduplication by a depth-limited radix sort of all suffixes.

Only the first DEPTH bytes of a suffix count, its window. Suffixes are grouped digit by digit,
the most significant first; a suffix alone in its group leaves, and groups that are equal to
full depth are the repeated windows. The digits are chosen so that neighbouring suffixes move
as one row:

1. the least gram of the window (by hash, of GRAM bytes) and its place in it. Every window decides
   this by its own bytes, and runs of some 150 neighbouring suffixes share one such gram;
2. all bytes that the run's windows cover. Equal runs are repeated throughout;
3. for runs with company after digit 1 and none after digit 2, those at the ends of a repeat:
   the bytes that STEP neighbouring windows have in common;
4. all bytes that these neighbours cover. Equal ones are repeated throughout;
5. for neighbours with company after digit 3 and none after digit 4: the window itself.

Of equal runs (digit 2) or neighbours (digit 4) in mixed company one stands for all at later digits.
Hashes have 128 bits over digits 1 and 2, 1 and 4, or 1 and 5.

This departs from a radix sort of every suffix in one point: digit 1 is not the first tokens of a
suffix but a gram inside its window, so that a row stands for a run of suffixes. With the leading
bytes as digit 1 every byte of the corpus would be a shuffled row of 16 bytes or more.

Tokens are bytes, or words for passages that count by words.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallymill.llm.shared import cut, drop, sliced, unused

DEPTH = 400
GRAM = 100
STEP = 16
_U = np.uint64
_BASE = _U(0x9E3779B97F4A7C15)
_INVERSE = _U(pow(int(_BASE), -1, 1 << 64))
_BYTE = np.random.default_rng(7).integers(1, 1 << 63, 256, dtype=np.uint64)
_ids = ("doc_id long", "text_hash long")
#: Told apart by what is mixed into digits 1 and 2.
_KIND = [np.int64(0), np.int64(0x5851F42D4C957F2D)]


class _Powers:
    up, down = np.ones(1, np.uint64), np.ones(1, np.uint64)

    @classmethod
    def to(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(cls.up) < n:
            size = max(n, 2 * len(cls.up), 1 << 16)
            cls.up, cls.down = (np.cumprod(np.r_[_U(1), np.full(size - 1, b)], dtype=np.uint64) for b in (_BASE, _INVERSE))
        return cls.up, cls.down


def grams(tokens: np.ndarray, gram: int) -> np.ndarray:
    """64-bit hashes of all runs of gram tokens, themselves 64-bit hashes."""
    n = len(tokens)
    up, down = _Powers.to(n + 1)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(tokens * down[:n], out=total[1:])
    h = (total[gram:] - total[:-gram]) * up[: n - gram + 1]
    h ^= h >> _U(32)
    h *= _U(0xD6E8FEB86659FD93)
    h ^= h >> _U(29)
    return h


def spans_hashed(tokens: np.ndarray, first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """64-bit hashes of the runs of tokens, themselves 64-bit hashes, at first and of size tokens."""
    n = len(tokens)
    up, down = _Powers.to(n + 1)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(tokens * down[:n], out=total[1:])
    return (total[first + size] - total[first]) * up[first]


def sliding_least(v: np.ndarray, width: int) -> np.ndarray:
    """Least of each width neighbours."""
    n = len(v) - width + 1
    padded = np.full(-(-len(v) // width) * width, np.iinfo(np.uint64).max, np.uint64)
    padded[: len(v)] = v
    rows = padded.reshape(-1, width)
    before = np.minimum.accumulate(rows, axis=1).ravel()
    after = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(after[:n], before[width - 1 : width - 1 + n])


def runs(text: bytes, depth: int = DEPTH, gram: int = GRAM, size: int = 1) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(first, last, anchor, digit 1, digit 2) of the runs of window starts that share their least
    gram; tokens are of size bytes, 1 or 8."""
    gram = min(gram, depth)
    if len(text) < depth * size:
        none = np.empty(0, np.int64)
        return none, none, none, none, none
    h = grams(_BYTE[np.frombuffer(text, np.uint8)] if size == 1 else np.frombuffer(text, _U), gram)
    place = np.arange(len(h), dtype=np.uint64)
    at = (sliding_least((h & _U(0xFFFFFFFF00000000)) | place, depth - gram + 1) & _U(0xFFFFFFFF)).astype(np.int64)
    first = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
    last = np.r_[first[1:], len(at)] - 1
    anchor = at[first]
    near, far = (anchor - last).tolist(), (anchor - first).tolist()
    whole = [xxhash.xxh3_64_intdigest(text[a * size : (b + depth) * size], (x << 32) | y) for a, b, x, y in zip(first.tolist(), last.tolist(), near, far)]
    return first, last, anchor, h[anchor].view(np.int64), np.array(whole, np.uint64).view(np.int64)


#: Scripts that put no spaces between words; a character of them is a word here.
_UNSPACED = rb"\xe0[\xb8-\xbb].|\xe1[\x80-\x82\x9e\x9f].|\xe2[\xba-\xbf].|[\xe3-\xe9]..|\xef[\xa4-\xab].|\xf0[\xa0-\xb3].."
_ANY_UNSPACED = re.compile(_UNSPACED, re.S)
_WORD = re.compile(_UNSPACED + rb"|(?:(?!" + _UNSPACED + rb")\S)+", re.S)
#: Bytes that stand for a word in spelt().
WORD = 8
#: Words of the shortest passage that counts by words.
PASSAGE = 51


def words(text: bytes) -> list[bytes]:
    """The words of a text in order, whitespace apart."""
    return _WORD.findall(text) if _ANY_UNSPACED.search(text) else text.split()


def has_unspaced(text: bytes) -> bool:
    return bool(_ANY_UNSPACED.search(text))


def word_spans(text: bytes) -> list[tuple[int, int]]:
    """(start, end) of the words of a text that has some unspaced script, else none."""
    return [m.span() for m in _WORD.finditer(text)] if _ANY_UNSPACED.search(text) else []


def spelt(text: bytes) -> bytes:
    """WORD bytes for each word of a text."""
    return b"".join(map(xxhash.xxh3_64_digest, words(text)))


@dataclass(frozen=True)
class Windows:
    """Windows of depth tokens, words or bytes; the gram of digit 1 has gram of them."""

    depth: int
    gram: int
    words: bool = False

    def form(self, text: bytes) -> tuple[bytes, int]:
        """The tokens of a text, and the bytes of each."""
        return (spelt(text), WORD) if self.words else (text, 1)


def _find_runs(kinds: list[Windows]):
    names = ["doc_id", "text_hash", "kind", "first", "last", "anchor", "one", "two"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, "text"):
            texts = b.column("text").cast(pa.binary()).to_pylist()
            for kind, of in enumerate(kinds):
                found = []
                for t in texts:
                    tokens, size = of.form(t)
                    found.append(runs(tokens, of.depth, of.gram, size))
                if not found:
                    continue
                take = pa.array(np.repeat(np.arange(len(found)), [len(r[0]) for r in found]))
                columns = [np.concatenate(c) for c in zip(*found)]
                yield pa.record_batch(
                    [
                        b.column("doc_id").take(take),
                        b.column("text_hash").take(take),
                        pa.array(np.full(len(take), kind, np.int32)),
                        *(pa.array(c.astype(np.int32)) for c in columns[:3]),
                        *(pa.array(c.astype(np.int64) ^ _KIND[kind]) for c in columns[3:]),
                    ],
                    names=names,
                )

    return run


def _find_steps(kinds: list[Windows]):
    """Rows of up to STEP neighbouring windows of a run: digits 3 and 4, and digit 5 of each."""
    names = ["doc_id", "text_hash", "kind", "first", "one", "three", "four", "five"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        digest = xxhash.xxh3_64_intdigest
        for b in sliced(batches, "text"):
            out: list[list] = [[] for _ in names]
            texts = b.column("text").cast(pa.binary())
            for k, found in enumerate(b.column("runs")):
                raw, doc, text_hash = texts[k].as_py(), b.column("doc_id")[k].as_py(), b.column("text_hash")[k].as_py()
                formed: dict[int, tuple[bytes, int]] = {}
                for r in found.as_py():
                    kind = r["kind"]
                    if kind not in formed:
                        formed[kind] = kinds[kind].form(raw)
                    (text, size), depth = formed[kind], kinds[kind].depth
                    at, last = r["anchor"], r["last"]
                    start = r["first"]
                    while start <= last:
                        step = (at - start) // STEP
                        stop = min(last, at - STEP * step)
                        # shared by all windows whose start is STEP * step to STEP * step + STEP - 1 before the anchor
                        shared = text[(at - STEP * step) * size : (at - STEP * step - STEP + 1 + depth) * size]
                        covered = digest(text[start * size : (stop + depth) * size], ((at - stop) << 32) | (at - start))
                        row = (doc, text_hash, kind, start, r["one"], digest(shared, step), covered, [digest(text[x * size : (x + depth) * size], at - x) for x in range(start, stop + 1)])
                        for column, value in zip(out, row):
                            column.append(value)
                        start = stop + 1
            ends = np.cumsum([0, *map(len, out[7])]).astype(np.int32)
            five = np.array([x for xs in out[7] for x in xs], np.uint64).view(np.int64)
            kept = [pa.array(c, t) for c, t in zip(out[:5], (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64()))]
            digits = [pa.array(np.array(c, np.uint64).view(np.int64)) for c in out[5:7]]
            yield pa.record_batch([*kept, *digits, pa.ListArray.from_arrays(pa.array(ends), pa.array(five))], names=names)

    return run


def keyed(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("text_hash", F.xxhash64("text"))


def repeats(docs: DataFrame, kinds: list[Windows]) -> DataFrame:
    """(doc_id, text_hash, spans) of the texts of docs(doc_id, text) that hold repeated windows of one
    of the kinds; spans are runs (first, last, kind) of their starts, in tokens. text_hash is
    xxhash64 of the text. Windows of different kinds never meet: the kind is in digits 1 and 2."""
    rows = keyed(docs)
    found = cut(rows.mapInArrow(_find_runs(kinds), ", ".join(_ids) + ", kind int, first int, last int, anchor int, one long, two long"), "runs")
    alive, state = _refined(found, ["one"], "two")
    alive = cut(alive.select("doc_id", "text_hash", "kind", "first", "last", "anchor", "one", "whole", "open"), "alive")
    drop(found)
    drop(state)
    opened = alive.where("open").groupBy("doc_id", "text_hash").agg(F.collect_set(F.struct("kind", "first", "last", "anchor", "one")).alias("runs"))
    steps = cut(_with_text(rows, opened).mapInArrow(_find_steps(kinds), ", ".join(_ids) + ", kind int, first int, one long, three long, four long, five array<long>"), "steps")
    near, state = _refined(steps, ["one", "three"], "four")
    near = cut(near.select("doc_id", "text_hash", "kind", "first", (F.col("first") + F.size("five") - 1).alias("last"), "one", "whole", F.when(F.col("open"), F.col("five")).alias("five")), "near")
    drop(steps)
    drop(state)
    exploded = near.select("doc_id", "text_hash", "kind", "one", "first", F.posexplode("five").alias("k", "window"))
    windows = cut(exploded.select("doc_id", "text_hash", "kind", "one", "window", (F.col("first") + F.col("k")).alias("first")), "windows")
    twice = windows.groupBy("one", "window").agg(F.count("*").alias("n")).where("n > 1").select("one", "window")
    ends = windows.join(twice, ["one", "window"]).select("doc_id", "text_hash", "kind", "first", F.col("first").alias("last"))
    every = ends
    for level in (alive, near):
        every = every.unionByName(level.where("whole").select("doc_id", "text_hash", "kind", "first", "last"))
    spans = cut(every.groupBy("doc_id", "text_hash").agg(F.collect_list(F.struct("first", "last", "kind")).alias("spans")), "spans")
    for done in (alive, near, windows):
        drop(done)
    return spans


def _refined(rows: DataFrame, shared: list[str], digit: str) -> tuple[DataFrame, DataFrame]:
    """rows that have company in shared digits, with whole (and in the next digit too) and open (the
    one of its kind that stands for all equal ones, as there are other kinds), and the table of
    kinds they are read from, written so that its shuffle files go before rows are shuffled."""
    ref = F.xxhash64("doc_id", "text_hash", "first")
    equal = rows.groupBy(*shared, digit).agg(F.count("*").alias("n"), F.min(ref).alias("ref"))
    company = equal.groupBy(*shared).agg(F.count("*").alias("kinds"), F.sum("n").alias("all")).where("all > 1")
    state = cut(equal.join(company, shared).select(*shared, digit, (F.col("n") > 1).alias("whole"), F.when(F.col("kinds") > 1, F.col("ref")).alias("open_ref")), "state")
    out = rows.join(state, [*shared, digit]).withColumn("open", F.coalesce(F.col("open_ref") == ref, F.lit(False)))
    return out.where("whole OR open"), state


def _with_text(rows: DataFrame, lists: DataFrame, how: str = "inner") -> DataFrame:
    lists = lists.withColumnsRenamed({"doc_id": "d", "text_hash": "h"}).hint("shuffle_hash")
    return rows.join(lists, (F.col("text_hash") == F.col("h")) & F.col("doc_id").eqNullSafe(F.col("d")), how).drop("d", "h")


def _merged(first: np.ndarray, last: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs that windows of depth tokens cover."""
    if not len(first):
        return first, first
    order = np.argsort(first, kind="stable")
    first, reach = first[order], np.maximum.accumulate(last[order] + depth)
    opens = np.flatnonzero(np.r_[True, first[1:] > reach[:-1]])
    return first[opens], reach[np.r_[opens[1:], len(reach)] - 1]


def _spans(column: pa.ListArray, kinds: list[Windows]) -> Iterator[list[tuple[np.ndarray, np.ndarray]]]:
    """For each row the merged runs of each kind."""
    edge = np.r_[0, np.cumsum(pc.fill_null(pc.list_value_length(column), 0).to_numpy(zero_copy_only=False))].tolist()
    first, last, kind = (c.to_numpy(zero_copy_only=False).astype(np.int64) for c in column.flatten().flatten())
    for a, b in zip(edge, edge[1:]):
        own = kind[a:b]
        yield [_merged(first[a:b][own == k], last[a:b][own == k], of.depth) for k, of in enumerate(kinds)]


def _without(text: bytes, start: np.ndarray, stop: np.ndarray) -> bytes:
    return b"".join(text[x:y] for x, y in zip([0, *stop.tolist()], [*start.tolist(), len(text)]))


def _kinds(depth: int, gram: int, n_words: int) -> list[Windows]:
    return [Windows(depth, gram), Windows(n_words, max(1, n_words // 4), True)][: 2 if n_words else 1]


def remaining(docs: DataFrame, depth: int = DEPTH, gram: int = GRAM, n_words: int = 0) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept) of every row of docs(doc_id, text): kept is the
    UTF-8 text without each byte that a string of depth bytes covers which also starts elsewhere,
    in the same or another row. With n_words also n_passages and n_passage_words: the maximal runs
    of words that passages of n_words words cover which also start elsewhere, whatever their bytes
    and the whitespace in them, and the words of these; kept is not changed by it. Null is empty;
    texts shorter than depth keep all; repeated rows are occurrences of their own; other columns
    are ignored."""
    kinds = _kinds(depth, gram, n_words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, "text"):
            texts, out = b.column("text").cast(pa.binary()).to_pylist(), []
            for t, (own, *more) in zip(texts, _spans(b.column("spans"), kinds)):
                kept = _without(t, *own)
                out.append((len(t), len(t) - len(kept), len(own[0]), kept, *(x for a, z in more for x in (len(a), int((z - a).sum())))))
            types = [pa.binary() if n == "kept" else pa.int64() for n in names[1:]]
            yield pa.record_batch([b.column("doc_id"), *(pa.array(c, t) for c, t in zip(zip(*out), types))], names=names)

    names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept", "n_passages", "n_passage_words"][: 7 if n_words else 5]
    joined = _with_text(keyed(docs), repeats(docs, kinds), "left").select("doc_id", "text", "spans")
    return joined.mapInArrow(run, ", ".join(f"{n} {'binary' if n == 'kept' else 'long'}" for n in names))


def _in_bytes(text: bytes, start: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Runs of words as runs of bytes of a text."""
    if not len(start):
        return start, stop
    place = np.array(word_spans(text) or [m.span() for m in re.finditer(rb"\S+", text)])
    return place[start, 0], place[stop - 1, 1]


def without_passages(docs: DataFrame, n_words: int, depth: int = DEPTH) -> DataFrame:
    """docs without each passage of n_words words or more that stands elsewhere too, whatever its
    length in bytes and the whitespace in it, and without what stripped() takes out; else as there."""
    return stripped(docs, depth, n_words=n_words)


def stripped(docs: DataFrame, depth: int = DEPTH, gram: int = GRAM, n_words: int = 0) -> DataFrame:
    """docs with repeated substrings taken out of text, and n_chars (if there is one) of what
    remains. Characters that lose some of their bytes go. Null texts stay null. With n_words,
    repeated passages of so many words go as well."""

    doc, text_hash, spans = (unused(docs, n) for n in ("span_doc", "span_text", "spans"))
    kinds = _kinds(depth, gram, n_words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, "text"):
            left = []
            for t, (own, *more) in zip(b.column("text").cast(pa.binary()).to_pylist(), _spans(b.column(spans), kinds)):
                runs = [own, *(_in_bytes(t or b"", *x) for x in more)]
                start, stop = _merged(*(np.concatenate(x) for x in zip(*runs)), 0)
                left.append(None if t is None else _without(t, start, stop).decode("utf-8", "ignore"))
            columns = {n: b.column(n) for n in names} | {"text": pa.array(left, pa.string())}
            yield pa.record_batch(list(columns.values()), names=list(columns))

    names = docs.columns
    lists = repeats(docs, kinds)
    lists = lists.withColumnsRenamed({"doc_id": doc, "text_hash": text_hash, "spans": spans}).hint("shuffle_hash")
    same = (F.xxhash64("text") == F.col(text_hash)) & F.col("doc_id").eqNullSafe(F.col(doc))
    out = docs.join(lists, same, "left").select(*names, spans).mapInArrow(run, docs.schema)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in names else out


def digests(left: DataFrame) -> DataFrame:
    """left, the rows of remaining(), with a digest in place of the bytes that remain."""
    return left.withColumn("kept_sha256", F.sha2("kept", 256)).drop("kept")


_WORDS_SQL = r"regexp_extract_all(coalesce(text, ''), '[\x{0E00}-\x{0EFF}\x{1000}-\x{10BF}\x{1780}-\x{17FF}\x{2E80}-\x{9FFF}\x{F900}-\x{FAFF}\x{20000}-\x{33FFF}]|[^\x20\x09-\x0D\x{0E00}-\x{0EFF}\x{1000}-\x{10BF}\x{1780}-\x{17FF}\x{2E80}-\x{9FFF}\x{F900}-\x{FAFF}\x{20000}-\x{33FFF}]+')"
REMAINING_SQL = f"""
WITH d AS (SELECT doc_id, row_number() OVER () AS r, hex(encode(coalesce(text, ''))) AS x, {_WORDS_SQL} AS ws FROM documents),
p AS (SELECT r, unnest(range(greatest(length(x) // 2 - 399, 0))) AS s FROM d),
w AS MATERIALIZED (SELECT r, s, md5_number(substr(x, (2 * s + 1)::BIGINT, 800)) AS h FROM p JOIN d USING (r)),
m AS (SELECT r, s FROM w JOIN (SELECT h FROM w GROUP BY h HAVING count(*) > 1) USING (h)),
g AS (SELECT r, s, CASE WHEN s <= lag(s) OVER (PARTITION BY r ORDER BY s) + 400 THEN 0 ELSE 1 END AS fresh FROM m),
q AS (SELECT r, min(s) AS a, max(s) + 400 AS b FROM (SELECT r, s, sum(fresh) OVER (PARTITION BY r ORDER BY s) AS i FROM g) GROUP BY r, i),
k AS (SELECT d.r, string_agg(substr(x, 2 * a0 + 1, 2 * (least(b0, length(x) // 2) - a0)), '' ORDER BY a0) AS kept FROM d JOIN (
  SELECT r, coalesce(lag(b) OVER o, 0) AS a0, a AS b0 FROM q WINDOW o AS (PARTITION BY r ORDER BY a)
  UNION ALL SELECT r, max(b), 1000000000000 FROM q GROUP BY r) USING (r) GROUP BY d.r),
wp AS (SELECT r, unnest(range(greatest(len(ws) - {PASSAGE - 1}, 0))) AS s FROM d),
ww AS MATERIALIZED (SELECT r, s, md5_number(array_to_string(ws[s + 1:s + {PASSAGE}], ' ')) AS h FROM wp JOIN d USING (r)),
wm AS (SELECT r, s FROM ww JOIN (SELECT h FROM ww GROUP BY h HAVING count(*) > 1) USING (h)),
wg AS (SELECT r, s, CASE WHEN s <= lag(s) OVER (PARTITION BY r ORDER BY s) + {PASSAGE} THEN 0 ELSE 1 END AS fresh FROM wm),
wq AS (SELECT r, count(*) AS n, sum(b - a) AS t FROM (SELECT r, min(s) AS a, max(s) + {PASSAGE} AS b FROM (SELECT r, s, sum(fresh) OVER (PARTITION BY r ORDER BY s) AS i FROM wg) GROUP BY r, i) GROUP BY r)
SELECT doc_id, length(x) // 2 AS n_bytes, coalesce(v.n, 0)::BIGINT AS n_removed, coalesce(v.c, 0) AS n_spans, sha256(unhex(coalesce(kept, x))) AS kept_sha256,
  coalesce(wq.n, 0)::BIGINT AS n_passages, coalesce(wq.t, 0)::BIGINT AS n_passage_words
FROM d LEFT JOIN k USING (r) LEFT JOIN (SELECT r, sum(b - a) AS n, count(*) AS c FROM q GROUP BY r) v USING (r) LEFT JOIN wq USING (r)
"""
