"""Paragraph deduplication: MinHash bands, exact Jaccard, components; passages inside lines.

A paragraph is a line with a word. Equal paragraphs (lower-cased words) share a hash and are one
node. One of one to four words is a single shingle, its whole sequence, so it is similar to its
equals only and takes no part in the rest. Bands of MinHash values put similar paragraphs in common buckets; pairs from
buckets are verified on their sets of five-word shingles, and the components of the verified
links decide which paragraphs go: all but the first occurrence of each.

Buckets of many paragraphs are first linked by a few pairs each. Where these leave a bucket's
members apart they are joined exactly: of each paragraph the shingles that are rarest among all in
such buckets, as many as two similar sets cannot both miss, meet those of the other components, and
pairs that length and place allow are verified too.

A passage need not be a line. The words of a text, line ends apart, are therefore also cut into
pieces at words that their neighbours alone decide, so that a passage is cut alike wherever it
stands. A run of neighbouring pieces that all stand elsewhere too is a passage once it has PASSAGE
words; short lines that many documents share are not.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tallymill.llm.shared import components, cut, drop, hot_join, sliced
from tallymill.llm.suffixes import _BYTE, _with_text, has_unspaced, keyed, sliding_least, spans_hashed, word_spans

WORDS = 5
SIMILAR = 0.8
#: 16 bands of 3 values: a pair of similarity 0.8 shares one with probability 1 - 1e-5, of 0.2 with 0.12.
BANDS, ROWS = 16, 3
#: The first members of a bucket, in an order drawn anew in each, link in every pair; later ones
#: with their two neighbours and with the first, and the bucket goes to crowded() if that leaves it apart.
ALL_PAIRS = 8
#: A text is cut before a word whose hash is the least of REACH neighbours on either side.
REACH = 4
#: Words of whole pieces that a passage has: what the cut ends leave of 97 in 100 passages of 51 to 58
#: random words, and of nearly all longer ones.
PASSAGE = 28
#: Members of a shingle up to which pairs are tried one by one, and pairs that are passed on at a time.
FEW, PASSED = 64, 1 << 18
_GAP = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
_rng = np.random.default_rng(11)
_ODD = np.random.default_rng(13).integers(1, 1 << 63, WORDS, dtype=np.uint64) | np.uint64(1)
_A = (_rng.integers(1, 1 << 63, BANDS * ROWS, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)
_B = _rng.integers(1, 1 << 63, BANDS * ROWS, dtype=np.uint64)


def _mixed(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(29))
    h *= np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def hashed(text: bytes, first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """64-bit hashes of the words of a text that start at first and have size bytes."""
    return _mixed(spans_hashed(_BYTE[np.frombuffer(text, np.uint8)], first, size))


def shingles(h: np.ndarray) -> np.ndarray:
    """Hashes of the five-word shingles at each of the words hashed to h, but the last four."""
    n = max(0, len(h) - WORDS + 1)
    out = np.zeros(n, np.uint64)
    for k in range(WORDS):
        out = (out ^ h[k : k + n]) * _ODD[k]
        out ^= out >> np.uint64(31)
    return out


@dataclass
class Words:
    """The lower-cased words, apart by ASCII whitespace, of several texts, one after another: their
    hashes, the bounds of each text among them, and the bounds of its lines."""

    h: np.ndarray
    text_start: np.ndarray
    line_text: np.ndarray
    line_place: np.ndarray
    line_start: np.ndarray
    line_stop: np.ndarray

    @classmethod
    def of(cls, texts: list[bytes | None]) -> Words:
        every = b"\n".join(t or b"" for t in texts).lower()
        raw = np.frombuffer(every, np.uint8)
        edge = np.flatnonzero(np.diff(np.r_[True, _GAP[raw], True].astype(np.int8)))
        first, size = edge[::2], edge[1::2] - edge[::2]
        opens = np.cumsum([0, *(len(t or b"") + 1 for t in texts)])[: len(texts)]
        line = np.r_[0, np.flatnonzero(raw == 10) + 1]
        of = np.searchsorted(opens, line, "right") - 1
        start = np.searchsorted(first, line)
        return cls(hashed(every, first, size), np.searchsorted(first, opens), of, np.arange(len(line)) - np.searchsorted(line, opens)[of], start, np.r_[start[1:], len(first)])

    def lines(self, least: int) -> tuple[np.ndarray, ...]:
        """(text, place among its lines, name, first word, last word and one) of the lines of least words or more."""
        some = np.flatnonzero(self.line_stop - self.line_start >= max(least, 1))
        start, stop = self.line_start[some], self.line_stop[some]
        return self.line_text[some], self.line_place[some], _names(self.h, start, stop), start, stop

    def pieces(self, skipped: list[int]) -> tuple[np.ndarray, ...]:
        """(text, place among its pieces, name, words) of the pieces of the texts that are not skipped."""
        if not len(self.h):
            return (np.empty(0, np.int64),) * 4
        stop = np.r_[self.text_start[1:], len(self.h)]
        cut, text = _cuts(self.h, self.text_start, stop)
        own = np.flatnonzero(stop > self.text_start)
        edge, text = np.r_[self.text_start[own], cut], np.r_[own, text]
        order = np.argsort(edge, kind="stable")
        edge, text = edge[order], text[order]
        end = np.r_[edge[1:], len(self.h)]
        names = _names(self.h, edge, end)
        place = np.arange(len(edge)) - np.searchsorted(text, text)
        keep = ~np.isin(text, skipped)
        return text[keep], place[keep], names[keep], (end - edge)[keep]


def _names(h: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
    return _mixed(spans_hashed(h, start, stop - start) ^ (stop - start).astype(np.uint64)).view(np.int64)


def _cuts(h: np.ndarray, start: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(word, text) of the words before which the texts, words start to stop of h, are cut."""
    none = np.empty(0, np.int64)
    if len(h) <= 2 * REACH:
        return none, none
    g = h * np.uint64(3)
    g[:-1] += h[1:] * np.uint64(0x9E3779B97F4A7C15)
    ends = stop[stop > start] - 1
    g[ends] = h[ends] * np.uint64(3)  # what follows a text is not its own
    g = _mixed(g)
    at = np.flatnonzero(g[REACH:-REACH] == sliding_least(g, 2 * REACH + 1)) + REACH
    text = np.searchsorted(start, at, "right") - 1
    inside = (at - REACH >= start[text]) & (at + REACH < stop[text])
    return at[inside], text[inside]


def unspaced(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(name, words) of the pieces of a text in which characters of unspaced scripts are words."""
    text = text.lower()
    first, end = np.array(word_spans(text)).T
    h = hashed(text, first, end - first)
    cut, _ = _cuts(h, np.array([0]), np.array([len(h)]))
    edge = np.r_[0, cut]
    stop = np.r_[edge[1:], len(h)]
    return _names(h, edge, stop), stop - edge


def bands(every: np.ndarray, where: np.ndarray) -> np.ndarray:
    """One 64-bit bucket for each band and set, sets being the runs of every that start at where."""
    out = np.empty((BANDS, len(where)), np.uint64)
    for b in range(BANDS):
        bucket = np.full(len(where), b, np.uint64)
        for r in range(b * ROWS, (b + 1) * ROWS):
            h = every * _A[r] + _B[r]
            h ^= h >> np.uint64(31)
            h *= np.uint64(0x9FB21C651E98DF25)
            h ^= h >> np.uint64(28)
            bucket = (bucket ^ np.minimum.reduceat(h, where)) * np.uint64(0x9E3779B97F4A7C15)
            bucket ^= bucket >> np.uint64(29)
        out[b] = bucket
    return out


_UNIT = "doc_id long, text_hash long, piece boolean, place int, words int, par long"


def _units(least: int, with_pieces: bool):
    """Lines of least words or more and, if wanted, pieces of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, "text"):
            texts = b.column("text").cast(pa.binary()).to_pylist()
            own = Words.of(texts)
            text, place, name, start, stop = own.lines(least)
            found = [(text, place, name, stop - start)]
            if with_pieces:
                other = [k for k, t in enumerate(texts) if t and not t.isascii() and has_unspaced(t)]
                found.append(own.pieces(other))
                for k in other:
                    name, size = unspaced(texts[k])
                    found.append((np.full(len(name), k), np.arange(len(name)), name, size))
            which, place, name, size = (np.concatenate(c) for c in zip(*found))
            take = pa.array(which.astype(np.int64))
            yield pa.record_batch(
                [b.column("doc_id").take(take), b.column("text_hash").take(take), pa.array(np.arange(len(which)) >= len(text)), pa.array(place.astype(np.int32)), pa.array(size.astype(np.int32)), pa.array(name.astype(np.int64))],
                names=["doc_id", "text_hash", "piece", "place", "words", "par"],
            )

    return run


#: Paragraphs whose bands are taken at once.
TOGETHER = 4000


def _buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    done: set[int] = set()
    for b in sliced(batches, "text"):
        if len(done) > 200_000:
            done.clear()
        own = Words.of(b.column("text").cast(pa.binary()).to_pylist())
        _, _, name, start, stop = own.lines(WORDS)
        name, at = np.unique(name, return_index=True)
        fresh = np.fromiter((x not in done for x in name.tolist()), bool, len(name))
        name, at = name[fresh], at[fresh]
        done.update(name.tolist())
        every = shingles(own.h)
        for k in range(0, len(name), TOGETHER):
            some = at[k : k + TOGETHER]
            size = stop[some] - start[some] - WORDS + 1
            where = np.cumsum(size) - size
            rows = bands(every[np.arange(size.sum()) + np.repeat(start[some] - where, size)], where).view(np.int64)
            yield pa.record_batch([pa.array(rows.ravel()), pa.array(np.tile(name[k : k + TOGETHER], BANDS))], names=["bucket", "par"])


def _pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Candidate pairs (a, b) from rows (bucket, drawn, par) sorted by bucket and drawn; members of
    buckets of more than ALL_PAIRS also come out paired with themselves, with their bucket. Of an
    open bucket only its first and its last ALL_PAIRS members are held."""
    none = np.empty(0, np.int64)
    bucket, par, rank, head = none, none, none, none
    for batch in batches:
        held = len(bucket)
        bucket = np.concatenate([bucket, batch.column("bucket").to_numpy()])
        par = np.concatenate([par, batch.column("par").to_numpy()])
        if len(bucket) == held:
            continue
        opens = np.r_[True, bucket[1:] != bucket[:-1]]
        fresh = opens | np.r_[True, par[1:] != par[:-1]]
        bucket, par, opens = bucket[fresh], par[fresh], opens[fresh]
        at = np.arange(len(bucket))
        first = np.flatnonzero(opens)
        of = np.cumsum(opens) - 1
        begun = rank[0] if held else 0
        rank = at - first[of] + np.where(of == 0, begun, 0)
        heads = par[first]
        if held:
            heads[0] = head
        a, b, where = [], [], []
        for step in range(1, ALL_PAIRS):
            k = np.flatnonzero((rank >= step) & ((rank < ALL_PAIRS) | (step <= 2)) & (at >= held))
            a.append(par[k - step])
            b.append(par[k])
        k = np.flatnonzero((rank >= ALL_PAIRS) & (at >= held))
        a.append(heads[of[k]])
        b.append(par[k])
        a, b = np.concatenate(a), np.concatenate(b)
        pair = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], 1), axis=0)
        # a bucket is known to be large at its ninth member
        known = np.flatnonzero((rank == ALL_PAIRS) & (at >= held))
        crowd = np.unique(np.r_[k, (known[:, None] - np.arange(1, ALL_PAIRS + 1)).ravel()])
        yield pa.record_batch(
            [pa.array(np.r_[pair[:, 0], par[crowd]]), pa.array(np.r_[pair[:, 1], par[crowd]]), pa.array(np.r_[np.zeros(len(pair), np.int64), bucket[crowd]], mask=np.arange(len(pair) + len(crowd)) < len(pair))],
            names=["a", "b", "bucket"],
        )
        head = heads[-1]
        keep = max(first[-1], len(bucket) - ALL_PAIRS)
        bucket, par, rank = bucket[keep:], par[keep:], rank[keep:]


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in sliced(batches, "text"):
        own = Words.of(b.column("text").cast(pa.binary()).to_pylist())
        text, place, name, start, stop = own.lines(WORDS)
        wanted = b.column("wanted")
        asked = np.repeat(np.arange(len(wanted)), pc.list_value_length(wanted).to_numpy(zero_copy_only=False)) << 32
        some = np.isin((text << 32) | place, asked | wanted.flatten().to_numpy(zero_copy_only=False))
        every = shingles(own.h)
        sets = [np.unique(every[x : y - WORDS + 1]).view(np.int64) for x, y in zip(start[some].tolist(), stop[some].tolist())]
        yield pa.record_batch([pa.array(name[some], pa.int64()), pa.array(sets, pa.list_(pa.int64()))], names=["par", "shingles"])


def _similar(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        keep = []
        for x, y in zip(b.column("x"), b.column("y")):
            x, y = x.values.to_numpy(), y.values.to_numpy()
            low, high = sorted((len(x), len(y)))
            both = len(np.intersect1d(x, y, assume_unique=True)) if low >= SIMILAR * high else 0
            keep.append(both >= SIMILAR * (low + high - both))
        yield pa.record_batch([b.column("a"), b.column("b")], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))


def _enough(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Common shingles that make sets of x and y similar: 4 ninths of both together."""
    return -(-4 * (x + y) // 9)


def _meetings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs of different labels from rows (shingle, size, at, label, par) sorted in this order, whose
    sets can be similar if this is the first shingle they share: at others come before it."""
    left = [np.empty(0, np.int64) for _ in range(5)]

    def passed(a: list[np.ndarray], b: list[np.ndarray]) -> pa.RecordBatch:
        a, b = np.concatenate(a), np.concatenate(b)
        pair = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], 1), axis=0)
        return pa.record_batch([pa.array(pair[:, 0]), pa.array(pair[:, 1])], names=["a", "b"])

    def few(shingle: np.ndarray, size: np.ndarray, at: np.ndarray, label: np.ndarray, par: np.ndarray) -> Iterator[pa.RecordBatch]:
        first = np.flatnonzero(np.r_[True, shingle[1:] != shingle[:-1]])
        stop = np.repeat(np.r_[first[1:], len(shingle)], np.diff(np.r_[first, len(shingle)]))
        rows, step = np.arange(len(shingle)), 1
        while len(rows := rows[rows + step < stop[rows]]):
            x, y = rows, rows + step
            need = _enough(size[x], size[y])
            k = (label[x] != label[y]) & (size[x] - at[x] >= need) & (size[y] - at[y] >= need)
            yield passed([par[x[k]]], [par[y[k]]])
            step += 1

    def many(size: np.ndarray, at: np.ndarray, label: np.ndarray, par: np.ndarray) -> Iterator[pa.RecordBatch]:
        # members of one size and place stand together, sorted by label
        edge = np.r_[np.flatnonzero(np.r_[True, (size[1:] != size[:-1]) | (at[1:] != at[:-1])]), len(size)]
        a, b, held = [], [], 0
        for i in range(len(edge) - 1):
            x = slice(edge[i], edge[i + 1])
            heads, rest = size[edge[i:-1]], at[edge[i:-1]]
            need = _enough(heads, size[edge[i]])
            for j in np.flatnonzero((size[edge[i]] - at[edge[i]] >= need) & (heads - rest >= need)) + i:
                y = slice(edge[j], edge[j + 1])
                for k in range(x.start, x.stop):
                    if i == j:  # labels ascend, so each pair comes once
                        other = par[k + 1 + np.searchsorted(label[k + 1 : y.stop], label[k], "right") : y.stop]
                    else:
                        low, high = np.searchsorted(label[y], label[k]), np.searchsorted(label[y], label[k], "right")
                        other = np.r_[par[y][:low], par[y][high:]]
                    if len(other):
                        a.append(np.full(len(other), par[k]))
                        b.append(other)
                        held += len(other)
                    if held > PASSED:
                        yield passed(a, b)
                        a, b, held = [], [], 0
        if held:
            yield passed(a, b)

    def out(columns: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        shingle = columns[0]
        first = np.flatnonzero(np.r_[True, shingle[1:] != shingle[:-1]])
        count = np.diff(np.r_[first, len(shingle)])
        small = np.repeat(count <= FEW, count)
        if small.any():
            yield from few(*(c[small] for c in columns))
        for k, n in zip(first[count > FEW], count[count > FEW]):
            yield from many(*(c[k : k + n] for c in columns[1:]))

    for batch in batches:
        left = [np.concatenate([held, c.to_numpy()]) for held, c in zip(left, batch.columns)]
        if len(left[0]) and (last := int(np.searchsorted(left[0], left[0][-1]))):
            yield from out([c[:last] for c in left])
            left = [c[last:] for c in left]
    if len(left[0]):
        yield from out(left)


def crowded(sets: DataFrame) -> DataFrame:
    """Candidate pairs (a, b) of sets(par, label, shingles), with every similar pair of different
    labels among them. Similar sets share one of their first fifth of shingles and one more, in any
    order that all keep to: here the rarest come first, and shingles of one label meet nothing."""
    parts = int(sets.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    size = F.size("shingles").cast("long").alias("size")
    every = sets.select("par", "label", size, F.explode("shingles").alias("shingle"))
    often = every.groupBy("shingle").agg(F.count("*").alias("n"), (F.min("label") != F.max("label")).alias("mixed"))
    ranked = every.join(often, "shingle").groupBy("par", "label", "size").agg(F.sort_array(F.collect_list(F.struct("n", "shingle", "mixed"))).alias("s"))
    prefix = F.slice("s", F.lit(1), F.floor(F.col("size") / 5).cast("int") + 1)
    met = ranked.select("par", "label", "size", F.posexplode(prefix).alias("at", "s")).where("s.mixed")
    met = met.select(F.col("s.shingle").alias("shingle"), "size", F.col("at").cast("long").alias("at"), "label", "par")
    met = met.repartition(parts, "shingle").sortWithinPartitions("shingle", "size", "at", "label", "par")
    return met.mapInArrow(_meetings, "a long, b long").distinct()


def _labels(rows: DataFrame, names: DataFrame) -> DataFrame:
    """(par, label) of the paragraphs that are similar to others, names(par, first) being all of rows."""
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    met = rows.select("text").mapInArrow(_buckets, "bucket long, par long").withColumn("drawn", F.xxhash64("bucket", "par"))
    pairs = met.repartition(parts, "bucket").sortWithinPartitions("bucket", "drawn", "par").select("bucket", "par").mapInArrow(_pairs, "a long, b long, bucket long")
    pairs = cut(pairs.distinct(), "pairs")
    wanted = pairs.select(F.col("a").alias("par")).unionByName(pairs.select(F.col("b").alias("par"))).distinct()
    lists = names.join(wanted, "par", "left_semi").groupBy("first.doc_id", "first.text_hash").agg(F.collect_set("first.place").alias("wanted"))
    sets = cut(_with_text(rows, lists).mapInArrow(_sets, "par long, shingles array<long>").dropDuplicates(["par"]), "shingles")
    x = sets.select(F.col("par").alias("a"), F.col("shingles").alias("x"))
    y = sets.select(F.col("par").alias("b"), F.col("shingles").alias("y"))

    def similar(pairs: DataFrame) -> DataFrame:
        return pairs.join(x, "a").join(y, "b").select("a", "b", "x", "y").mapInArrow(_similar, "a long, b long")

    label = components(similar(pairs.where("bucket IS NULL").select("a", "b"))).withColumnRenamed("node", "par")
    # only buckets that the links leave in several components have pairs to add
    member = pairs.where("bucket IS NOT NULL").select("bucket", F.col("a").alias("par")).join(label, "par", "left").withColumn("label", F.coalesce("label", "par"))
    apart = member.groupBy("bucket").agg(F.min("label").alias("low"), F.max("label").alias("high")).where("low <> high").select("bucket")
    member = cut(member.join(apart, "bucket", "left_semi").select("par", "label").distinct(), "crowd")
    if not member.isEmpty():
        more = similar(crowded(sets.join(member, "par")))
        for side in "ab":
            own = member.select(F.col("par").alias(side), F.col("label").alias(f"l{side}"))
            more = more.join(own, side)
        over = components(more.select(F.col("la").alias("a"), F.col("lb").alias("b"))).withColumnRenamed("label", "top")
        own = label.unionByName(member).distinct()
        label = cut(own.join(over, own["label"] == over["node"], "left").select("par", F.coalesce("top", "label").alias("label")), "labels")
    for done in (pairs, sets, member):
        drop(done)
    return label


def _clusters(rows: DataFrame, lines: DataFrame) -> DataFrame:
    place = F.struct("doc_id", "text_hash", "place")
    # a very common paragraph is one row before anything is joined
    names = cut(lines.groupBy("par").agg(F.count("*").alias("n"), F.min(place).alias("first")), "names")
    label = _labels(rows, names)
    own = names.join(label, "par", "left").select("par", "n", F.coalesce("label", "par").alias("cluster"))
    first = names.join(label, "par", "left").groupBy(F.coalesce("label", "par").alias("cluster")).agg(F.count("*").alias("members"), F.sum("n").alias("size"), F.min("first").alias("first"))
    first = cut(first, "clusters")
    marked = cut(hot_join(own, first, "cluster", "members"), "marked")
    for done in (names, first):
        drop(done)
    return hot_join(lines, marked, "par", "n").select("doc_id", "text_hash", "place", "words", "par", "cluster", "size", (~place.eqNullSafe(F.col("first"))).alias("removed"))


def clusters(docs: DataFrame, least: int = WORDS) -> DataFrame:
    """(doc_id, text_hash, place, words, par, cluster, size, removed) of every paragraph of least words or
    more of docs(doc_id, text): cluster is a paragraph name shared by its component, size its number of
    occurrences; removed is false for its first by doc_id, text_hash and place. Null and empty
    texts have no paragraphs; repeated rows are occurrences of one place; other columns are ignored."""
    rows = keyed(docs)
    lines = cut(rows.mapInArrow(_units(least, False), _UNIT), "paragraphs")
    return _clusters(rows, lines)


_RUNS = f"""aggregate(at, named_struct('last', -2, 'now', 0L, 'n', 0L, 'words', 0L),
  (r, x) -> if(x.place = r.last + 1, named_struct('last', x.place, 'now', r.now + x.words, 'n', r.n, 'words', r.words),
    named_struct('last', x.place, 'now', bigint(x.words), 'n', r.n + if(r.now >= {PASSAGE}, 1L, 0L), 'words', r.words + if(r.now >= {PASSAGE}, r.now, 0L))),
  r -> named_struct('n', r.n + if(r.now >= {PASSAGE}, 1L, 0L), 'words', r.words + if(r.now >= {PASSAGE}, r.now, 0L)))"""


def passages(units: DataFrame) -> DataFrame:
    """(doc_id, text_hash, n_passages, n_passage_words): the longest runs of neighbouring pieces of
    units that all occur twice or more, PASSAGE words or longer, in texts that have one."""
    cuts = units.where("piece").select("doc_id", "text_hash", "place", "words", "par")
    twice = cut(cuts.groupBy("par").agg(F.count("*").alias("n")).where("n > 1"), "twice")
    hits = hot_join(cuts, twice, "par", "n", "left_semi").groupBy("doc_id", "text_hash").agg(F.array_sort(F.collect_set(F.struct("place", "words"))).alias("at"))
    return hits.select("doc_id", "text_hash", F.expr(_RUNS).alias("r")).where("r.n > 0").select("doc_id", "text_hash", F.col("r.n").alias("n_passages"), F.col("r.words").alias("n_passage_words"))


def _copies(rows: DataFrame) -> DataFrame:
    """(doc_id, text_hash, first) for every row of rows: whether it is the first of those equal in both."""
    key = ["doc_id", "text_hash"]
    here = rows.select(*key, F.spark_partition_id().alias("part")).groupBy(*key, "part").agg(F.count("*").alias("n"))
    parts = here.groupBy(*key).agg(F.collect_list("n").alias("ns")).select(*key, F.posexplode("ns").alias("k", "n"))
    return parts.select(*key, "k", F.explode(F.sequence(F.lit(1), F.col("n"))).alias("j")).select(*key, ((F.col("k") == 0) & (F.col("j") == 1)).alias("first"))


def by_document(docs: DataFrame) -> DataFrame:
    """One row for every row of docs(doc_id, text), short paragraphs included: (doc_id, n_paragraphs, n_repeated,
    n_repeated_words, n_removed, repeated, removed_places, clusters, n_passages, n_passage_words), clusters those of
    two or more occurrences, passages as in passages(). Null and empty texts have none of all; of rows equal
    in doc_id and text all but one lose every paragraph; other columns are ignored, whatever their names."""
    rows = keyed(docs)
    units = cut(rows.mapInArrow(_units(1, True), _UNIT), "paragraphs")
    key = ["doc_id", "text_hash"]
    own = _clusters(rows, units.where("NOT piece")).groupBy(*key).agg(
        F.array_sort(F.collect_set(F.struct("place", "words", (F.col("size") > 1).alias("twice"), "removed"))).alias("ps"),
        F.array_sort(F.collect_set(F.when(F.col("size") > 1, F.col("cluster")))).alias("clusters"),
    )
    told = own.withColumnsRenamed({"doc_id": "d", "text_hash": "h"})
    found = passages(units).withColumnsRenamed({"doc_id": "d2", "text_hash": "h2"})
    # without the texts here
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("text_hash"))
    joined = _copies(ids).join(told, (F.col("text_hash") == F.col("h")) & F.col("doc_id").eqNullSafe(F.col("d")), "left")
    joined = joined.join(found, (F.col("text_hash") == F.col("h2")) & F.col("doc_id").eqNullSafe(F.col("d2")), "left")
    joined = joined.withColumn("ps", F.coalesce("ps", F.expr("cast(array() as array<struct<place:int,words:int,twice:boolean,removed:boolean>>)")))
    # of equal rows only the first keeps what it may keep
    joined = joined.withColumn("ps", F.when(F.col("first"), F.col("ps")).otherwise(F.expr("transform(ps, p -> named_struct('place', p.place, 'words', p.words, 'twice', true, 'removed', true))")))
    return joined.select(
        "doc_id",
        F.size("ps").cast("long").alias("n_paragraphs"),
        F.expr("bigint(size(filter(ps, p -> p.twice)))").alias("n_repeated"),
        F.expr("aggregate(filter(ps, p -> p.twice), 0L, (n, p) -> n + p.words)").alias("n_repeated_words"),
        F.expr("bigint(size(filter(ps, p -> p.removed)))").alias("n_removed"),
        F.expr("exists(ps, p -> p.twice)").alias("repeated"),
        F.expr("transform(filter(ps, p -> p.removed), p -> p.place)").alias("removed_places"),
        F.coalesce("clusters", F.expr("cast(array() as array<bigint>)")).alias("clusters"),
        F.coalesce("n_passages", F.lit(0).cast("long")).alias("n_passages"),
        F.coalesce("n_passage_words", F.lit(0).cast("long")).alias("n_passage_words"),
    )


def stripped(docs: DataFrame) -> DataFrame:
    """(doc_id, text) of every row of docs(doc_id, text) without its removed paragraphs; of rows equal in
    both all but one keep lines without a word only. Null is empty; other columns are ignored."""
    lists = clusters(docs, 1).groupBy("doc_id", "text_hash").agg(F.collect_set(F.when(F.col("removed"), F.col("place"))).alias("gone"), F.collect_set("place").alias("every"))
    rows = _with_text(keyed(docs), lists, "left")
    again = keyed(docs).groupBy("doc_id", "text_hash").agg(F.count("*").alias("n")).where("n > 1").withColumnsRenamed({"doc_id": "d", "text_hash": "h"})
    same = (F.col("text_hash") == F.col("h")) & F.col("doc_id").eqNullSafe(F.col("d"))
    nth = F.row_number().over(Window.partitionBy("doc_id", "text_hash").orderBy("text_hash"))
    several = rows.join(again, same, "left_semi").withColumn("gone", F.when(nth > 1, F.col("every")).otherwise(F.col("gone")))
    rows = rows.join(again, same, "left_anti").unionByName(several)
    lines = F.split("text", "\n", -1)
    kept = F.filter(F.transform(lines, lambda x, k: F.struct(x.alias("x"), k.alias("k"))), lambda s: ~F.coalesce(F.array_contains(F.col("gone"), s["k"]), F.lit(False)))
    return rows.select("doc_id", F.array_join(F.transform(kept, lambda s: s["x"]), "\n").alias("text"))
