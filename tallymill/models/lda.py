"""Stochastic EM for topic models whose word-by-topic counts are dense or sketched.

A sweep is one pass over document rows: every token draws a topic from smoothed counts of the
former sweep, the document recounts its own topics, and each task fills a partial
representation from zero. Partials are merged block by block; the merged one is read-only in
the next sweep, so nothing is locked or taken back.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tallymill.functions.keyed import draw, mixed, uniform, uniform_py, uniforms_np
from tallymill.operators.combined import built
from tallymill.operators.matrix import CountMatrix, Dense, RowSketches
from tallymill.params import SketchParams, smoothed
from tallymill.plans.lineage import cut, drop
from tallymill.plans.planner import BROADCAST_BYTES, choose_lookup, sketches_documents
from tallymill.sources.corpus import give_back, parts_of

_PASS = pa.schema([("doc_id", pa.int64()), ("vs", pa.list_(pa.int64())), ("zs", pa.list_(pa.int32())), ("block", pa.int32()), ("part", pa.int32()), ("payload", pa.binary())])
_PASS_SQL = "doc_id long, vs array<long>, zs array<int>, block int, part int, payload binary"
#: Elements of a block; a multiple of the number of topics is taken.
BLOCK = 1 << 22
#: Tokens whose weights are held at once.
CHUNK = 1 << 14


@dataclass
class Topics:
    """What a sweep reads: a representation, exact totals, smoothing and vocabulary size."""

    matrix: CountMatrix
    flat: np.ndarray
    totals: np.ndarray
    beta: float
    types: int

    def phi(self, keys: np.ndarray) -> np.ndarray:
        """Smoothed word probabilities, [words, topics]."""
        return (self.matrix.estimates(self.flat, keys) + self.beta) / (self.totals + self.types * self.beta)

    def mass(self) -> np.ndarray:
        """Sum of a topic's estimates over the vocabulary."""
        total = np.zeros(len(self.totals))
        for a in range(0, self.types, CHUNK):
            total += self.matrix.estimates(self.flat, np.arange(a, min(self.types, a + CHUNK))).sum(0)
        return total

    def normalised(self) -> Topics:
        """The same with totals that make word probabilities add up to one."""
        return Topics(self.matrix, self.flat, self.mass(), self.beta, self.types)


def _uniforms(stream: str, purpose: str, seed: int, sweep: int, doc: int, n: int) -> np.ndarray:
    if stream == "md5":
        return np.array([uniform_py(purpose, seed, sweep, doc, pos) for pos in range(n)])
    return mixed(seed, sweep, doc, np.arange(n), ord(purpose[-1]))


def _drawn(weights: np.ndarray, u: np.ndarray) -> np.ndarray:
    run = np.cumsum(weights, axis=1)
    hit = run > (u * run[:, -1])[:, None]
    return np.where(hit.any(1), hit.argmax(1), weights.shape[1] - 1).astype(np.int32)


def start(corpus: DataFrame, topics: int, seed: int, stream: str = "mixed") -> DataFrame:
    """corpus(doc_id, vs) with initial topics zs from keyed uniforms."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            docs, sizes = b.column("doc_id").to_pylist(), [len(v) if v.is_valid else 0 for v in b.column("vs")]
            zs = [(_uniforms(stream, "z0", seed, 0, d, n) * topics).astype(np.int32) for d, n in zip(docs, sizes)]
            yield pa.record_batch([b.column("doc_id"), b.column("vs"), pa.array(zs, pa.list_(pa.int32()))], names=["doc_id", "vs", "zs"])

    return corpus.select("doc_id", "vs").mapInArrow(run, "doc_id long, vs array<long>, zs array<int>")


def one_pass(docs: DataFrame, matrix: CountMatrix, alpha: float, seed: int, sweep: int, topics: Topics | None, stream: str = "mixed", tpd: SketchParams | None = None, local_sweeps: int = 1) -> DataFrame:
    """Rows of documents with new topics and, at the end of each task, of its partial counts: block
    -1 holds the topic totals. Without topics the present assignment is only counted."""
    held = docs.sparkSession.sparkContext.broadcast(topics)
    count = matrix.components
    size = max(1, BLOCK // count) * count

    def own_topics(z: np.ndarray, doc: int) -> np.ndarray:
        counts = np.bincount(z, minlength=count)
        if tpd is None:
            return counts.astype(float)
        keys = np.arange(count)
        one = RowSketches(tpd, 1)
        some = counts > 0
        return one.estimates(built(counts[some], keys[some], np.zeros(some.sum(), np.int64), 1, tpd, seed * 7919 + sweep + doc), keys)[:, 0]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        read, pairs, tallied = held.value, [], (np.empty(0, np.int64), np.empty(0, np.int64))
        for b in batches:
            docs_, news = b.column("doc_id").to_pylist(), []
            for doc, vs, zs in zip(docs_, b.column("vs"), b.column("zs")):
                v = vs.values.to_numpy() if vs.is_valid else np.empty(0, np.int64)
                z = zs.values.to_numpy() if zs.is_valid else np.empty(0, np.int32)
                if read is not None and len(v):
                    words, at = np.unique(v, return_inverse=True)
                    phi = read.phi(words)
                    for local in range(local_sweeps):
                        theta = own_topics(z, doc) + alpha
                        u = _uniforms(stream, "z", seed, sweep * local_sweeps + local, doc, len(v))
                        z = np.concatenate([_drawn(theta * phi[at[a : a + CHUNK]], u[a : a + CHUNK]) for a in range(0, len(v), CHUNK)])
                news.append(z)
                pairs.append(v * count + z)
            if len(pairs) > 1 << 12:
                tallied = _tally([tallied, *pairs])
                pairs = []
            yield pa.record_batch([b.column("doc_id"), b.column("vs"), pa.array(news, pa.list_(pa.int32())), *(pa.nulls(b.num_rows, f.type) for f in list(_PASS)[3:])], schema=_PASS)
        keys, n = _tally([tallied, *pairs])
        if not len(keys):
            return
        totals = np.bincount(keys % count, n, count).astype(np.int64)
        flat = matrix.build(n, keys // count, keys % count, seed * 1_000_003 + sweep * 1009 + part)
        rows = [(-1, totals.tobytes())] + [(a // size, flat[a : a + size].tobytes()) for a in range(0, len(flat), size)]
        for block, payload in rows:
            yield pa.record_batch([pa.nulls(1, f.type) for f in list(_PASS)[:3]] + [pa.array([block], pa.int32()), pa.array([part], pa.int32()), pa.array([payload], pa.binary())], schema=_PASS)

    return docs.select("doc_id", "vs", "zs").mapInArrow(run, _PASS_SQL)


def _tally(pairs: list) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys and their counts, from a tally and plain keys."""
    (keys, n), plain = pairs[0], np.concatenate([np.empty(0, np.int64), *pairs[1:]])
    every, at = np.unique(np.concatenate([keys, plain]), return_inverse=True)
    return every, np.bincount(at, np.concatenate([n, np.ones(len(plain), np.int64)]), len(every)).astype(np.int64)


def merged(done: DataFrame, matrix: CountMatrix, seed: int, sweep: int) -> tuple[np.ndarray, np.ndarray, int]:
    """(representation, totals, bytes of partials): partials of a block meet in one task, which holds
    one accumulator; what comes to the driver is the representation, whose size the planner checks."""
    kind = np.dtype(matrix.build(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64), 0).dtype)
    size = max(1, BLOCK // matrix.components) * matrix.components

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, total, moved = None, None, 0

        def out() -> pa.RecordBatch:
            return pa.record_batch([pa.array([now], pa.int32()), pa.array([total.tobytes()], pa.binary()), pa.array([moved], pa.int64())], names=["block", "payload", "moved"])

        for b in batches:
            for block, part, raw in zip(b.column("block").to_pylist(), b.column("part").to_pylist(), b.column("payload")):
                own = np.frombuffer(raw.as_py(), np.int64 if block < 0 else kind)
                if block != now:
                    if now is not None:
                        yield out()
                    now, total, moved = block, own, 0
                elif block < 0:
                    total = total + own
                else:
                    total = matrix.join(total, own, seed * 31 + sweep, part, block * size)
                moved += raw.as_py().__len__()
        if now is not None:
            yield out()

    rows = done.where("block IS NOT NULL").select("block", "part", "payload")
    parts = int(done.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    got = rows.repartition(parts, "block").sortWithinPartitions("block", "part").mapInArrow(run, "block int, payload binary, moved long").collect()
    blocks = {r.block: r.payload for r in got}
    totals = np.frombuffer(blocks.pop(-1, bytes(8 * matrix.components)), np.int64)
    flat = np.frombuffer(b"".join(bytes(blocks[k]) for k in sorted(blocks)), kind)
    return flat, totals, sum(r.moved for r in got)


@dataclass
class Fit:
    docs: DataFrame
    topics: Topics
    log: list[dict] = field(default_factory=list)


def sem_lda(
    corpus: DataFrame,
    matrix: CountMatrix,
    types: int,
    alpha: float = 0.1,
    beta: float = 0.1,
    sweeps: int = 60,
    seed: int = 42,
    stream: str = "mixed",
    tpd: SketchParams | None = None,
    held_out: DataFrame | None = None,
    normaliser: str = "mass",
    tolerance: float = 0.0,
    local_sweeps: int = 1,
    budget: int = BROADCAST_BYTES,
    every: int = 1,
) -> Fit:
    """Fits corpus(doc_id, vs) by sweeps; log has the seconds, bytes and, with held_out(doc_id,
    vs), the perplexity of the first five, the last, and those divisible by every. Stops before
    all sweeps once perplexity moves by less than tolerance, relatively, for three sweeps in a row
    that tell it. Only the two latest sweeps stay on disk."""
    from tallymill.evaluation import perplexity

    smoothed(alpha, beta)
    if tpd is not None and not sketches_documents(matrix.components, tpd):
        raise ValueError("a sketch of topics per document would be larger than its counts")
    if choose_lookup(matrix, budget) != "broadcast":
        raise ValueError("too large to broadcast; use joined_sweep")
    docs = start(corpus, matrix.components, seed, stream)
    fit, quiet, former = None, 0, None
    for sweep in range(sweeps + 1):
        began = time.monotonic()
        done = cut(one_pass(docs, matrix, alpha, seed, sweep, fit.topics if fit else None, stream, tpd, local_sweeps if fit else 1), "sweep")
        flat, totals, moved = merged(done, matrix, seed, sweep)
        topics = Topics(matrix, flat, totals, beta, types)
        seconds = time.monotonic() - began
        if former is not None:
            drop(former)
        former, docs = done, done.where("block IS NULL").select("doc_id", "vs", "zs")
        fit = Fit(docs, topics, fit.log if fit else [])
        row = {"sweep": sweep, "seconds": seconds, "bytes": matrix.size_bytes(), "moved": moved}
        told = held_out is not None and (sweep <= 5 or sweep == sweeps or sweep % every == 0)
        if told:
            row |= perplexity(held_out, topics, alpha, normaliser)
        if tolerance and told and fit.log and "perplexity" in fit.log[-1]:
            quiet = quiet + 1 if abs(row["perplexity"] / fit.log[-1]["perplexity"] - 1) < tolerance else 0
        fit.log.append(row)
        if quiet >= 3:
            break
    return fit


# Many chains over one corpus: one pass a sweep serves all of them.

#: Rows of documents hold up to ROWS of them, packed: ids in 8 bytes; lengths, words and topic counts, chain after chain, in 4.
_PACKED = ["ids", "sizes", "vs", "ns"]
_CHAINS = pa.schema([*((n, pa.binary()) for n in _PACKED), ("chain", pa.int32()), ("block", pa.int32()), ("part", pa.int32()), ("payload", pa.binary()), ("seconds", pa.float64())])
_CHAINS_SQL = "ids binary, sizes binary, vs binary, ns binary, chain int, block int, part int, payload binary, seconds double"
#: Elements, of 4 bytes, of the tallies that a task holds as plain arrays; beyond, distinct keys are sorted.
TALLIES = 40_000_000
#: Elements of a block of a chain's counts; a row is held several times over on its way to a file.
CHAIN_BLOCK = 1 << 19
#: Of the tables of sweeps: writers and readers hold a row group each.
SMALL = {"parquet.block.size": str(32 << 20), "parquet.enable.dictionary": "false", "compression": "zstd"}


def flat_lists(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values and lengths of a list column; null is empty."""
    return col.flatten().to_numpy(zero_copy_only=False), pc.fill_null(pc.list_value_length(col), 0).to_numpy(zero_copy_only=False)


def words_of(keys: np.ndarray, types: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys, all from 0 to types, in order, and the place of every key among them."""
    seen = np.zeros(types, bool)
    seen[keys] = True
    words = np.flatnonzero(seen)
    place = np.empty(types, np.intp)
    place[words] = np.arange(len(words))
    return words, place[keys]


def _drawn_by_topic(theta: np.ndarray, phi: np.ndarray, doc: np.ndarray, at: np.ndarray, u: np.ndarray) -> np.ndarray:
    """_drawn of theta[:, doc] * phi[:, at], topic by topic; doc and at are in range."""
    run, own = np.empty((len(phi), len(at))), np.empty(len(at))
    for k in range(len(phi)):
        np.take(theta[k], doc, out=run[k], mode="clip")
        np.take(phi[k], at, out=own, mode="clip")
        run[k] *= own
        if k:
            run[k] += run[k - 1]
    np.multiply(u, run[-1], out=own)
    z = np.zeros(len(at), np.int8 if len(phi) < 128 else np.int32)
    for k in range(len(phi) - 1):
        z += (run[k] <= own).view(np.int8)
    return z


def _documents(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray | None]]:
    """Ids, lengths, words and topic counts of documents, of rows(doc_id, vs) or of packed ones."""
    for b in batches:
        if "ids" in b.schema.names:
            for row in zip(*b.columns):
                yield tuple(np.frombuffer(x.as_buffer(), kind) for x, kind in zip(row, (np.int64, np.int32, np.int32, np.int32))) + (None,) * (4 - len(row))
        else:
            for part in parts_of(iter([b])):
                v, sizes = flat_lists(part.column("vs"))
                yield part.column("doc_id").fill_null(0).to_numpy(zero_copy_only=False), sizes, v.astype(np.int32), None
    give_back()


def _summed(tallies: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys of several tallies, in order, and their counts."""
    keys, at = np.unique(np.concatenate([k for k, _ in tallies]), return_inverse=True)
    return keys, np.bincount(at, np.concatenate([n for _, n in tallies]), len(keys)).astype(np.int64)


def chains_pass(docs: DataFrame, chains: list[tuple[CountMatrix, int]], types: int, alpha: float, sweep: int, topics: Broadcast | None, stream: str = "mixed") -> DataFrame:
    """one_pass for several (matrix, seed) at once, with the draws that each has alone. docs are rows(doc_id, vs), or
    packed ones of placed() or a former pass; documents leave packed, with topic counts in place of their tokens' topics.
    A word is tallied in 32 bits."""
    count = chains[0][0].components
    size, dense = max(1, CHAIN_BLOCK // count) * count, len(chains) * types * count <= TALLIES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, read = TaskContext.get().partitionId(), topics and topics.value
        spent = [0.0] * len(chains)
        # chains of one seed start alike: one tally serves them
        own = [c if read is not None else [s for _, s in chains].index(seed) for c, (_, seed) in enumerate(chains)]
        tallied: dict = {c: np.zeros((types, count), np.int32) if dense else [(np.empty(0, np.int64), np.empty(0, np.int64))] for c in own}
        rows = 0
        for ids, sizes, v, former in _documents(batches):
            doc = np.repeat(np.arange(len(sizes)), sizes)
            pos = np.arange(len(v)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
            rows += len(v)
            if stream == "md5":
                us = {s: uniforms_np(ids, sizes, "z0" if read is None else "z", s, sweep) for s in {s for _, s in chains}}
            else:
                us = {s: mixed(s, sweep, ids[doc], pos, ord("0" if read is None else "z")) for s in {s for _, s in chains}}
            words, at = words_of(v, types)
            if read is not None:
                former = former.reshape(len(sizes), len(chains), count)
            news = np.empty((len(sizes), len(chains), count), np.int32)
            for c, (_, seed) in enumerate(chains):
                if own[c] < c:
                    news[:, c] = news[:, own[c]]
                    continue
                began, u = time.thread_time(), us[seed]
                if read is None:
                    z = (u * count).astype(np.int64)
                else:
                    theta, phi = np.ascontiguousarray(former[:, c].T + alpha), np.ascontiguousarray(read[c].phi(words).T)
                    z = np.concatenate([np.empty(0, np.int8), *(_drawn_by_topic(theta, phi, doc[a : a + CHUNK], at[a : a + CHUNK], u[a : a + CHUNK]) for a in range(0, len(v), CHUNK))])
                news[:, c] = np.bincount(doc * count + z, minlength=len(sizes) * count).reshape(-1, count)
                new = np.bincount(at * count + z, minlength=len(words) * count)
                if dense:
                    tallied[c][words] += new.reshape(-1, count).astype(np.int32)
                else:
                    some, tallies = np.flatnonzero(new), tallied[c]
                    tallies.append((words[some // count] * count + some % count, new[some]))
                    # summed once the new keys outnumber the sum, so that no key is sorted for every part
                    if sum(len(k) for k, _ in tallies[1:]) > max(1 << 20, len(tallies[0][0])):
                        tallied[c] = [_summed(tallies)]
                spent[c] += time.thread_time() - began
            told = [pa.array([x.tobytes()], pa.binary()) for x in (ids, sizes.astype(np.int32), v, news)]
            yield pa.record_batch([*told, *(pa.nulls(1, f.type) for f in list(_CHAINS)[4:])], schema=_CHAINS)
        if not rows:
            return
        for c, (matrix, seed) in enumerate(chains):
            spent[c] += spent[own[c]] if own[c] < c else 0.0
        for c, (matrix, seed) in enumerate(chains):
            began = time.thread_time()
            if dense and type(matrix) is Dense:
                totals, flat = tallied[own[c]].sum(0, dtype=np.int64), tallied[own[c]].reshape(-1)
            else:
                if dense:
                    keys = np.flatnonzero(tallied[own[c]])
                    n = tallied[own[c]].reshape(-1)[keys].astype(np.int64)
                else:
                    keys, n = _summed(tallied[own[c]])
                if own[c] not in own[c + 1 :]:
                    tallied[own[c]] = None
                totals = np.bincount(keys % count, n, count).astype(np.int64)
                flat = matrix.build(n, keys // count, keys % count, seed * 1_000_003 + sweep * 1009 + part)
                keys = n = None
            spent[c] += time.thread_time() - began
            for a in range(-size, len(flat), size):
                payload = totals.tobytes() if a < 0 else flat[a : a + size].tobytes()
                told = [pa.array([x], f.type) for x, f in zip((c, a // size, part, payload, spent[c] if a < 0 else 0.0), list(_CHAINS)[4:])]
                yield pa.record_batch([pa.nulls(1, pa.binary())] * 4 + told, schema=_CHAINS)
            flat = None
            if own[c] not in own[c + 1 :]:
                tallied[own[c]] = None
        give_back()

    names = _PACKED if "ns" in docs.columns else _PACKED[:3] if "ids" in docs.columns else ["doc_id", "vs"]
    return docs.select(*names).mapInArrow(run, _CHAINS_SQL)


def merged_chains(done: DataFrame, chains: list[tuple[CountMatrix, int]], sweep: int) -> list[tuple[np.ndarray, np.ndarray, int, float]]:
    """(representation, totals, bytes of partials, seconds of the workers) of each chain, as merged() has them."""
    nothing = np.empty(0, np.int64)
    kinds = [np.dtype(m.build(nothing, nothing, nothing, 0).dtype) for m, _ in chains]
    count = chains[0][0].components
    size = max(1, CHAIN_BLOCK // count) * count

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, total, moved, spent = None, None, 0, 0.0

        def out() -> pa.RecordBatch:
            return pa.record_batch([pa.array([now[0]], pa.int32()), pa.array([now[1]], pa.int32()), pa.array([total.tobytes()], pa.binary()), pa.array([moved], pa.int64()), pa.array([spent])], names=["chain", "block", "payload", "moved", "seconds"])

        for b in batches:
            for c, block, part, seconds, row in zip(*(b.column(n).to_pylist() for n in ("chain", "block", "part", "seconds")), b.column("payload")):
                began, raw = time.thread_time(), row.as_buffer()
                own = np.frombuffer(raw, np.int64 if block < 0 else kinds[c])
                if (c, block) != now:
                    if now is not None:
                        yield out()
                    now, total, moved, spent = (c, block), own, 0, 0.0
                elif block < 0:
                    total = total + own
                else:
                    matrix, seed = chains[c]
                    total = matrix.join(total, own, seed * 31 + sweep, part, block * size)
                moved += len(raw)
                spent += seconds + time.thread_time() - began
        if now is not None:
            yield out()
        total = None
        give_back()

    rows = done.where("block IS NOT NULL").select("chain", "block", "part", "payload", "seconds")
    parts = int(done.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.repartition(parts, "chain", "block").sortWithinPartitions("chain", "block", "part")
    # written, so that the shuffle is gone before the next sweep
    met = cut(dealt.mapInArrow(run, "chain int, block int, payload binary, moved long, seconds double"), "merged", **SMALL)
    got = sorted(met.collect(), key=lambda r: (r.chain, r.block))
    drop(met)
    out = []
    for c, ((matrix, _), kind) in enumerate(zip(chains, kinds)):
        own = [r for r in got if r.chain == c]
        totals = next((np.frombuffer(r.payload, np.int64) for r in own if r.block < 0), np.zeros(count, np.int64))
        flat = b"".join(bytes(r.payload) for r in own if r.block >= 0)
        read = np.frombuffer(flat, kind) if flat else matrix.build(nothing, nothing, nothing, 0)
        out.append((read, totals, sum(r.moved for r in own), sum(r.seconds for r in own)))
    return out


def sem_chains(corpus: DataFrame, chains: list[tuple[CountMatrix, int]], types: int, alpha: float = 0.1, beta: float = 0.1, sweeps: int = 60, held_out: dict[str, DataFrame] | None = None, normaliser: str = "mass", every: int = 1) -> list[list[dict]]:
    """The logs of sem_lda for chains(matrix, seed) of equally many topics, swept together: a corpus, packed or not,
    is read once a sweep, not once a chain. A log's seconds are those of the workers, of all
    tasks, for a chain's draws, counts and merges. held_out names sets; a log has a row for each."""
    from tallymill.evaluation import perplexities

    smoothed(alpha, beta)
    if any(choose_lookup(m) != "broadcast" for m, _ in chains):
        raise ValueError("too large to broadcast; use joined_sweep")
    logs: list[list[dict]] = [[] for _ in chains]
    # a partial for each task, which is built and merged: one task a core
    docs, topics, former, cores = corpus, None, None, corpus.sparkSession.sparkContext.defaultParallelism
    for sweep in range(sweeps + 1):
        read = corpus.sparkSession.sparkContext.broadcast(topics) if topics else None
        done = cut(chains_pass(docs.coalesce(cores), chains, types, alpha, sweep, read), "sweep", **SMALL)
        if read:
            read.destroy()  # else its files stay on every machine
        got = merged_chains(done, chains, sweep)
        topics = [Topics(m, flat, totals, beta, types) for (m, _), (flat, totals, _, _) in zip(chains, got)]
        if former is not None:
            drop(former)
        former, docs = done, done.where("block IS NULL").select(*_PACKED)
        told = sweep <= 5 or sweep == sweeps or sweep % every == 0
        scores = {name: perplexities(held, topics, alpha, normaliser) for name, held in (held_out or {}).items()} if told else {}
        for c, ((matrix, _), (_, _, moved, seconds)) in enumerate(zip(chains, got)):
            row = {"sweep": sweep, "seconds": seconds, "bytes": matrix.size_bytes(), "moved": moved}
            logs[c] += [row | {"held": name} | s[c] for name, s in scores.items()] or [row]
    drop(former)
    return logs


def document_topics(corpus: DataFrame, matrix: CountMatrix, types: int, alpha: float, beta: float, sweeps: int, seed: int, stream: str = "md5") -> DataFrame:
    """(doc_id, z, n) of corpus(doc_id, vs), a row a document, after some sweeps: with exact counts and draws by md5 what
    joined_sweep() gives, but no token is shuffled."""
    smoothed(alpha, beta)
    docs, topics, former, cores = corpus, None, None, corpus.sparkSession.sparkContext.defaultParallelism
    for sweep in range(sweeps + 1):
        read = corpus.sparkSession.sparkContext.broadcast(topics) if topics else None
        done = cut(chains_pass(docs.coalesce(cores), [(matrix, seed)], types, alpha, sweep, read, stream), "sweep", **SMALL)
        if read:
            read.destroy()
        if sweep < sweeps:
            flat, totals, _, _ = merged_chains(done, [(matrix, seed)], sweep)[0]
            topics = [Topics(matrix, flat, totals, beta, types)]
        if former is not None:
            drop(former)
        former, docs = done, done.where("block IS NULL").select(*_PACKED)
    count = matrix.components

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, _, _, ns in _documents(batches):
            some = np.flatnonzero(ns)
            yield pa.record_batch([pa.array(ids[some // count]), pa.array((some % count).astype(np.int32)), pa.array(ns[some].astype(np.int64))], names=["doc_id", "z", "n"])

    return docs.mapInArrow(run, "doc_id long, z int, n long")


# Token relations: the same sweep by joins, for representations that outgrow a worker.


def token_start(toks: DataFrame, topics: int, seed: int) -> DataFrame:
    """toks(doc_id, pos, v) with an initial topic z."""
    return toks.select("doc_id", "pos", "v", F.floor(uniform("z0", seed, 0, F.col("doc_id"), F.col("pos")) * topics).cast("int").alias("z"))


def topic_counts(toks: DataFrame, topics: int) -> DataFrame:
    """(v, est): exact counts of each topic for every word, as an array."""
    pairs = toks.groupBy("v", "z").agg(F.count("*").cast("double").alias("n"))
    return _spread(pairs, "v", "z", "n", topics)


def _spread(pairs: DataFrame, by: str, index: str, value: str, size: int) -> DataFrame:
    held = pairs.groupBy(by).agg(F.map_from_entries(F.collect_list(F.struct(F.col(index), F.col(value)))).alias("m"))
    return held.select(by, F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda k: F.coalesce(F.col("m")[k], F.lit(0.0))).alias("est"))


def sketch_vectors(toks: DataFrame, topics: int, p: SketchParams) -> DataFrame:
    """(v, est) from a sketch of each topic's words."""
    from tallymill.operators import cms, combined

    rows = toks.select(F.col("z").alias("k"), "v", F.concat_ws(",", "doc_id", "pos").alias("event"), "doc_id", "pos")
    keys = toks.select("v").distinct().select(F.explode(F.sequence(F.lit(0), F.lit(topics - 1))).alias("k"), "v")
    if p.counter == "exact":
        cells = cms.cm_build(rows, "v", p, ["k"]) if p.rule == "plain" else cms.cm_build_conservative(rows, "v", p, ["doc_id", "pos"], ["k"])
        est = cms.cm_query(cells, keys, "v", p, ["k"])
    else:
        est = combined.query(combined.build(rows, "v", p, ["k"], ["doc_id", "pos"]), keys, "v", p, ["k"])
    return _spread(est.select("v", "k", F.col("est").cast("double").alias("n")), "v", "k", "n", topics)


def joined_sweep(toks: DataFrame, vectors: DataFrame, topics: int, alpha: float, beta: float, types: int, seed: int, sweep: int, weight=None) -> DataFrame:
    """toks(doc_id, pos, v, z) with topics drawn anew: word vectors are joined on v, the topics of
    a document counted by a window over it."""
    smoothed(alpha, beta)
    totals = toks.groupBy("z").agg(F.count("*").alias("n"))
    totals = totals.agg(F.map_from_entries(F.collect_list(F.struct("z", F.col("n").cast("double")))).alias("totals"))
    own = _spread(toks.groupBy("doc_id", "z").agg(F.count("*").cast("double").alias("n")), "doc_id", "z", "n", topics).withColumnRenamed("est", "tpd")
    every = toks.join(vectors, "v").join(own, "doc_id").crossJoin(F.broadcast(totals))

    def weigh(k: Column) -> Column:
        n = F.coalesce(F.col("totals")[k], F.lit(0.0))
        return (F.get("tpd", k) + alpha) * (F.get("est", k) + beta) / (n + types * beta)

    weights = F.transform(F.sequence(F.lit(0), F.lit(topics - 1)), weigh)
    u = uniform("z", seed, sweep, F.col("doc_id"), F.col("pos"))
    return every.select("doc_id", "pos", "v", draw(weights, u).cast("int").alias("z"))


def top_words(toks: DataFrame, vocab: DataFrame, n: int = 10) -> DataFrame:
    """(z, rank, w, count): the most frequent words of each topic, ties by word."""
    counts = toks.groupBy("z", "v").agg(F.count("*").alias("count"))
    rank = F.row_number().over(Window.partitionBy("z").orderBy(F.desc("count"), "w"))
    return counts.join(vocab.select("v", "w"), "v").withColumn("rank", rank).where(F.col("rank") <= n).select("z", "rank", "w", "count")
