"""Hidden Markov models with categorical emissions whose counts may be sketched: Gibbs by
forward filtering and backward sampling of whole sequences."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallymill.functions.keyed import mixed
from tallymill.models.lda import merged, one_pass
from tallymill.operators.matrix import CountMatrix
from tallymill.params import smoothed
from tallymill.plans.lineage import cut, drop


@dataclass
class States:
    matrix: CountMatrix
    flat: np.ndarray
    totals: np.ndarray
    moves: np.ndarray
    starts: np.ndarray


def sequences(df: DataFrame, by: str, order: list[str], symbol: str) -> DataFrame:
    """(seq_id, xs): the symbols of a sequence in order."""
    return df.groupBy(F.col(by).alias("seq_id")).agg(F.transform(F.array_sort(F.collect_list(F.struct(*order, symbol))), lambda r: r[symbol].cast("long")).alias("xs"))


def filter_sample(x: np.ndarray, start: np.ndarray, move: np.ndarray, emit: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, float]:
    """A state sequence from its posterior, and the log-likelihood of x; emit is [symbols of x, states]."""
    n, k = emit.shape
    f, loglik = np.empty((n, k)), 0.0
    now = start * emit[0]
    for t in range(n):
        if t:
            now = (f[t - 1] @ move) * emit[t]
        total = now.sum()
        loglik += np.log(total)
        f[t] = now / total
    z = np.empty(n, np.int32)
    z[-1] = min(k - 1, int(np.searchsorted(np.cumsum(f[-1]), u[-1] * f[-1].sum(), "right")))
    for t in range(n - 2, -1, -1):
        w = f[t] * move[:, z[t + 1]]
        z[t] = min(k - 1, int(np.searchsorted(np.cumsum(w), u[t] * w.sum(), "right")))
    return z, loglik


def sweep(seqs: DataFrame, matrix: CountMatrix, types: int, alpha: float, beta: float, seed: int, number: int, read: States | None) -> DataFrame:
    """seqs(seq_id, xs, zs) with states drawn given smoothed counts; initial states without."""
    k = matrix.components
    held = seqs.sparkSession.sparkContext.broadcast(read)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r = held.value
        for b in batches:
            zs, logs = [], []
            for seq, xs in zip(b.column("seq_id").to_pylist(), b.column("xs")):
                x = xs.values.to_numpy()
                u = mixed(seed, number, seq, np.arange(len(x)))
                if r is None:
                    zs.append((u * k).astype(np.int32))
                    logs.append(0.0)
                    continue
                emit = (r.matrix.estimates(r.flat, x) + beta) / (r.totals + types * beta)
                move = (r.moves + alpha) / (r.moves.sum(1, keepdims=True) + k * alpha)
                start = (r.starts + alpha) / (r.starts.sum() + k * alpha)
                z, log = filter_sample(x, start, move, emit, u)
                zs.append(z)
                logs.append(log)
            yield pa.record_batch([b.column("seq_id"), b.column("xs"), pa.array(zs, pa.list_(pa.int32())), pa.array(logs, pa.float64())], names=["seq_id", "xs", "zs", "loglik"])

    return seqs.select("seq_id", "xs").where(F.size("xs") > 0).mapInArrow(run, "seq_id long, xs array<long>, zs array<int>, loglik double")


def gibbs(seqs: DataFrame, matrix: CountMatrix, types: int, alpha: float = 0.1, beta: float = 0.1, sweeps: int = 10, seed: int = 42) -> tuple[DataFrame, list[float]]:
    """(seqs with states zs, log-likelihood by sweep). Transition counts are exact (K x K); emission
    counts are filled and merged as those of topics are."""
    smoothed(alpha, beta)
    k, read, log = matrix.components, None, []
    for number in range(sweeps + 1):
        seqs = cut(sweep(seqs, matrix, types, alpha, beta, seed, number, read), "hmm")
        rows = seqs.select(F.col("seq_id").alias("doc_id"), F.col("xs").alias("vs"), "zs")
        counted = cut(one_pass(rows, matrix, alpha, seed, number, None).where("block IS NOT NULL"), "emissions")
        flat, totals, _ = merged(counted, matrix, seed, number)
        drop(counted)
        here, after = F.slice("zs", F.lit(1), F.size("zs") - 1), F.slice("zs", F.lit(2), F.size("zs") - 1)
        steps = seqs.where(F.size("zs") > 1).select(F.explode(F.arrays_zip(here.alias("a"), after.alias("b"))).alias("p")).groupBy("p.a", "p.b").agg(F.count("*").alias("n")).collect()
        moves, starts = np.zeros((k, k)), np.zeros(k)
        for r in steps:
            moves[r[0], r[1]] = r[2]
        for r in seqs.groupBy(F.get("zs", F.lit(0)).alias("z")).agg(F.count("*").alias("n")).collect():
            starts[r.z] = r.n
        read = States(matrix, flat, totals, moves, starts)
        log.append(seqs.agg(F.sum("loglik")).first()[0] or 0.0)
    return seqs, log
