"""Measures: perplexity, sizes, errors by band, laws, agreement with known classes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tallymill.params import dense_bytes
from tallymill.sources.corpus import parts_of

FOLD_IN = 20


def perplexity(docs: DataFrame, topics, alpha: float, normaliser: str = "mass") -> dict:
    """Held-out perplexity of docs(doc_id, vs): topic shares are fitted by EM on the first half of
    each document, with word probabilities fixed, and the second half is scored. With normaliser
    'mass' word probabilities add up to one; with 'exact' sketches flatter themselves."""
    return perplexities(docs, [topics], alpha, normaliser)[0]


#: Tokens whose word probabilities are held at once, while a document has no more.
_TOGETHER = 1 << 14


def _alike(half: np.ndarray) -> Iterator[np.ndarray]:
    """Places of the positive lengths in groups of similar length, so that little is padded."""
    order = np.argsort(-half, kind="stable")
    order = order[half[order] > 0]
    a = 0
    while a < len(order):
        most = int(half[order[a]])
        near = np.searchsorted(-half[order], -(most * 3 // 4), "right")
        stop = min(int(near), a + max(1, _TOGETHER // most))
        yield order[a:stop]
        a = stop


def perplexities(docs: DataFrame, models: list, alpha: float, normaliser: str = "mass") -> list[dict]:
    """perplexity() under each of several models, in one pass over docs(doc_id, vs)."""
    from tallymill.models.lda import flat_lists, words_of

    if normaliser not in ("mass", "exact"):
        raise ValueError("normaliser is mass or exact")
    held = docs.sparkSession.sparkContext.broadcast([m.normalised() for m in models] if normaliser == "mass" else models)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read, n = held.value, 0
        loss = np.zeros(len(read))
        for b in parts_of(batches):
            v, sizes = flat_lists(b.column("vs"))
            words, at = words_of(v, read[0].types)
            starts, half = np.cumsum(sizes) - sizes, sizes // 2
            n += int((sizes - half)[sizes > 1].sum())
            phis = [model.phi(words) for model in read]
            for own in _alike(half):
                a, least, most = starts[own], half[own], int(half[own].max())
                beyond = np.arange(most) >= least[:, None]
                first = at[np.where(beyond, a[:, None], a[:, None] + np.arange(most))]
                rest = sizes[own] - least
                doc = np.repeat(np.arange(len(own)), rest)
                second = at[np.arange(len(doc)) + np.repeat(a + least - np.cumsum(rest) + rest, rest)]
                for c, phi in enumerate(phis):
                    p = phi[first]
                    p[beyond] = 0
                    theta = np.full((len(own), phi.shape[1]), 1 / phi.shape[1])
                    for _ in range(FOLD_IN):
                        inverse = 1 / ((p @ theta[:, :, None])[:, :, 0] + beyond)
                        theta = alpha + theta * (inverse[:, None, :] @ p)[:, 0]
                        theta /= theta.sum(1, keepdims=True)
                    loss[c] -= float(np.log(np.einsum("ij,ij->i", phi[second], theta[doc])).sum())
        yield pa.record_batch([pa.array(np.arange(len(read)), pa.int32()), pa.array(loss), pa.array([n] * len(read), pa.int64())], names=["chain", "loss", "n"])

    rows = docs.select("vs").mapInArrow(run, "chain int, loss double, n long").groupBy("chain").agg(F.sum("loss"), F.sum("n")).collect()
    held.destroy()
    got = {r[0]: (r[1], r[2]) for r in rows}
    scores = [got.get(c, (0.0, 0)) for c in range(len(models))]
    return [{"perplexity": float(np.exp(loss / n)) if n else float("nan"), "tokens": n} for loss, n in scores]


def log_likelihood(toks: DataFrame, topics: int, alpha: float, beta: float, types: int) -> DataFrame:
    """Joint log-likelihood of toks(doc_id, v, z) under smoothed shares; a cheap diagnostic."""
    wz = toks.groupBy("z", "v").agg(F.count("*").alias("n"))
    nz = wz.groupBy("z").agg(F.sum("n").alias("total"))
    dz = toks.groupBy("doc_id", "z").agg(F.count("*").alias("n"))
    nd = dz.groupBy("doc_id").agg(F.sum("n").alias("total"))
    words = wz.join(nz, "z").agg(F.sum(F.col("n") * F.log((F.col("n") + beta) / (F.col("total") + types * beta))).alias("words"))
    shares = dz.join(nd, "doc_id").agg(F.sum(F.col("n") * F.log((F.col("n") + alpha) / (F.col("total") + topics * alpha))).alias("shares"))
    return words.crossJoin(shares).select((F.col("words") + F.col("shares")).alias("log_likelihood"))


def trials(log: DataFrame, by: list[str], values: list[str]) -> DataFrame:
    """Mean and standard deviation over trials."""
    return log.groupBy(*by).agg(*[f(v).alias(f"{v}_{n}") for v in values for f, n in ((F.avg, "mean"), (F.stddev_samp, "sd"))])


def gaps(log: DataFrame, baseline: str) -> DataFrame:
    """Perplexity over that of the baseline at the first and last sweep, by config."""
    ends = log.groupBy("config", "trial").agg(F.min_by("perplexity", "sweep").alias("first"), F.max_by("perplexity", "sweep").alias("last"))
    base = ends.where(F.col("config") == baseline).select("trial", F.col("first").alias("b_first"), F.col("last").alias("b_last"))
    return ends.join(base, "trial").groupBy("config").agg(F.avg(F.col("first") / F.col("b_first")).alias("gap_first"), F.avg(F.col("last") / F.col("b_last")).alias("gap_last"))


def error_bands(exact: DataFrame, est: DataFrame, on: list[str], bands: int = 4) -> DataFrame:
    """Bias, mean squared, absolute and relative error of est by band of frequency, and the shares
    of keys under- and overestimated. exact has n; ties of n are ordered by key."""
    both = exact.join(est, on).withColumn("error", F.col("est") - F.col("n"))
    # bands by distinct frequency, so that equal keys share one; few distinct values
    freq = both.select("n").distinct().withColumn("band", F.ntile(bands).over(Window.orderBy("n")))
    e = F.col("error")
    return both.join(freq, "n").groupBy("band").agg(
        F.count("*").alias("keys"),
        F.avg(e).alias("bias"),
        F.avg(e * e).alias("mse"),
        F.avg(F.abs(e)).alias("mae"),
        F.avg(F.abs(e) / F.col("n")).alias("relative"),
        F.avg((e < 0).cast("double")).alias("under"),
        F.avg((e > 0).cast("double")).alias("over"),
    )


def load_factor(cells: DataFrame, value: str, cap: int) -> DataFrame:
    """Used and saturated cells by hash row."""
    return cells.groupBy("i").agg(F.count("*").alias("used"), F.sum((F.col(value) >= cap).cast("long")).alias("saturated"))


def size_table(components: int, types: int, grid: list[tuple[int, int]], width: int) -> list[tuple]:
    """(l, log2 w, bytes / 1e5, dense bytes / 1e5) of sketches with cells of so many bytes."""
    return [(l, b, components * l * (1 << b) * width / 1e5, dense_bytes(components, types) / 1e5) for l, b in grid]


def purity(assigned: DataFrame, cluster: str, truth: str) -> DataFrame:
    """Share of rows in the commonest class of their cluster, and normalised mutual information."""
    t = assigned.groupBy(cluster, truth).agg(F.count("*").alias("n"))
    a = t.groupBy(cluster).agg(F.sum("n").alias("na"), F.max("n").alias("top"))
    b = t.groupBy(truth).agg(F.sum("n").alias("nb"))
    n = t.agg(F.sum("n").alias("total"))
    pure = a.agg((F.sum("top") / F.sum("na")).alias("purity"))
    joint = t.join(a, cluster).join(b, truth).crossJoin(F.broadcast(n))
    mi = joint.agg(F.sum(F.col("n") / F.col("total") * F.log(F.col("n") * F.col("total") / (F.col("na") * F.col("nb")))).alias("mi"))

    def entropy(rows: DataFrame, col: str, name: str) -> DataFrame:
        return rows.crossJoin(F.broadcast(n)).agg((-F.sum(F.col(col) / F.col("total") * F.log(F.col(col) / F.col("total")))).alias(name))

    every = pure.crossJoin(mi).crossJoin(entropy(a, "na", "ha")).crossJoin(entropy(b, "nb", "hb"))
    return every.select("purity", F.when(F.col("ha") + F.col("hb") > 0, 2 * F.col("mi") / (F.col("ha") + F.col("hb"))).otherwise(1.0).alias("nmi"))
