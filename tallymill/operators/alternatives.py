"""Methods the sketched samplers are compared with: data subsets, projections, other Gibbs samplers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallymill.functions.keyed import uniform, uniform_py


def random_projection(vectors: DataFrame, buckets: int, seed: int, key: str = "vec_id", column: str = "embedding") -> DataFrame:
    """(bucket, dim, value): rows summed into buckets with random signs, a k x d summary of n x d."""
    u = uniform("b", seed, 0, F.col(key))
    sign = F.when(uniform("s", seed, 0, F.col(key)) < 0.5, -1.0).otherwise(1.0)
    flat = vectors.select(F.floor(u * buckets).cast("int").alias("bucket"), sign.alias("sign"), F.posexplode(column).alias("dim", "x"))
    return flat.groupBy("bucket", "dim").agg(F.sum(F.col("sign") * F.col("x").cast("double")).alias("value"))


def regression(design: DataFrame, key: str, dim: str, value: str, target: int) -> np.ndarray:
    """Least squares of one dimension on the others from a long design, by normal equations."""
    a = design.select(key, F.col(dim).alias("i"), F.col(value).alias("x"))
    b = a.withColumnsRenamed({"i": "j", "x": "y"})
    gram = a.join(b, key).groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("g")).toPandas()
    d = int(gram.i.max()) + 1
    g = np.zeros((d, d))
    g[gram.i, gram.j] = gram.g
    rest = [k for k in range(d) if k != target]
    return np.linalg.lstsq(g[np.ix_(rest, rest)], g[rest, target], rcond=None)[0]


def weighted_subset(df: DataFrame, size: int, score: str, seed: int, key: str) -> DataFrame:
    """Rows kept by a keyed draw in proportion to score, about size of them, with weight one over
    their chance, so that weighted sums are unbiased."""
    total = df.agg(F.sum(score).alias("total"))
    chance = F.least(F.lit(1.0), F.lit(float(size)) * F.col(score) / F.col("total"))
    every = df.crossJoin(F.broadcast(total)).withColumn("chance", chance)
    return every.where(uniform("tr", seed, 0, F.col(key)) < F.col("chance")).withColumn("weight", 1 / F.col("chance")).drop("total", "chance")


def subset_mh(df: DataFrame, value: str, key: str, fraction: float, steps: int, seed: int, scale: float = 0.1, sd: float = 1.0) -> list[tuple[int, float, bool]]:
    """A Metropolis chain for the mean of normal values, with acceptance from a keyed sample of rows
    at every step, scaled up: (step, mean, accepted)."""
    mean, chain = 0.0, []
    for step in range(steps):
        x = [uniform_py("p", seed, step, j) for j in (1, 2, 3)]
        new = mean + scale * np.sqrt(-2 * np.log(max(x[0], 1e-12))) * np.cos(2 * np.pi * x[1])
        row = df.where(uniform("tr", seed, step, F.col(key)) < fraction)
        v = F.col(value)
        gain = row.agg(F.sum(((v - float(mean)) ** 2 - (v - float(new)) ** 2) / (2 * sd * sd))).first()[0] or 0.0
        took = np.log(max(x[2], 1e-300)) < gain / fraction
        mean = float(new) if took else mean
        chain.append((step, mean, bool(took)))
    return chain


def collapsed_gibbs_small(corpus: DataFrame, topics: int, types: int, alpha: float, beta: float, sweeps: int, seed: int) -> DataFrame:
    """(doc_id, pos, v, z) by collapsed Gibbs: a token leaves its counts before it is redrawn, which
    needs exact counts and one sequence of updates. A reference for small corpora; one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        docs = sorted((r["doc_id"], r["vs"] or []) for b in batches for r in b.to_pylist())
        d = np.concatenate([np.full(len(v), i, int) for i, (_, v) in enumerate(docs)] or [np.empty(0, int)])
        v = np.concatenate([np.array(x, int) for _, x in docs] or [np.empty(0, int)])
        rng = np.random.default_rng(seed)
        z = rng.integers(0, topics, len(v))
        tpd, wpt = np.zeros((len(docs), topics)), np.zeros((types, topics))
        np.add.at(tpd, (d, z), 1)
        np.add.at(wpt, (v, z), 1)
        n = wpt.sum(0)
        for _ in range(sweeps):
            u = rng.random(len(v))
            for t in range(len(v)):
                for m in (tpd[d[t]], wpt[v[t]], n):
                    m[z[t]] -= 1
                w = np.cumsum((tpd[d[t]] + alpha) * (wpt[v[t]] + beta) / (n + types * beta))
                z[t] = min(topics - 1, int(np.searchsorted(w, u[t] * w[-1], "right")))
                for m in (tpd[d[t]], wpt[v[t]], n):
                    m[z[t]] += 1
        pos = np.concatenate([np.arange(len(x)) for _, x in docs] or [np.empty(0, int)])
        ids = np.array([i for i, x in docs for _ in x], np.int64)
        yield pa.record_batch([pa.array(ids), pa.array(pos.astype(np.int32)), pa.array(v.astype(np.int64)), pa.array(z.astype(np.int32))], names=["doc_id", "pos", "v", "z"])

    return corpus.select("doc_id", "vs").coalesce(1).mapInArrow(run, "doc_id long, pos int, v long, z int")
