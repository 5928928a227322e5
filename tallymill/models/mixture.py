"""Mixtures of categorical components with Dirichlet priors: simulation, blocked Gibbs, stochastic EM."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallymill.functions.keyed import draw, mixed, uniform
from tallymill.models.lda import sketch_vectors, topic_counts
from tallymill.params import SketchParams, smoothed


def gamma(shape: np.ndarray, seed: int, *ids: np.ndarray | int) -> np.ndarray:
    """Keyed Gamma(shape, 1) draws by rejection from a cubed normal; shapes below one are boosted."""
    small = shape < 1
    d = np.where(small, shape + 1, shape) - 1 / 3
    c = 1 / np.sqrt(9 * d)
    out, open_, attempt = np.empty(len(shape)), np.arange(len(shape)), 0
    ids = [np.broadcast_to(np.asarray(x), shape.shape) for x in ids]
    while len(open_):
        own = [x[open_] for x in ids]
        u1, u2, u3 = (mixed(seed, *own, attempt, k) for k in (1, 2, 3))
        x = np.sqrt(-2 * np.log(u1)) * np.cos(2 * np.pi * u2)
        v = (1 + c[open_] * x) ** 3
        ok = (v > 0) & (np.log(u3) < 0.5 * x * x + d[open_] * (1 - v + np.log(np.maximum(v, 1e-300))))
        out[open_[ok]] = d[open_[ok]] * v[ok]
        open_, attempt = open_[~ok], attempt + 1
    return np.where(small, out * mixed(seed, *ids, -1, 4) ** (1 / np.maximum(shape, 1e-12)), out)


def simulate(spark: SparkSession, n: int, components: int, types: int, alpha: float, tau: list[float], seed: int) -> DataFrame:
    """(obs_id, z, x) of the generative model; component distributions are drawn on the fly by key."""
    smoothed(alpha, alpha)
    weights = F.array(*[F.lit(float(t)) for t in tau])

    def thetas(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in b.column("id").to_pylist():
                g = gamma(np.full(types, alpha), seed, k, np.arange(types))
                yield pa.record_batch([pa.array([k], pa.int64()), pa.array([(np.cumsum(g) / g.sum()).tolist()], pa.list_(pa.float64()))], names=["z", "upto"])

    theta = spark.range(components).mapInArrow(thetas, "z long, upto array<double>")
    obs = spark.range(n).select(F.col("id").alias("obs_id"), draw(weights, uniform("z0", seed, 0, F.col("id"))).cast("long").alias("z"))
    upto = F.filter("upto", lambda c: c < uniform("x", seed, 0, F.col("obs_id")))
    return obs.join(theta, "z").select("obs_id", "z", F.least(F.size(upto), F.lit(types - 1)).cast("long").alias("x"))


def initial(df: DataFrame, components: int, seed: int) -> DataFrame:
    """df(obs_id, x) with z from keyed uniforms."""
    return df.select("obs_id", "x", F.floor(uniform("z0", seed, 0, F.col("obs_id")) * components).cast("int").alias("z"))


def _as_tokens(state: DataFrame) -> DataFrame:
    return state.select(F.col("obs_id").alias("doc_id"), F.lit(0).alias("pos"), F.col("x").alias("v"), "z")


def vectors(state: DataFrame, components: int, p: SketchParams | None) -> DataFrame:
    toks = _as_tokens(state)
    return topic_counts(toks, components) if p is None else sketch_vectors(toks, components, p)


def _redrawn(state: DataFrame, probs: DataFrame, tau: list[float], seed: int, sweep: int) -> DataFrame:
    """probs(v, est): unnormalised word probabilities of every component."""
    weights = F.transform(F.sequence(F.lit(0), F.lit(len(tau) - 1)), lambda k: F.get(F.array(*[F.lit(float(t)) for t in tau]), k) * F.get("est", k))
    drawn = draw(weights, uniform("z", seed, sweep, F.col("obs_id"))).cast("int")
    return state.join(probs.withColumnRenamed("v", "x"), "x").select("obs_id", "x", drawn.alias("z"))


def sem_sweep(state: DataFrame, tau: list[float], alpha: float, types: int, seed: int, sweep: int, p: SketchParams | None = None) -> DataFrame:
    """Draws z anew from the smoothed counts of state(obs_id, x, z)."""
    smoothed(alpha, alpha)
    k = len(tau)
    totals = state.groupBy("z").agg(F.count("*").cast("double").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("z", "n"))).alias("t"))
    est = vectors(state, k, p).crossJoin(F.broadcast(totals))
    phi = F.transform("est", lambda e, j: (e + alpha) / (F.coalesce(F.col("t")[j], F.lit(0.0)) + types * alpha))
    return _redrawn(state, est.select("v", phi.alias("est")), tau, seed, sweep)


def gibbs_sweep(state: DataFrame, tau: list[float], alpha: float, seed: int, sweep: int, p: SketchParams | None = None) -> DataFrame:
    """First draws every component from its Dirichlet, as gamma variates keyed by component and
    type that are divided by their sum, then z. Types that are not observed share the rest of a
    component's mass, which no observation asks for."""
    smoothed(alpha, alpha)
    k = len(tau)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            v = b.column("v").to_numpy()
            if not len(v):
                continue
            est = np.array(b.column("est").to_pylist())
            g = gamma((est + alpha).ravel(), seed, sweep, np.tile(np.arange(k), len(v)), np.repeat(v, k)).reshape(len(v), k)
            yield pa.record_batch([b.column("v"), pa.array(g.tolist(), pa.list_(pa.float64()))], names=["v", "g"])

    g = vectors(state, k, p).mapInArrow(run, "v long, g array<double>")
    sums = g.agg(*[F.sum(F.get("g", F.lit(j))).alias(f"s{j}") for j in range(k)])
    theta = g.crossJoin(F.broadcast(sums)).select("v", F.array(*[F.get("g", F.lit(j)) / F.col(f"s{j}") for j in range(k)]).alias("est"))
    return _redrawn(state, theta, tau, seed, sweep)


__all__ = ["gamma", "gibbs_sweep", "initial", "sem_sweep", "simulate", "vectors"]
