"""Repeated small sketches with fresh randomness: moments, brackets, consistency, coupling."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallymill.functions.counters import reads, thresholds
from tallymill.functions.hashing import hash_np
from tallymill.operators import cms, combined
from tallymill.params import SketchParams


def simulate(keys: np.ndarray, freq: np.ndarray, p: SketchParams, trial: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(estimates, shadow reads, conservative states less plain states at most) of one trial over a
    stream of the keys in random order. The shadow of a key counts only its own increments, by
    the same draws; independent counters have none."""
    rng = np.random.default_rng([p.seed, trial])
    own = replace(p, seed=p.seed + 7919 * trial)
    stream = rng.permutation(np.repeat(np.arange(len(keys)), freq))
    at = np.stack([hash_np(keys, i, own) for i in range(p.l)], 1)
    rows = np.arange(p.l)
    cells, plain, shadow = np.zeros((p.l, p.w), np.int64), np.zeros((p.l, p.w), np.int64), np.zeros(len(keys), np.int64)
    exact = p.counter == "exact"
    if exact:
        thr, table = np.ones(len(stream) + 1), np.arange(len(stream) + 1.0)
    else:
        cap = min(4095, int(690 / np.log(p.base)))
        thr, table = np.array(thresholds(p.base, cap)), np.array(reads(p.base, cap))
    for x in stream:
        u = rng.random(p.l) if p.counter == "independent" else np.full(p.l, rng.random())
        mine = cells[rows, at[x]]
        up = u < thr[mine]
        if p.rule == "conservative":
            up &= mine == mine.min()
            also = plain[rows, at[x]]
            plain[rows, at[x]] = also + (u < thr[also])
        cells[rows, at[x]] = mine + up
        shadow[x] += u[0] < thr[shadow[x]]
    least = np.min(cells[rows[:, None], at.T], axis=0)
    over = int((cells > plain).sum()) if p.rule == "conservative" else 0
    return table[least], table[shadow], np.array([over])


def jumped(keys: np.ndarray, freq: np.ndarray, p: SketchParams, trial: int) -> np.ndarray:
    """Estimates of one trial whose counts are added a key at a time, in random order, so that its time
    does not grow with the frequencies."""
    own = replace(p, seed=p.seed + 7919 * trial)
    order = np.random.default_rng([p.seed, trial]).permutation(len(keys))
    cells = combined.built(freq[order], keys[order], np.zeros(len(keys), np.int64), 1, own, own.seed).reshape(p.l, p.w)
    least = np.min([cells[i, hash_np(keys, i, own)] for i in range(p.l)], axis=0).astype(float)
    return least if p.counter == "exact" else (p.base**least - 1) / (p.base - 1)


def run_trials(spark: SparkSession, keys: list[int], freq: list[int], configs: list[tuple[str, SketchParams]], trials: int, bulk: bool = False) -> DataFrame:
    """(config, trial, key, f, est, shadow, over) of every trial, trials as tasks. Increments come one
    at a time; with bulk, a key's all at once, and shadow and over, which compare single draws, are null."""
    k, f = np.array(keys, np.int64), np.array(freq, np.int64)

    def run(batches):
        import pandas as pd

        for pdf in batches:
            for i in pdf.id:
                name, p = configs[i % len(configs)]
                trial = int(i // len(configs))
                est, shadow, over = (jumped(k, f, p, trial), None, [None]) if bulk else simulate(k, f, p, trial)
                yield pd.DataFrame({"config": name, "trial": trial, "key": k, "f": f, "est": est, "shadow": shadow, "over": over[0]})

    n = len(configs) * trials
    return spark.range(0, n, 1, max(1, min(n, 64))).mapInPandas(run, "config string, trial long, key long, f long, est double, shadow double, over long")


def sketch_kernel(counts: DataFrame, key: str, p: SketchParams, trials: int, group: Sequence[str] = (), fresh: bool = True) -> DataFrame:
    """(trial, group..., key, n, est): the estimates that replace counts(group..., key, n), trial by trial.
    With fresh, a trial draws hash functions and counters of its own, as the kernel of the theory
    does; else all trials share them, as samplers do in practice. The counts may be random
    themselves: a column `trial` of theirs keeps each trial to its own rows."""
    out = None
    for t in range(trials):
        own = replace(p, seed=p.seed + 7919 * t) if fresh else p
        rows = (counts.where(F.col("trial") == t).drop("trial") if "trial" in counts.columns else counts).select(*group, key, "n")
        cells = combined.build_bulk(rows, key, own, group, "n")
        read = cms.cm_query if p.counter == "exact" else combined.query
        est = read(cells, rows.select(*group, key), key, own, list(group)).select(*group, key, F.col("est").cast("double").alias("est"))
        done = rows.join(est, [*group, key]).select(F.lit(t).alias("trial"), *group, key, "n", "est")
        out = done if out is None else out.unionByName(done)
    return out
