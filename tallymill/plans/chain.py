"""A Markov chain in three phases, and the loop that tunes its sketches."""

from __future__ import annotations

import json
from collections.abc import Callable
from dataclasses import asdict, dataclass
from typing import Any

from pyspark.sql import DataFrame, SparkSession

from tallymill.params import SketchParams
from tallymill.plans.lineage import cut, drop

Rest = DataFrame
Counts = Any


@dataclass(frozen=True)
class SketchedChain:
    """pre and post change the rest of the state given the counts; count makes counts from the rest
    alone; sketch replaces exact counts by what is read from a sketch of them."""

    count: Callable[[Rest, int], Counts]
    post: Callable[[Counts, Rest, int], Rest]
    pre: Callable[[Counts, Rest, int], Rest] = lambda counts, rest, sweep: rest
    sketch: Callable[[Counts, int], Counts] = lambda counts, sweep: counts

    def run(self, rest: Rest, sweeps: int, first: int = 1) -> Rest:
        """Every sweep is written out, so a lost executor costs one sweep at most."""
        counts, former = self.sketch(self.count(rest, first - 1), first - 1), None
        for sweep in range(first, first + sweeps):
            rest = self.pre(counts, rest, sweep)
            counts = self.sketch(self.count(rest, sweep), sweep)
            rest = cut(self.post(counts, rest, sweep), "chain")
            if former is not None:
                drop(former)
            former = rest
        return rest


def save_manifest(spark: SparkSession, path: str, sweep: int, seed: int, params: SketchParams | None) -> None:
    """What a restart needs beside the last sweep's rows."""
    body = json.dumps({"sweep": sweep, "seed": seed, "params": asdict(params) if params else None})
    spark.createDataFrame([(body,)], "value string").coalesce(1).write.mode("overwrite").text(path)


def load_manifest(spark: SparkSession, path: str) -> dict:
    body = json.loads(spark.read.text(path).first()[0])
    return body | {"params": SketchParams(**body["params"]) if body["params"] else None}


def tune(fit: Callable[[SketchParams], Any], evaluate: Callable[[Any], float], sequence: list[SketchParams], tolerance: float, components: int, budget: int | None = None) -> list[tuple[SketchParams, float]]:
    """Walks a sequence of ever finer parameters from the cheapest, until the measure (less is
    better) improves by less than tolerance, relatively, or the next sketch exceeds the budget."""
    tried: list[tuple[SketchParams, float]] = []
    for p in sequence:
        if budget is not None and p.size_bytes(components) > budget:
            break
        tried.append((p, evaluate(fit(p))))
        if len(tried) > 1 and tried[-2][1] - tried[-1][1] < tolerance * abs(tried[-2][1]):
            break
    return tried
