"""The experiments do their whole job."""

from __future__ import annotations

import inspect

from pyspark.sql import functions as F

from tallymill.functions.text import words
from tallymill.sources.tables import load
from tallymill.workloads import experiments
from tallymill.workloads.queries import QUERIES

SF = "/root/testdata/sf0.001"


def test_microbench_has_every_kind_and_all_words(spark):
    rows = experiments.microbench(spark, SF).collect()
    kinds = {"cm", "cm mean_min", "cm mean_clip", "cm conservative", "independent", "correlated", "conservative"}
    assert {(r.source, r.kind) for r in rows} == {(s, k) for s in ("parts", "users", "words") for k in kinds}
    types = load(spark, SF, "documents").select(F.explode(words(F.col("text")))).distinct().count()
    assert {sum(r["keys"] for r in rows if (r.source, r.kind) == ("words", k)) for k in kinds} == {types}
    # exact cells never underestimate, and the conservative rule errs no more
    bias = {k: sum(r.bias * r["keys"] for r in rows if (r.source, r.kind) == ("words", k)) for k in kinds}
    assert all(r.under == 0 for r in rows if r.kind in ("cm", "cm conservative")) and 0 < bias["cm conservative"] < bias["cm"]


def whole(monkeypatch, spark, name):
    """(topics, sweeps, trials) that a registered query asks of run_grid()."""
    asked, shape = [], inspect.signature(experiments.run_grid)

    def run(*args, **more):
        own = shape.bind(*args, **more)
        own.apply_defaults()
        asked.append(tuple(own.arguments[n] for n in ("topics", "sweeps", "trials")))
        return []

    monkeypatch.setattr(experiments, "run_grid", run)
    out = QUERIES[name](spark, SF)
    return asked, out.columns


def test_exp2_grid_is_whole(spark, monkeypatch):
    assert whole(monkeypatch, spark, "exp2_grid")[0] == [(100, 60, 3)]


def test_heldout_sets_are_whole(spark, monkeypatch):
    asked, columns = whole(monkeypatch, spark, "heldout_sets")
    assert asked == [(100, 60, 3)] * 2 and "trial" in columns


def test_param_sweep_is_whole(spark, monkeypatch):
    assert whole(monkeypatch, spark, "param_sweep")[0] == [(100, 60, 3)]
