from __future__ import annotations

from collections import Counter
from dataclasses import replace

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from tallymill.functions.hashing import hash_col, hash_np
from tallymill.functions.keyed import uniform_py, uniforms_text
from tallymill.operators import cms, combined, trials
from tallymill.params import SketchParams, consistent_sequence
from tallymill.plans import planner
from tallymill.sources.tables import load_cells, save_cells
from tallymill.sqlsurface import register

P = SketchParams(3, 16)
CORR = SketchParams(3, 16, 1.3, 8, counter="correlated")


@pytest.fixture(scope="module")
def stream(spark):
    rng = np.random.default_rng(4)
    rows = [(int(k), int(x), e) for e, (k, x) in enumerate(zip(rng.integers(0, 3, 1500), rng.zipf(1.4, 1500) % 60))]
    return rows, spark.createDataFrame(rows, "k int, key long, event long").repartition(5).cache()


def naive(rows, p, rule="plain", counter="exact"):
    cells = {}
    for k, x, e in sorted(rows, key=lambda r: r[2]):
        m = cells.setdefault(k, np.zeros((p.l, p.w), int))
        at = [int(hash_np(np.array([x]), i, p)[0]) for i in range(p.l)]
        own = np.array([m[i, a] for i, a in enumerate(at)])
        u = np.array([uniform_py("ci", p.seed, e, i) for i in range(p.l)]) if counter == "independent" else np.full(p.l, uniform_py("cc", p.seed, e))
        up = np.ones(p.l, bool) if counter == "exact" else u < p.base ** -own.astype(float)
        if rule == "conservative":
            up &= own == own.min()
        for i, a in enumerate(at):
            m[i, a] += up[i]
    return {(k, i, a): int(v) for k, m in cells.items() for (i, a), v in np.ndenumerate(m) if v}


def collected(df, value):
    return {(r.k, r.i, r.col): r[value] for r in df.collect()}


def test_hash_parity(spark):
    keys = [0, 1, 2**31 - 1, 2**31, 2**40 + 7, 2**60 - 1]
    p = SketchParams(3, 1000, seed=9)
    rows = spark.createDataFrame([(k,) for k in keys], "key long").select("key", *[hash_col("key", i, p).alias(f"h{i}") for i in range(3)], hash_col("key", 0, p, "5").alias("c")).collect()
    for r in rows:
        assert [r.h0, r.h1, r.h2] == [int(hash_np(np.array([r.key]), i, p)[0]) for i in range(3)]
        assert r.c == int(hash_np(np.array([r.key]), 0, p, 5)[0])


def test_plain_and_conservative_cells(stream):
    rows, df = stream
    assert collected(cms.cm_build(df, "key", P, ["k"]), "cell") == naive(rows, P)
    assert collected(cms.cm_build_conservative(df, "key", P, ["event"], ["k"]), "cell") == naive(rows, P, "conservative")


def test_update_merge_and_totals(stream):
    rows, df = stream
    first, rest = df.where("event < 400"), df.where("event >= 400")
    got = cms.cm_update(cms.cm_build(first, "key", P, ["k"]), rest, "key", P, ["k"])
    assert collected(got, "cell") == naive(rows, P)
    totals = {(r.k, r.total) for r in cms.row_totals(got, ["k"]).collect()}
    assert totals == set(Counter(k for k, _, _ in rows).items())


def test_queries(stream, spark):
    rows, df = stream
    true = Counter((k, x) for k, x, _ in rows)
    cells = cms.cm_build(df, "key", P, ["k"])
    keys = df.select("k", "key").distinct().unionByName(spark.createDataFrame([(0, 10**9), (7, 3)], "k int, key long"))
    got = {(r.k, r.key): r.est for r in cms.cm_query(cells, keys, "key", P, ["k"]).collect()}
    assert all(got[k] >= n for k, n in true.items()) and got[7, 3] == 0
    for rule in ("mean_min", "mean_clip"):
        other = {(r.k, r.key): r.est for r in cms.cm_query(cells, keys.where("k < 3"), "key", P, ["k"], rule).collect()}
        assert all(v >= 0 for v in other.values())
        if rule == "mean_min":
            assert all(v <= got[k] for k, v in other.items())
    careful = {(r.k, r.key): r.est for r in cms.cm_query(cms.cm_build_conservative(df, "key", P, ["event"], ["k"]), keys, "key", P, ["k"]).collect()}
    assert all(true[k] <= careful[k] <= got[k] for k in true)


@pytest.mark.parametrize(("counter", "rule"), [("independent", "plain"), ("correlated", "plain"), ("correlated", "conservative")])
def test_combined_cells(stream, counter, rule):
    rows, df = stream
    p = replace(CORR, counter=counter, rule=rule)
    assert collected(combined.build(df, "key", p, ["k"], ["event"]), "state") == naive(rows, p, rule, counter)


def test_only_increments_that_move_a_state_are_shuffled(spark):
    """A pass for several sketches leaves few of many increments, and each sketch is the same from those."""
    rng = np.random.default_rng(8)
    # naive() folds in the order of events, which are texts here
    rows = [(int(k), int(x), f"{e},{e % 7}") for e, (k, x) in enumerate(zip(rng.integers(0, 2, 20000), rng.zipf(1.3, 20000) % 90))]
    df = spark.createDataFrame(rows, "k int, key long, event string").repartition(3)
    kinds = [replace(CORR, counter="independent"), CORR, replace(CORR, rule="conservative"), replace(CORR, l=2), replace(CORR, base=1.1, w=8)]
    kept = combined.moving(df, "key", kinds, ["k"], ["event"]).cache()
    assert kept.columns == ["k", "event", "key"] and kept.count() < len(rows) / 4
    for p in kinds:
        want = naive(rows, p, p.rule, p.counter)
        assert collected(combined.build(kept, "key", p, ["k"], ["event"]), "state") == want
        assert collected(combined.build(df, "key", p, ["k"], ["event"]), "state") == want


def test_draws_of_texts_equal_each_alone():
    ids = [f"{d},{n}" for d in (0, 7, 123456, 10**17) for n in range(0, 1200, 13)] + ["", "é" * 5]
    for texts in (ids, [*ids, "x" * 60]):
        got = uniforms_text("ci|42|", pa.array(texts), ["|0", "|12"])
        assert [g.tolist() for g in got] == [[uniform_py("ci", 42, x, n) for x in texts] for n in (0, 12)]


def test_packing(stream):
    rows, df = stream
    cells = cms.cm_build(df, "key", P, ["k"])
    packed = cms.to_packed(cells, P)
    assert {len(r.payload) for r in packed.collect()} == {P.size_bytes(1)}
    assert collected(cms.from_packed(packed, P), "cell") == naive(rows, P)
    side = cms.topic_vectors(cells, 3).collect()
    want = naive(rows, P)
    assert all(r.states == [want.get((k, r.i, r.col), 0) for k in range(3)] for r in side)


def test_saving_and_pruned_reads(stream, tmp_path, spark):
    rows, df = stream
    save_cells(cms.cm_build(df, "key", P, ["k"]), f"{tmp_path}/s", P)
    cells, p = load_cells(spark, f"{tmp_path}/s")
    assert p == P and {(r.k, r.i, r.col): r.cell for r in cells.collect()} == naive(rows, P)
    some = planner.cells_for(cells, [1, 2], P)
    assert some.count() < cells.count()
    assert "PushedFilters" in some._jdf.queryExecution().toString()


def test_sql_surface(stream, spark):
    rows, df = stream
    cells = cms.cm_build(df, "key", P, ["k"])
    register(spark, replace(CORR, bits=32, counter="exact"), cells)
    got = spark.sql("SELECT k, min(cell) AS est FROM cells JOIN (SELECT 3L AS key, explode(sequence(0, 2)) AS i) q USING (i) WHERE col = cm_col(key, i) GROUP BY k").collect()
    want = {r.k: r.est for r in cms.cm_query(cells, spark.createDataFrame([(k, 3) for k in range(3)], "k int, key long"), "key", P, ["k"]).collect()}
    assert {r.k: r.est for r in got} == want
    cms.to_packed(cells, P).createOrReplaceTempView("packed")
    assert spark.sql("SELECT p.k, s.* FROM packed p, LATERAL sketch_cells(p.payload) s").count() == cells.count()
    assert spark.sql("SELECT counter_read(3) AS r").first().r == pytest.approx(1 + 1.3 + 1.69)


def test_bulk_numpy_builds_agree_with_exact_cells():
    keys, comp, n = np.array([5, 9, 5, 77]), np.array([0, 0, 1, 1]), np.array([3, 2, 4, 1])
    flat = combined.built(n, keys, comp, 2, P, 1).reshape(P.l, P.w, 2)
    for k, c, m in zip(keys, comp, n):
        assert all(flat[i, hash_np(np.array([k]), i, P)[0], c] >= m for i in range(P.l))
    assert flat.sum() == P.l * n.sum()


@pytest.mark.parametrize("rule", ["plain", "conservative"])
def test_bulk_correlated_builds_keep_the_mean_bracket(rule):
    p = SketchParams(3, 8, 1.3, 8, rule, "correlated")
    keys, n = np.arange(12), np.array([40, 20, 13, 10, 8, 7, 6, 5, 4, 3, 2, 1])
    reads = (1.3 ** np.arange(256.0) - 1) / 0.3
    est = []
    for t in range(400):
        own = replace(p, seed=t)
        flat = combined.built(n, keys, np.zeros(12, int), 1, own, t).reshape(p.l, p.w)
        est.append(reads[np.min([flat[i, hash_np(keys, i, own)] for i in range(p.l)], axis=0)])
    est = np.array(est)
    error = 4 * est.std(0) / 20
    assert (est.mean(0) >= n - error).all() and (est.mean(0) <= n + (n.sum() - n) / p.w + error).all()


def test_merged_correlated_sketches_keep_the_lower_bound():
    p = SketchParams(3, 8, 1.3, 8, "plain", "correlated")
    keys, n = np.arange(6), np.array([30, 12, 6, 4, 2, 1])
    reads = (1.3 ** np.arange(256.0) - 1) / 0.3
    est = []
    for t in range(400):
        own = replace(p, seed=t)
        a, b = (combined.built(n, keys, np.zeros(6, int), 1, own, 1000 * j + t) for j in (1, 2))
        flat = combined.joined(a, b, own, t, 0, 1).reshape(p.l, p.w)
        est.append(reads[np.min([flat[i, hash_np(keys, i, own)] for i in range(p.l)], axis=0)])
    est = np.array(est)
    assert (est.mean(0) >= 2 * n - 4 * est.std(0) / 20).all()


def test_brackets_coupling_and_order(spark):
    keys, freq = list(range(10)), [40, 20, 10, 8, 6, 4, 3, 2, 1, 1]
    p = SketchParams(3, 8, 1.3, 32, counter="correlated")
    rows = trials.run_trials(spark, keys, freq, [("corr", p), ("cu", replace(p, rule="conservative")), ("ind", SketchParams(5, 4096, 1.8, 32, counter="independent"))], 200).toPandas()
    for name in ("corr", "cu"):
        own = rows[rows.config == name]
        assert (own.shadow <= own.est + 1e-9).all() and (own.over == 0).all()
        g = own.groupby("key").est
        error, f = 4 * g.std() / np.sqrt(200), np.array(freq)
        assert (g.mean() >= f - error).all() and (g.mean() <= f + (sum(freq) - f) / p.w + error).all()
    ind = rows[rows.config == "ind"].groupby("key").est.mean()
    assert ind[0] < 0.8 * freq[0]


def test_consistency(spark):
    rows = trials.run_trials(spark, [1, 2, 3, 4], [60, 25, 10, 5], [(str(n), p) for n, p in enumerate(consistent_sequence(6, 1.5, 8))], 60).toPandas()
    rows["off"] = abs(rows.est - rows.f) > 0.2 * rows.f
    off = rows.groupby("config").off.mean()
    assert off["5"] < 0.1 < off["0"]


def test_bulk_counters_follow_the_law(spark):
    from pyspark.sql import functions as F

    from tallymill.functions.counters import counter_pmf
    from tallymill.operators import combined
    from tallymill.params import SketchParams

    n, base = 40, 1.5
    law = counter_pmf(n, base)
    for counter in ("independent", "correlated"):
        # many components, each with one key of n increments: as many draws of one counter
        p = SketchParams(1, 64, base, 8, counter=counter)
        rows = spark.range(4000).select(F.col("id").alias("k"), (F.col("id") * 7919).alias("key"), F.lit(n).cast("long").alias("n"))
        got = combined.build_bulk(rows, "key", p, ["k"], "n").groupBy("state").count().collect()
        seen = {r["state"]: r["count"] / 4000 for r in got}
        assert sum(abs(seen.get(s, 0) - q) for s, q in enumerate(law)) < 0.1


def test_bulk_counters_take_a_hot_key_as_one_row(spark):
    from pyspark.sql import functions as F

    from tallymill.operators import cms, combined
    from tallymill.params import SketchParams

    hot = spark.range(90_000).select(F.when(F.col("id") % 3 == 0, F.lit(5)).otherwise(F.col("id") % 1000).alias("key"))
    n = hot.groupBy("key").count()
    for p in (SketchParams(3, 4096), SketchParams(3, 4096, rule="conservative"), SketchParams(3, 4096, 1.02, 16, counter="correlated"), SketchParams(3, 4096, 1.02, 16, counter="correlated", rule="conservative"), SketchParams(3, 4096, 1.0005, 16, counter="independent")):
        cells = combined.build_bulk(hot, "key", p)
        read = cms.cm_query if p.counter == "exact" else combined.query
        got = n.join(read(cells, n.select("key"), "key", p), "key").toPandas()
        if p.counter == "exact":
            assert (got.est >= got["count"]).all()
        assert abs(got.est.sum() / got["count"].sum() - 1) < 0.25 and abs(got.est[got.key == 5].iloc[0] / 30_060 - 1) < 0.6


def test_kernel_draws_afresh(spark):
    from tallymill.operators import trials
    from tallymill.params import SketchParams

    counts = spark.createDataFrame([(0, k, 1 + k % 5) for k in range(200)], "k long, key long, n long")
    got = trials.sketch_kernel(counts, "key", SketchParams(2, 64), 3, ["k"]).toPandas()
    assert len(got) == 600 and (got.est >= got.n).all()
    means = got.groupby("trial").est.sum()
    assert means.nunique() == 3
    same = trials.sketch_kernel(counts, "key", SketchParams(2, 64), 2, ["k"], fresh=False).toPandas()
    assert same.groupby("trial").est.sum().nunique() == 1
