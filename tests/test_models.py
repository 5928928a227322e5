from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from tallymill import evaluation
from tallymill.models import dag, hmm, lda, mixture
from tallymill.operators import alternatives, stationary
from tallymill.operators.matrix import Blocks, Counters, Dense, RowSketches, WholeMatrix, sparse, sparse_lookup
from tallymill.params import SketchParams, consistent_sequence
from tallymill.plans import planner
from tallymill.plans.chain import SketchedChain, load_manifest, save_manifest, tune

TYPES = 60


@pytest.fixture(scope="module")
def corpus(spark):
    rng = np.random.default_rng(1)
    rows = [(d, [int(x) for x in rng.integers(0, 20, 40) + 20 * (d % 3)]) for d in range(60)]
    return spark.createDataFrame([*rows, (900, []), (901, [7])], "doc_id long, vs array<long>").repartition(3).cache()


@pytest.fixture(scope="module")
def toks(corpus):
    return corpus.select("doc_id", F.posexplode("vs").alias("pos", "v")).cache()


def assigned(fit):
    return {(r.doc_id, k): z for r in fit.docs.collect() for k, z in enumerate(r.zs)}


def test_packed_and_joined_sweeps_agree(corpus, toks):
    fit = lda.sem_lda(corpus, Dense(TYPES, 3), TYPES, sweeps=2, stream="md5", seed=7)
    z = lda.token_start(toks, 3, 7)
    for n in (1, 2):
        z = lda.joined_sweep(z, lda.topic_counts(z, 3), 3, 0.1, 0.1, TYPES, 7, n).cache()
    assert assigned(fit) == {(r.doc_id, r.pos): r.z for r in z.collect()}
    assert fit.topics.totals.sum() == 60 * 40 + 1


def test_partitions_do_not_matter(corpus):
    runs = [assigned(lda.sem_lda(corpus.repartition(n), Dense(TYPES, 3), TYPES, sweeps=2)) for n in (1, 4)]
    assert runs[0] == runs[1]


def test_wide_sketch_gives_the_dense_assignments(corpus):
    dense = assigned(lda.sem_lda(corpus, Dense(TYPES, 3), TYPES, sweeps=2))
    wide = assigned(lda.sem_lda(corpus, RowSketches(SketchParams(3, 1 << 16), 3), TYPES, sweeps=2))
    assert dense == wide


@pytest.mark.parametrize(
    "matrix",
    [
        Dense(TYPES, 3),
        Counters(TYPES, 3),
        RowSketches(SketchParams(3, 32), 3),
        RowSketches(SketchParams(3, 32, hash_scope="per_component"), 3),
        RowSketches(SketchParams(3, 32, 1.08, 8, counter="independent"), 3),
        RowSketches(SketchParams(3, 32, 1.08, 8, counter="correlated"), 3),
        RowSketches(SketchParams(3, 32, 1.08, 8, "conservative", "correlated"), 3),
        WholeMatrix(SketchParams(3, 128), 3),
        Blocks(SketchParams(3, 16), 3, 2),
    ],
    ids=lambda m: f"{type(m).__name__}-{getattr(getattr(m, 'params', None), 'counter', '')}-{getattr(getattr(m, 'params', None), 'rule', '')}",
)
def test_representations_learn(corpus, matrix):
    fit = lda.sem_lda(corpus, matrix, TYPES, sweeps=12, held_out=corpus)
    assert fit.log[-1]["perplexity"] < 0.85 * fit.log[0]["perplexity"]
    assert len(fit.topics.flat.tobytes()) == matrix.size_bytes()


def test_sketched_documents_and_refusals(corpus):
    m = Dense(TYPES, 64)
    fit = lda.sem_lda(corpus, m, TYPES, sweeps=1, tpd=SketchParams(2, 16, 1.05, 8, counter="independent"))
    assert fit.topics.totals.sum() == 2401
    with pytest.raises(ValueError):
        lda.sem_lda(corpus, Dense(TYPES, 2), TYPES, tpd=SketchParams(3, 64))
    with pytest.raises(ValueError):
        lda.sem_lda(corpus, m, TYPES, budget=10)
    with pytest.raises(ValueError):
        lda.sem_lda(corpus, m, TYPES, alpha=0)


def test_early_stop(corpus):
    fit = lda.sem_lda(corpus, Dense(TYPES, 1), TYPES, sweeps=30, held_out=corpus, tolerance=0.01)
    assert len(fit.log) < 10


def test_planner():
    assert isinstance(planner.choose_counts(1000, 10, 1 << 20), Dense)
    big = planner.choose_counts(10**7, 100, 1 << 20)
    assert isinstance(big, RowSketches) and big.size_bytes() <= 1 << 20
    assert planner.choose_lookup(big) == "broadcast" and planner.choose_lookup(big, 10) == "join"
    assert [len(b) for b in planner.component_blocks(10, 100, 400)] == [4, 4, 2]


def test_mixture(spark):
    sim = mixture.simulate(spark, 3000, 3, 12, 0.1, [0.5, 0.3, 0.2], 5)
    share = {r.z: r["count"] / 3000 for r in sim.groupBy("z").count().collect()}
    assert share[0] == pytest.approx(0.5, abs=0.05)
    obs = sim.select("obs_id", "x").cache()
    z = mixture.initial(obs, 3, 5).cache()
    for n in (1, 2):
        z = mixture.sem_sweep(z, [0.5, 0.3, 0.2], 0.1, 12, 5, n).cache()
        assert z.count() == 3000
    g = mixture.gibbs_sweep(z, [0.5, 0.3, 0.2], 0.1, 5, 3, SketchParams(2, 16, 1.05, 8, counter="correlated"))
    assert g.count() == 3000 and g.columns == ["obs_id", "x", "z"]
    shape = np.repeat([0.3, 1.0, 7.0], 20_000)
    draws = mixture.gamma(shape, 3, np.arange(60_000)).reshape(3, -1)
    assert draws.mean(1) == pytest.approx([0.3, 1, 7], rel=0.05) and draws.var(1) == pytest.approx([0.3, 1, 7], rel=0.1)


def test_hierarchy(spark, toks):
    paths = dag.paths(spark, [("root", "a"), ("root", "b"), ("a", "x"), ("a", "y"), ("b", "y")], "root").collect()
    assert [r.nodes for r in sorted(paths, key=lambda r: r.path)] == [["root", "a", "x"], ["root", "a", "y"], ["root", "b", "y"]]
    z = dag.initial(toks, 2, 3, 1).cache()
    for draws in (False, True):
        out = dag.sweep(z, 2, 3, 0.1, 0.1, 0.1, TYPES, 1, 1, SketchParams(2, 64), draws).cache()
        assert out.count() == 2401 and out.where("z < 0 OR z > 5").count() == 0


def test_paths_of_any_depth(spark, toks):
    z = dag.initial(toks, 2, 3, 1).cache()
    two = [["r", s, t] for s in "ab" for t in "xyz"]
    for p in (None, SketchParams(2, 64)):
        a = dag.sweep(z, 2, 3, 0.1, 0.1, 0.1, TYPES, 1, 1, p)
        b = dag.path_sweep(z, two, 0.1, 0.1, TYPES, 1, 1, p)
        assert a.exceptAll(b).count() == 0 and a.count() == b.count() == 2401
    # paths of two lengths that share nodes, weights from the rule alone
    ways = [["r", "a", "x"], ["r", "a", "y", "x"], ["r", "b", "y", "x"], ["r", "b", "y", "w"]]
    own = spark.createDataFrame([(1, [3.0, 1.0, 2.0, 0.0])], "doc_id long, joint array<double>")
    got = dag._edge_weights(own, ways, 0.5).first().pw
    yx, yw = 3.5 / 4, 0.5 / 4
    assert got == pytest.approx([4.5 * (3.5 / 5), 4.5 * (1.5 / 5) * yx, 2.5 * (2.5 / 2.5) * yx, 2.5 * yw])
    assert dag.path_sweep(dag.initial(toks, 4, 1, 1), ways, 0.1, 0.1, TYPES, 1, 1).count() == 2401
    with pytest.raises(ValueError):
        dag.path_sweep(z, [["r"]], 0.1, 0.1, TYPES, 1, 1)


def test_hidden_states(spark):
    rng = np.random.default_rng(0)
    rows = []
    for s in range(60):
        z, xs = 0, []
        for _ in range(50):
            z = z if rng.random() < 0.9 else 1 - z
            xs.append(int(rng.integers(0, 3) + 3 * z))
        rows.append((s, xs))
    seqs = spark.createDataFrame([*rows, (99, [])], "seq_id long, xs array<long>")
    done, log = hmm.gibbs(seqs, RowSketches(SketchParams(2, 32), 2), 6, sweeps=12)
    assert log[-1] > log[1] and done.count() == 60
    x = np.array([0, 1, 0])
    start, move, emit = np.array([0.6, 0.4]), np.array([[0.7, 0.3], [0.2, 0.8]]), np.array([[0.9, 0.2], [0.1, 0.8]])[x]
    total = sum(start[a] * emit[0, a] * move[a, b] * emit[1, b] * move[b, c] * emit[2, c] for a in (0, 1) for b in (0, 1) for c in (0, 1))
    assert hmm.filter_sample(x, start, move, emit, rng.random(3))[1] == pytest.approx(np.log(total))


def test_stationary_laws():
    x = [0, 1, 0, 2]
    z, law = stationary.stationary_exact(x, 2, 3, 0.5)
    assert law.sum() == pytest.approx(1) and (law > 0).all()
    # symmetric under exchange of the components
    flipped = {tuple(1 - s): p for s, p in zip(z, law)}
    assert all(flipped[tuple(s)] == pytest.approx(p) for s, p in zip(z, law))
    tv = [0.5 * np.abs(stationary.stationary_sketched(x, 2, 3, 0.5, p, 150) - law).sum() for p in consistent_sequence(5, 2.0, 2, 2)]
    assert tv[-1] < 0.3 * tv[0]


def test_chain_in_phases(spark):
    obs = spark.createDataFrame([(k, k % 3) for k in range(60)], "obs_id long, x long")
    tau = [0.5, 0.5]
    chain = SketchedChain(count=lambda rest, s: rest, post=lambda c, rest, s: mixture.sem_sweep(c, tau, 0.5, 3, 9, s))
    got = chain.run(mixture.initial(obs, 2, 9), 2)
    want = mixture.sem_sweep(mixture.sem_sweep(mixture.initial(obs, 2, 9), tau, 0.5, 3, 9, 1).cache(), tau, 0.5, 3, 9, 2)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_tuning_and_manifest(spark, tmp_path):
    seq = consistent_sequence(6)
    tried = tune(lambda p: p.w, lambda w: 100 + 64 / w, seq, 0.01, 10)
    assert len(tried) == 4 and tune(lambda p: p, lambda p: 1.0, seq, 0.01, 10, budget=1) == []
    save_manifest(spark, f"{tmp_path}/m", 3, 42, seq[0])
    assert load_manifest(spark, f"{tmp_path}/m") == {"sweep": 3, "seed": 42, "params": seq[0]}


def test_alternatives(spark, corpus):
    z = alternatives.collapsed_gibbs_small(corpus, 3, TYPES, 0.1, 0.1, 20, 1)
    main = z.groupBy("doc_id", "z").count().groupBy("doc_id").agg(F.max_by("z", "count").alias("z")).where("doc_id < 900").withColumn("t", F.pmod("doc_id", F.lit(3)))
    assert evaluation.purity(main, "z", "t").first().purity > 0.6
    rows = spark.range(4000).select("id", (F.col("id") % 10 + 1).cast("double").alias("s"))
    sub = alternatives.weighted_subset(rows, 500, "s", 3, "id")
    assert sub.agg(F.sum("weight")).first()[0] == pytest.approx(4000, rel=0.15)
    chain = alternatives.subset_mh(rows.select("id", F.lit(2.0).alias("v")), "v", "id", 0.2, 25, 1, scale=0.5)
    assert chain[-1][1] == pytest.approx(2, abs=0.3)
    vec = spark.createDataFrame([(k, [float(k), float(2 * k + 1), 1.0]) for k in range(50)], "vec_id long, embedding array<double>")
    proj = alternatives.random_projection(vec, 16, 4)
    assert alternatives.regression(proj, "bucket", "dim", "value", 1) == pytest.approx([2, 1], abs=1e-6)


def test_measures(spark, corpus):
    inc = spark.createDataFrame([(0, 5), (0, 5), (1, 5), (1, 6)], "k int, key long")
    counts = sparse(inc)
    got = {(r.k, r.v): r.est for r in sparse_lookup(counts, spark.createDataFrame([(0, 5), (0, 6)], "k int, v long")).collect()}
    assert got == {(0, 5): 2, (0, 6): 0}
    pure = evaluation.purity(spark.createDataFrame([(0, "a"), (0, "a"), (1, "b")], "z int, t string"), "z", "t").first()
    assert pure.purity == 1 and pure.nmi == pytest.approx(1)
    log = spark.createDataFrame([("dense", 0, 0, 10.0), ("dense", 0, 1, 8.0), ("cm", 0, 0, 12.0), ("cm", 0, 1, 8.0)], "config string, trial int, sweep int, perplexity double")
    gap = {r.config: (r.gap_first, r.gap_last) for r in evaluation.gaps(log, "dense").collect()}
    assert gap["cm"] == (1.2, 1.0)
    flat = Dense(TYPES, 2).build(np.array([5, 3]), np.array([1, 2]), np.array([0, 1]), 0)
    topics = lda.Topics(Dense(TYPES, 2), flat, np.array([5, 3]), 0.1, TYPES)
    assert topics.phi(np.arange(TYPES)).sum(0) == pytest.approx([1, 1])
    assert evaluation.perplexity(corpus.where("doc_id >= 900"), topics, 0.1)["tokens"] == 0


def test_chains_together_equal_each_alone(corpus):
    """A pass that serves all chains gives each the log that it has on its own."""
    whole, held = corpus.repartition(1).cache(), corpus.where("doc_id % 7 = 0")
    odd = SketchParams(3, 16, 1.08, 8, counter="correlated", rule="conservative")
    chains = [(Dense(TYPES, 3), 42), (RowSketches(SketchParams(2, 16), 3), 42), (RowSketches(odd, 3), 43)]
    together = lda.sem_chains(whole, chains, TYPES, sweeps=2, held_out={"own": held})
    for (matrix, seed), log in zip(chains, together):
        alone = lda.sem_lda(whole, matrix, TYPES, sweeps=2, seed=seed, held_out=held).log
        for a, b in zip(alone, log, strict=True):
            assert (a["sweep"], a["tokens"], a["bytes"]) == (b["sweep"], b["tokens"], b["bytes"])
            assert abs(a["perplexity"] / b["perplexity"] - 1) < 1e-9, (matrix, a, b)


def test_sweeps_write_packed_documents(spark, corpus, monkeypatch):
    """lda_perplexity: a sweep writes a few rows, of 4 bytes a word; tallies too large for arrays give the same logs."""
    whole = corpus.repartition(1).cache()
    chains = [(Dense(TYPES, 3), 42), (RowSketches(SketchParams(2, 16, 1.08, 8, counter="independent"), 3), 42)]
    rows = lda.chains_pass(whole, chains, TYPES, 0.1, 0, None).where("block IS NULL").collect()
    assert len(rows) == 1 and len(rows[0].vs) == 4 * 2401 and len(rows[0].ns) == 4 * 62 * 2 * 3

    def told():
        return [[(r["perplexity"], r["tokens"], r["moved"]) for r in log] for log in lda.sem_chains(whole, chains, TYPES, sweeps=2, held_out={"own": whole})]

    arrays = told()
    monkeypatch.setattr(lda, "TALLIES", 0)
    assert told() == arrays


def test_scores_of_documents_together_equal_each_alone(spark, monkeypatch):
    """Documents of similar length are scored together, padded; the score is that of a loop over them."""
    rng = np.random.default_rng(3)
    texts = [rng.integers(0, TYPES, n).tolist() for n in (0, 1, 2, 3, 3, 5, 8, 9, 40, 41, 150, 700)]
    held = spark.createDataFrame([*enumerate(texts), (99, None)], "doc_id long, vs array<long>")
    flat = rng.integers(0, 50, TYPES * 3).astype(np.int32)
    topics = lda.Topics(Dense(TYPES, 3), flat, flat.reshape(-1, 3).sum(0), 0.1, TYPES)
    phi, loss, n = topics.normalised().phi(np.arange(TYPES)), 0.0, 0
    for vs in texts:
        if len(vs) > 1:
            first, theta = phi[vs[: len(vs) // 2]], np.full(3, 1 / 3)
            for _ in range(evaluation.FOLD_IN):
                theta = 0.1 + theta * ((1 / (first @ theta)) @ first)
                theta /= theta.sum()
            loss, n = loss - np.log(phi[vs[len(vs) // 2 :]] @ theta).sum(), n + len(vs) - len(vs) // 2
    assert [len(g) for g in evaluation._alike(np.array([0, 4, 1, 4, 3]))] == [3, 1]
    for most in (1, 16, 1 << 14):
        monkeypatch.setattr(evaluation, "_TOGETHER", most)
        got = evaluation.perplexity(held, topics, 0.1)
        assert got["tokens"] == n and got["perplexity"] == pytest.approx(np.exp(loss / n), rel=1e-12)


def test_row_counts_equal_token_counts(spark):
    from tallymill.sources import corpus as src

    docs = spark.createDataFrame([(1, "a b a", "x"), (2, None, "x"), (3, "b, É c", None), (4, "...", "y"), (5, "c A", "y")], "doc_id long, text string, lang string")
    toks = src.tokens(docs)
    got = src.row_counts(docs)
    assert sorted(got.groupBy("w").agg({"df": "sum", "n": "sum"}).collect()) == sorted(src.vocabulary(toks).collect())
    assert {r[0] for r in src.commonest(got, 1).collect()} == {r[0] for r in src.stop_words(toks, docs.select("doc_id", "lang"), 1).collect()}
    vocab = src.numbered(src.vocabulary(toks))
    known = spark.sparkContext.broadcast([r[0] for r in vocab.orderBy("v").select("w").collect()])
    assert src.one_row_each(docs) and not src.one_row_each(docs.union(docs.limit(1)))
    assert sorted(src.looked_up(docs, known).collect()) == sorted(src.documents(toks, vocab).collect())


def test_written_tables_leave_no_shuffle_files(spark):
    from tallymill.plans.lineage import cut

    def left():
        files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
        return {f for f in files.mkString("\n").split("\n") if "shuffle_" in f}

    before = left()
    cut(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count())
    assert left() <= before


def test_uniforms_of_documents_equal_each_alone():
    from tallymill.functions.keyed import uniform_py, uniforms_np

    docs, sizes = np.array([0, 7, -3, 123456, 2**62]), np.array([3, 0, 12, 1100, 101])
    for seed in (42, 10**40):
        want = [uniform_py("z", seed, 3, d, p) for d, n in zip(docs.tolist(), sizes.tolist()) for p in range(n)]
        assert uniforms_np(docs, sizes, "z", seed, 3).tolist() == want


def test_document_rows_equal_joins(spark, monkeypatch):
    """lda_lang_purity sweeps document rows: topics by document as joins give them, with ids that repeat too."""
    from tallymill.sources import corpus as src
    from tallymill.workloads import queries

    texts = [(k, " ".join(f"w{(k * j) % 11}" for j in range(k))) for k in range(1, 30)] + [(40, None), (41, "..."), (42, "É w1 " * 120)]
    monkeypatch.setattr(src.parts_of, "__defaults__", ("vs", 4, 64))
    for rows, joined in ((texts, 0), ([*texts, (3, "w1 w2")], 1)):
        own, calls = spark.createDataFrame(rows, "doc_id long, text string").withColumn("lang", F.lit("x")), []
        monkeypatch.setattr(queries, "load", lambda *_, own=own: own)
        want, swept = sorted(queries._by_doc(queries._swept(spark, "", 3)).collect()), queries._swept
        with monkeypatch.context() as m:
            m.setattr(queries, "_swept", lambda *a, swept=swept, calls=calls: calls.append(1) or swept(*a))
            assert sorted(queries._exact_by_doc(spark, "", 3).collect()) == want
        assert len(calls) == joined
