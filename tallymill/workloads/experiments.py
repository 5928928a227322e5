"""The experiments: perplexity, time and size of dense and sketched topic models, and key errors."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallymill import evaluation
from tallymill.models import lda
from tallymill.operators import cms, combined
from tallymill.operators.matrix import CountMatrix, Counters, Dense, RowSketches
from tallymill.params import SketchParams
from tallymill.plans.lineage import cut, drop, modest
from tallymill.sources import corpus
from tallymill.sources.tables import load

#: Bytes of the representations that a pass sweeps together; each worker reads them all.
GROUP_BYTES = 128 << 20
RULES = {"independent": ("independent", "plain"), "correlated": ("correlated", "plain"), "conservative": ("correlated", "conservative")}


@dataclass
class Corpus:
    train: DataFrame
    sets: dict[str, DataFrame]
    types: int
    vocab: DataFrame
    #: train, packed as sem_chains() takes it, where documents have a row each.
    packed: DataFrame | None = None

    @property
    def held(self) -> DataFrame:
        return next(iter(self.sets.values()))


def prepare(spark: SparkSession, sf_dir: str, least_df: int = 3, held: str | tuple[str, ...] = "in_corpus", stop: int = 10) -> Corpus:
    """Training documents and held-out sets: in_corpus, conversations, pages, benchmark.
    With 'benchmark', training documents that hold an item's text are left out first."""
    modest(spark)
    docs = load(spark, sf_dir, "documents")
    names = (held,) if isinstance(held, str) else held
    train = corpus.training(docs)
    if "benchmark" in names:
        # a document holds an item if it has its first eight words in a row
        first = corpus.benchmark(spark, sf_dir).select(F.array_join(F.slice(F.split("text", r"\s+"), 1, 8), " ").alias("head"))
        grams = F.explode(F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("ws") - 7)), lambda k: F.array_join(F.slice("ws", k, 8), " "))).alias("head")
        hit = train.select("doc_id", F.split("text", r"\s+").alias("ws")).select("doc_id", grams).join(first, "head", "left_semi").select("doc_id").distinct()
        train = train.join(cut(hit, "hit"), "doc_id", "left_anti")
    single = corpus.one_row_each(docs)
    if single:
        coded = cut(corpus.coded(train), "coded", **lda.SMALL)
        freq = cut(corpus.counted(coded), "frequencies")
        stops = corpus.commonest(freq, stop) if stop else None
        counted = freq.groupBy("w").agg(F.sum("df").alias("df"), F.sum("n").alias("tf"))
    else:
        toks = corpus.tokens(train)
        stops = corpus.stop_words(toks, docs.select("doc_id", "lang"), stop) if stop else None
        counted = corpus.vocabulary(toks)
    vocab = cut(corpus.numbered(corpus.filtered(counted, least_df, stops)), "vocabulary")
    types = vocab.count()
    known = spark.sparkContext.broadcast(vocab.select("v", "w").toArrow().sort_by("v").column("w").to_pylist()) if types <= corpus.HELD_WORDS else None

    def rows(texts: DataFrame, one_each: bool) -> DataFrame:
        return corpus.looked_up(texts, known) if one_each and known is not None else corpus.documents(corpus.tokens(texts), vocab)

    makers = {"in_corpus": corpus.held_out, "conversations": lambda _: corpus.conversations(spark, sf_dir), "pages": lambda _: corpus.pages(spark, sf_dir), "benchmark": lambda _: corpus.benchmark(spark, sf_dir)}
    texts = {n: makers[n](docs) for n in names}
    sets = {n: cut(rows(t, single if n == "in_corpus" else corpus.one_row_each(t)), "held") for n, t in texts.items()}
    if single and known is not None:
        packed = cut(corpus.placed(coded, known), "train", **lda.SMALL)
        drop(coded)
        known.destroy()
        return Corpus(corpus.unpacked(packed), sets, types, vocab, packed)
    return Corpus(cut(rows(train, single), "train"), sets, types, vocab)


def widths(types: int) -> list[int]:
    """log2 of w at about 0.12, 0.23 and 0.47 columns a word type, the ratios of the full-size experiment."""
    top = max(5, round(0.467 * types).bit_length() - (0.467 * types < 0.75 * (1 << round(0.467 * types).bit_length())))
    return [top - 2, top - 1, top]


def grid1(types: int, topics: int, rows: tuple[int, ...] = (3, 4, 5), logs: list[int] | None = None) -> dict[str, CountMatrix]:
    """Dense, and count-min of 4-byte cells by hash rows and range."""
    out: dict[str, CountMatrix] = {"dense": Dense(types, topics)}
    for n in rows:
        for b in logs or widths(types):
            out[f"cm/{n}/{b}"] = RowSketches(SketchParams(n, 1 << b), topics)
    return out


def grid2(types: int, topics: int, logs: list[int] | None = None, base: float = 1.08) -> dict[str, CountMatrix]:
    """Dense, and one-byte combined sketches of three hash rows under three rules."""
    out: dict[str, CountMatrix] = {"dense": Dense(types, topics)}
    for name, (counter, rule) in RULES.items():
        for b in logs or widths(types):
            out[f"{name}/3/{b}"] = RowSketches(SketchParams(3, 1 << b, base, 8, counter=counter, rule=rule), topics)
    return out


def quick_grid():
    return lambda types, topics: {k: v for k, v in grid2(types, topics).items() if k == "dense" or k.endswith(str(widths(types)[1]))}


def run_grid(
    spark: SparkSession,
    sf_dir: str,
    grid,
    topics: int = 100,
    sweeps: int = 60,
    trials: int = 3,
    held: str | tuple[str, ...] = "in_corpus",
    alpha: float = 0.1,
    beta: float = 0.1,
    normaliser: str = "mass",
    least_df: int = 3,
    every: int = 1,
) -> list[dict]:
    """A log row for every config, trial, sweep that is told and held-out set. Trials of all configs share starts
    and draws. Chains are swept together as far as their representations add up to GROUP_BYTES, see sem_chains."""
    c = prepare(spark, sf_dir, least_df, held)
    groups: list[list] = []
    for chain in ((name, matrix, t) for name, matrix in grid(c.types, topics).items() for t in range(trials)):
        if not groups or sum(m.size_bytes() for _, m, _ in [*groups[-1], chain]) > GROUP_BYTES:
            groups.append([])
        groups[-1].append(chain)
    out = []
    for group in groups:
        logs = lda.sem_chains(c.train if c.packed is None else c.packed, [(m, 42 + t) for _, m, t in group], c.types, alpha, beta, sweeps, c.sets, normaliser, every)
        out += [{"config": name, "trial": t, **r} for (name, _, t), log in zip(group, logs) for r in log]
    return out


def exp1(spark: SparkSession, sf_dir: str, topics: int = 100, sweeps: int = 60, trials: int = 3, **more) -> list[dict]:
    return run_grid(spark, sf_dir, grid1, topics, sweeps, trials, **more)


def exp2(spark: SparkSession, sf_dir: str, topics: int = 100, sweeps: int = 60, trials: int = 3, **more) -> list[dict]:
    return run_grid(spark, sf_dir, grid2, topics, sweeps, trials, **more)


def param_sweep(spark: SparkSession, sf_dir: str, topics: int = 100, sweeps: int = 60, trials: int = 3) -> list[dict]:
    """Bases, cell widths and hash rows; counters without hashing."""

    def grid(types: int, k: int) -> dict[str, CountMatrix]:
        w = 1 << widths(types)[1]
        out: dict[str, CountMatrix] = {"dense": Dense(types, k), "counters": Counters(types, k)}
        out |= {f"base/{b}": RowSketches(SketchParams(3, w, b, 8, counter="independent"), k) for b in (1.02, 1.08, 1.2, 1.5, 2.0)}
        out |= {f"bits/{s}": RowSketches(SketchParams(3, w, b, s, counter="independent"), k) for s, b in ((8, 1.08), (16, 1.0005))}
        return out | {f"rows/{n}": RowSketches(SketchParams(n, w), k) for n in range(1, 6)}

    return run_grid(spark, sf_dir, grid, topics, sweeps, trials)


def grid_frame(spark: SparkSession, log: list[dict]) -> DataFrame:
    told = [r for r in log if "perplexity" in r]
    rows = [(r["config"], r["trial"], r["sweep"], float(r["perplexity"]), int(r["tokens"]), float(r["seconds"]), int(r["bytes"]), int(r["moved"])) for r in told]
    return spark.createDataFrame(rows, "config string, trial int, sweep int, perplexity double, tokens long, seconds double, bytes long, moved long")


def tables(log: DataFrame) -> DataFrame:
    """Mean and deviation of seconds a sweep, and size, by config, with subtotals by rule."""
    rule = F.element_at(F.split("config", "/"), 1)
    rows = log.where("sweep > 0").withColumn("rule", rule).rollup("rule", "config").agg(F.avg("seconds").alias("seconds"), F.stddev_samp("seconds").alias("sd"), F.max("bytes").alias("bytes"), F.avg("moved").alias("moved"))
    return rows.where("rule IS NOT NULL")


def spread(log: DataFrame) -> DataFrame:
    """Mean and deviation over trials of each config's perplexity by sweep, and its bytes."""
    return log.groupBy("config", "sweep").agg(F.avg("perplexity").alias("mean"), F.stddev_samp("perplexity").alias("sd"), F.max("bytes").alias("bytes"), F.count("*").alias("trials"))


def curves(log: DataFrame) -> DataFrame:
    """Perplexity of each config by sweep, a column for each config."""
    return log.groupBy("sweep").pivot("config").agg(F.avg("perplexity"))


def microbench(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors by frequency band of every kind of sketch, and of every query rule of count-min, over three key streams,
    even to skewed: parts of lines, users of events, words of all documents. Exact conservative cells are counted in bulk."""
    modest(spark)
    sources = {
        "parts": corpus.order_lines(spark, sf_dir).select(F.lit(0).alias("k"), "key", "event"),
        "users": corpus.clicks(spark, sf_dir).select(F.lit(0).alias("k"), "key", F.col("event").cast("string").alias("event")),
        "words": corpus.word_stream(spark, sf_dir).select(F.lit(0).alias("k"), "key", "event"),
    }
    base = SketchParams(3, 512, 1.08, 8)
    plain = SketchParams(3, 512)
    kinds = {"cm": plain} | {f"cm {q}": replace(plain, query=q) for q in ("mean_min", "mean_clip")} | {"cm conservative": replace(plain, rule="conservative")}
    kinds |= {n: replace(base, counter=c, rule=r) if c != "exact" else base for n, (c, r) in RULES.items()}
    out = None
    for source, rows in sources.items():
        rows = cut(rows, "increments")
        exact = cut(rows.groupBy("k", "key").agg(F.count("*").alias("n")), "counts")
        keys = exact.select("k", "key")
        # one pass finds what any kind's states depend on; each is then built from that
        some = cut(combined.moving(rows, "key", [p for p in kinds.values() if p.counter != "exact"], ["k"], ["event"]), "moving")
        for kind, p in kinds.items():
            if p.counter == "exact":
                est = cms.cm_query(combined.build_bulk(exact, "key", p, ["k"], "n"), keys, "key", p, ["k"])
            else:
                est = combined.query(combined.build(some, "key", p, ["k"], ["event"]), keys, "key", p, ["k"])
            # a few rows, written so that the shuffles of a kind are gone before the next
            bands = cut(evaluation.error_bands(exact, est, ["k", "key"]).select(F.lit(source).alias("source"), F.lit(kind).alias("kind"), "*"), "bands")
            out = bands if out is None else out.unionByName(bands)
        drop(rows)
        drop(some)
    return out


def microbench_grid(spark: SparkSession, sf_dir: str, bases: tuple[float, ...] = (1.02, 1.08, 1.5), rows: tuple[int, ...] = (1, 3, 5), logs: tuple[int, ...] = (7, 9)) -> DataFrame:
    """Errors by frequency band over (base, l, w), for words and parts, each sketch counted in bulk."""
    sources = {"parts": corpus.order_lines(spark, sf_dir).select(F.lit(0).alias("k"), "key"), "words": corpus.word_increments(spark, sf_dir).select(F.lit(0).alias("k"), "key")}
    out = None
    for source, increments in sources.items():
        exact = cut(increments.groupBy("k", "key").agg(F.count("*").alias("n")), "counts")
        keys = exact.select("k", "key")
        for l, log in ((a, b) for a in rows for b in logs):  # noqa: E741
            for base in bases:
                p = SketchParams(l, 1 << log, base, 32, counter="independent")
                est = combined.query(combined.build_bulk(exact, "key", p, ["k"], "n"), keys, "key", p, ["k"])
                # written, so that no plan holds more than one sketch
                bands = evaluation.error_bands(exact, est, ["k", "key"]).select(F.lit(source).alias("source"), F.lit(base).alias("base"), F.lit(l).alias("l"), F.lit(log).alias("log2w"), "*")
                bands = cut(bands, "bands")
                out = bands if out is None else out.unionByName(bands)
    return out


def partition_invariance(spark: SparkSession, sf_dir: str, parts: tuple[int, ...] = (1, 2, 4, 8), topics: int = 4, sweeps: int = 2) -> DataFrame:
    """Checksums of the assignments by number of partitions: exact counts do not depend on it."""
    c, out = prepare(spark, sf_dir), []
    for n in parts:
        fit = lda.sem_lda(c.train.repartition(n), Dense(c.types, topics), c.types, sweeps=sweeps)
        out.append((n, fit.docs.agg(F.bit_xor(F.xxhash64("doc_id", "zs"))).first()[0]))
    return spark.createDataFrame(out, "partitions int, checksum long")


def main() -> None:
    """Both experiments at their own size: python -m tallymill.workloads.experiments TABLES."""
    import sys

    spark = SparkSession.builder.config("spark.scheduler.mode", "FAIR").getOrCreate()
    both = lambda types, k: grid1(types, k) | grid2(types, k)
    log = grid_frame(spark, run_grid(spark, sys.argv[1], both, every=10))
    spread(log).orderBy("config", "sweep").show(1000, truncate=False)


if __name__ == "__main__":
    main()
