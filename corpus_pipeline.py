"""A corpus cleaned and encoded stage by stage, each on all that its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tallymill.llm import bpe, decontaminate, langid, simhash, suffixes
from tallymill.llm.queries import tokenizer
from tallymill.llm.shared import cut, modest, table

#: Words of the shortest repeated passage that goes.
PASSAGE = 51


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is recognised."""
    modest(spark)
    found = langid.identify(docs, langid.fit(docs))
    return found.where("NOT rejected").select(*docs.columns)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near duplicates."""
    modest(spark)
    return simhash.one_row(docs)


def without_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the passages that repeat, of more than 50 words or of suffixes.DEPTH bytes."""
    modest(spark)
    return suffixes.without_passages(docs, PASSAGE)


def uncontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that do not repeat the benchmark."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document, and digests of them and of what they decode to."""
    modest(spark)
    both = bpe.decode(bpe.encode(docs, *tokenizer()), *tokenizer())
    return bpe.digests(both, keep_ids=True)


STAGES = [
    ("language", known_language),
    ("near_duplicates", one_of_each),
    ("repeats", without_repeats),
    ("uncontaminated", uncontaminated),
    ("encoded", encoded),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
