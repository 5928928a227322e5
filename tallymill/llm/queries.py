"""The queries of these operators over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallymill.llm import bpe, chats, decontaminate, imatch, langid, licenses, paragraphs, sharding, simhash, suffixes
from tallymill.llm.shared import table


def tokenizer() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN


def op1_paragraphs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return paragraphs.by_document(table(spark, sf_dir, "documents"))


def op2_chats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chats.formatted(table(spark, sf_dir, "conversations"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op4_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    left = suffixes.digests(suffixes.remaining(table(spark, sf_dir, "documents"), n_words=suffixes.PASSAGE))
    return left.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "n_passages", "n_passage_words")


def op5_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = licenses.scan(docs, licenses.fit(docs))
    families = F.array_sort(F.array_distinct(F.transform("found", lambda x: x["family"])))
    return found.select("doc_id", F.size("found").cast("long").alias("n_found"), families.alias("families"), "found")


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = langid.fit(docs.where(langid.fold(F.col("doc_id")) != 2))
    found = langid.identify(docs.select("doc_id", "text"), model)
    return found.select("doc_id", (langid.fold(F.col("doc_id")) == 2).alias("held_out"), "lang_pred", "score", "rejected")


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.overlaps(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return decontaminate.judged(found).select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("item_ids").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "item_ids").cast("binary"), 256).alias("items_sha256"),
        "contaminated",
    )


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    ids = bpe.encode(table(spark, sf_dir, "documents"), *tokenizer())
    return bpe.digests(bpe.decode(ids, *tokenizer()))


def op9_imatch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return imatch.fingerprints(table(spark, sf_dir, "documents"))


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.sharded(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for k, f in globals().items() if k.startswith("op") and callable(f)}


def oracle_sql() -> dict[str, str]:
    return {"op2_chats": chats.FORMATTED_SQL, "op4_suffixes": suffixes.REMAINING_SQL, "op7_decontaminate": decontaminate.OVERLAPS_SQL}
