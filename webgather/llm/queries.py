"""The queries of this subpackage: each applies an operator to whole tables and derives the digest columns asked for."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from webgather.llm import decontaminate, exact_dedup, langid, minhash, packing, pii, quality, substring, suffix, toolcalls


def trained_on() -> Column:
    """Which documents a model may learn from."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    """WEBGATHER_TOKENIZERS names the folder of the vocabularies, else the installed package does."""
    if own := os.environ.get("WEBGATHER_TOKENIZERS"):
        return os.path.join(own, name)
    import public_tokenizers

    return public_tokenizers.path(name)


def held_out() -> Column:
    return F.coalesce(~trained_on(), F.lit(False)).alias("held_out")


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.flagged(decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")))
    digest = F.sha2(F.array_join("items", ","), 256)
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), digest.alias("items_sha256"), "contaminated")


def op2_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return langid.identify(docs, langid.learn(docs, trained_on())).select("doc_id", held_out(), "lang_pred", "score")


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = quality.score(docs, quality.learn(docs, table(spark, sf_dir, "labels"), trained_on()))
    return scored.select("doc_id", held_out(), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op4_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents"))


def op5_tool_calls(spark: SparkSession, sf_dir: str) -> DataFrame:
    schemas = {"reply": {"prompt": ("STRING", True), "words": ("BIGINT", True)}}
    return toolcalls.format_calls(toolcalls.turns_as_calls(table(spark, sf_dir, "conversations")), schemas)


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(table(spark, sf_dir, "documents"), keep="largest")


def op7_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = substring.remove_repeated_windows(table(spark, sf_dir, "documents"))
    return cut.select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


def op8_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = suffix.remove_earlier_strings(table(spark, sf_dir, "documents"))
    return cut.select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


def op9_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find_personal_data(table(spark, sf_dir, "documents"))

    def of_kind(kind: str) -> Column:
        return F.size(F.filter("seeds", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    counts = [of_kind(k) for k in pii.KINDS]
    return found.select("doc_id", *counts, F.sha2(pii.spelled("seeds"), 256).alias("base_sha256"), pii.spelled(F.concat("seeds", "added")).alias("spans"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path())


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_decontaminate": op1_decontaminate,
    "op2_language": op2_language,
    "op3_quality": op3_quality,
    "op4_minhash": op4_minhash,
    "op5_tool_calls": op5_tool_calls,
    "op6_exact_dedup": op6_exact_dedup,
    "op7_substring": op7_substring,
    "op8_suffix_array": op8_suffix_array,
    "op9_personal_data": op9_personal_data,
    "op10_packing": op10_packing,
}
