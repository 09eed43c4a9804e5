"""From raw documents to packed sequences, in five stages, each over all that the one before kept.

Language identification drops texts in which no language can be told, exact and near duplicate
removal keep one of each group, decontamination drops documents that repeat benchmark items,
and packing cuts what is left into sequences.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from webgather.llm import decontaminate, exact_dedup, langid, minhash, packing
from webgather.llm._shared import let_go, written
from webgather.llm.queries import table, tokenizer_path, trained_on


def _row_key(text: Column) -> Column:
    """A row by its id, which may be null, and its content."""
    return F.concat(F.coalesce(F.concat(F.lit("i"), F.col("doc_id").cast("string")), F.lit("n")), F.lit(":"), text)


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return langid.recognised(docs, langid.learn(docs, trained_on()))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each text: decisions are by id and content, as ids may be null or repeated."""
    let_go(spark)  # the language model's parts, on the driver
    stays = exact_dedup.exact_groups(docs, keep="largest").filter("kept").select(_row_key(F.col("text_sha256")).alias("_row"))
    keyed = docs.withColumn("_row", _row_key(F.sha2(F.coalesce("text", F.lit("")), 256)))
    # rows of one id and one text are together after the join, so no further shuffle parts them
    return keyed.join(stays, "_row", "left_semi").dropDuplicates(["_row"]).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group; rows whose ids are null or repeated are numbered first, in order of their ids, nulls last."""
    let_go(spark)
    odd = docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).filter("n > 1 or doc_id is null")
    if odd.isEmpty():
        return docs.join(minhash.near_duplicates(docs).filter("kept").select("doc_id"), "doc_id", "left_semi").select(*docs.columns)
    order = [F.col("doc_id").asc_nulls_last(), F.col("_text")]
    spread = docs.withColumn("_text", F.sha2(F.coalesce("text", F.lit("")), 256)).repartitionByRange(*order).sortWithinPartitions(*order)
    rows = written(spread.withColumn("_row", F.monotonically_increasing_id()))
    stays = minhash.near_duplicates(rows, id_col="_row").filter("kept").select(F.col("doc_id").alias("_row"))
    return rows.join(stays, "_row", "left_semi").select(*docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.uncontaminated(docs, table(spark, sf_dir, "benchmark"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, tokenizer_path())


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language identification", identify_language),
    ("exact deduplication", drop_copies),
    ("near deduplication", drop_near_copies),
    ("benchmark decontamination", drop_contaminated),
    ("packing", pack_sequences),
]

#: SQL can express neither the language model nor the packing.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what a stage keeps is written and read again as the next one's input."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = written(docs)
    return docs
