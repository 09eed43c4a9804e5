"""Exact duplicate removal with built-in SQL functions only.

A 128-bit content hash names a group and the bytes inside a group are compared, by
grouping on hash and text together, before a group is believed. The text crosses the
network once, after a map-side aggregate has folded equal texts of a task, so a text
that a third of all rows share sends one row per task. The join back carries hashes and
groups of several rows only; rows of a very large group are joined where they are.

Defined cases: a null text is the empty text; empty texts equal each other; of rows with
one id each row is returned; a null id never wins over an id, and stays only if all ids
of its group are null; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from webgather.llm._shared import joined, written


def _hashes(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text: Column = F.coalesce(F.col(text_col), F.lit(""))
    return docs.select(F.col(id_col).alias("doc_id"), text.alias("body")).select(
        "doc_id", "body", F.unhex(F.md5("body")).alias("digest"), F.sha2("body", 256).alias("text_sha256")
    )


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest") -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every row of docs.

    keep: which id of a group stays, "smallest" or "largest". Should two texts share the
    128-bit hash, the SHA-256 parts them; should they share both, the job stops.
    """
    if keep not in ("smallest", "largest"):
        raise ValueError(f"keep is smallest or largest, not {keep!r}")
    best = F.min if keep == "smallest" else F.max
    rows = _hashes(docs, id_col, text_col)
    texts = rows.groupBy("digest", "text_sha256", "body").agg(best("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    groups = texts.groupBy("digest", "text_sha256").agg(
        best("keep_id").alias("keep_id"), F.sum("group_size").alias("group_size"), F.count(F.lit(1)).alias("texts")
    )
    groups = groups.select(
        "digest",
        "text_sha256",
        "keep_id",
        F.when(F.col("texts") > 1, F.raise_error(F.lit("two texts share both hashes")).cast("bigint")).otherwise(F.col("group_size")).alias("group_size"),
    )
    copies = written(groups.filter("group_size > 1"))
    found = joined(rows.drop("body"), copies, ["digest", "text_sha256"], "group_size", "left")
    lone = F.col("group_size").isNull()
    found = found.withColumn("keep_id", F.when(lone, F.col("doc_id")).otherwise(F.col("keep_id")))
    return found.select("doc_id", "keep_id", F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"), F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")


def drop_exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest") -> DataFrame:
    """The rows of docs whose id stays, all columns as they were."""
    stays = exact_groups(docs, id_col, text_col, keep).filter("kept").select(F.col("doc_id").alias("_stays")).distinct()
    return docs.join(stays, docs[id_col].eqNullSafe(stays["_stays"]), "left_semi")
