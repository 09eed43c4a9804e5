"""Registrable domains: the label above the longest public suffix of a host."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A small rule set in the public suffix list's notation; the full list is a parameter.
RULES = [
    ("com", "icann"), ("net", "icann"), ("org", "icann"), ("uk", "icann"), ("co.uk", "icann"), ("ac.uk", "icann"), ("jp", "icann"), ("co.jp", "icann"),
    ("ck", "icann"), ("*.ck", "icann"), ("!www.ck", "icann"), ("kawasaki.jp", "icann"), ("*.kawasaki.jp", "icann"), ("!city.kawasaki.jp", "icann"),
    ("de", "icann"), ("fr", "icann"), ("it", "icann"), ("br", "icann"), ("com.br", "icann"), ("pages.example.net", "private"),
]
ADDRESS = r"^(\d{1,3}\.){3}\d{1,3}$|^\[.*\]$"


def rules(spark: SparkSession, rows=RULES, private: bool = True) -> DataFrame:
    """rule (without its mark), kind (plain, wildcard, exception), n labels."""
    kept = [(r.lstrip("!").removeprefix("*."), "exception" if r[0] == "!" else "wildcard" if r[:2] == "*." else "plain") for r, part in rows if private or part != "private"]
    return spark.createDataFrame(kept, "rule string, kind string")


def registrable(hosts: DataFrame, host: str, rule_table: DataFrame) -> DataFrame:
    """host and domain for each distinct host; an address is its own domain, a suffix has none.

    A rule table is a few hundred kilobytes at most and goes to all tasks.
    """
    names = hosts.select(F.col(host).alias("host")).distinct()
    labels = F.split("host", r"\.")
    n = F.size(labels)
    tails = names.filter(~F.col("host").rlike(ADDRESS)).select("host", n.alias("n"), F.posexplode(labels).alias("p", "_")).select("host", "n", (F.col("n") - F.col("p")).alias("k"), F.expr("substring_index(host, '.', p - n)").alias("tail"))
    hits = tails.join(F.broadcast(rule_table.withColumnRenamed("rule", "tail")), "tail")
    # how many labels the suffix has: a wildcard takes one more, an exception one less
    size = F.col("k") + F.when(F.col("kind") == "wildcard", 1).when(F.col("kind") == "exception", -1).otherwise(0)
    best = hits.filter(size <= F.col("n")).groupBy("host").agg(F.max(F.when(F.col("kind") == "exception", size)).alias("x"), F.max(F.when(F.col("kind") != "exception", size)).alias("s"))
    found = names.join(best, "host", "left").withColumn("s", F.coalesce("x", "s", F.lit(1)))
    domain = F.when(F.col("host").rlike(ADDRESS), F.col("host")).when(n > F.col("s"), F.expr("substring_index(host, '.', -(s + 1))"))
    return found.select("host", domain.alias("domain"))


def site(host: Column | str) -> Column:
    """A host without the usual prefixes: a second, coarser label."""
    return F.regexp_replace(host, r"^(www|m|blog)\.", "")
