"""Graphs of pages and their quotients, degrees, breadth-first levels and basic data.

edges: (src, dst); nodes: (id, labels). Loops over levels write each step as a table in the
shared folder, so plans stay short and lost executors cost one step.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a temporary folder only where it is unset and Spark runs in one process."""
    sc = spark.sparkContext
    base = sc.getCheckpointDir() or sc.getConf().get("spark.checkpoint.dir")
    if not base:
        if not sc.master.startswith("local[") and sc.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="webgather-")
        sc.setCheckpointDir(base)
    return base


def step_table(df: DataFrame) -> DataFrame:
    """df written to the shared checkpoint folder and read again."""
    spark = df.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/steps/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def quotient(edges: DataFrame, nodes: DataFrame, label: str, loops: bool = False) -> DataFrame:
    """src, dst, links: labels joined by at least one edge, and by how many."""
    own = nodes.select(F.col("id").alias("src"), F.col(label).alias("a"))
    other = nodes.select(F.col("id").alias("dst"), F.col(label).alias("b"))
    pairs = edges.join(own, "src").join(other, "dst")
    return (pairs if loops else pairs.filter("a <> b")).groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.count(F.lit(1)).alias("links"))


def page_graph(links: DataFrame, pages: DataFrame, closed: bool = True, loops: bool = False) -> DataFrame:
    """src, dst ids of links (page_id, target) whose target is a page; without `closed`, the target URL of all."""
    if not closed:
        return links.select(F.col("page_id").alias("src"), F.col("target").alias("dst")).distinct()
    found = links.join(pages.select(F.col("url").alias("target"), F.col("page_id").alias("dst")), "target").select(F.col("page_id").alias("src"), "dst")
    return (found if loops else found.filter("src <> dst")).distinct()


def basic(nodes: DataFrame, edges: DataFrame, repeats: DataFrame | None = None) -> DataFrame:
    """overall, first_copies, mean content, mean outdegree, mean external outdegree (to another host)."""
    host = nodes.select(F.col("id").alias("src"), F.col("host").alias("a"))
    other = nodes.select(F.col("id").alias("dst"), F.col("host").alias("b"))
    out = edges.join(host, "src").join(other, "dst").groupBy("src").agg(F.count(F.lit(1)).alias("d"), F.count_if(F.col("a") != F.col("b")).alias("x"))
    rows = nodes.select("id", "content").join(out.withColumnRenamed("src", "id"), "id", "left")
    rows = rows.join(repeats.select("id", "is_repeat"), "id") if repeats is not None else rows.withColumn("is_repeat", F.lit(False))
    return rows.agg(
        F.count(F.lit(1)).alias("overall"), F.count_if(~F.col("is_repeat")).alias("first_copies"), F.round(F.avg("content"), 6).alias("mean_content"),
        F.round(F.avg(F.coalesce("d", F.lit(0))), 6).alias("mean_outdegree"), F.round(F.avg(F.coalesce("x", F.lit(0))), 6).alias("mean_external"),
    )


def degrees(edges: DataFrame, nodes: DataFrame, direction: str = "in") -> DataFrame:
    """id, degree of every node, 0 included."""
    end = "dst" if direction == "in" else "src"
    counts = edges.groupBy(F.col(end).alias("id")).agg(F.count(F.lit(1)).alias("degree"))
    return nodes.select("id").join(counts, "id", "left").select("id", F.coalesce("degree", F.lit(0)).alias("degree"))


def degree_freq(edges: DataFrame, nodes: DataFrame, direction: str = "in") -> DataFrame:
    return degrees(edges, nodes, direction).groupBy("degree").agg(F.count(F.lit(1)).alias("freq"))


def fibonacci_bins(freq: DataFrame) -> DataFrame:
    """low, high, nodes, mean_freq, center: frequencies by bins between Fibonacci numbers."""
    bounds, a, b = [], 1, 2
    while a < 1 << 62:
        bounds.append((a, b))
        a, b = b, a + b
    bins = freq.sparkSession.createDataFrame(bounds, "low long, high long")
    hit = freq.filter("degree > 0").join(F.broadcast(bins), (F.col("degree") >= F.col("low")) & (F.col("degree") < F.col("high")))
    return hit.groupBy("low", "high").agg(F.sum("freq").alias("nodes")).select("low", "high", "nodes", F.round(F.col("nodes") / (F.col("high") - F.col("low")), 6).alias("mean_freq"), ((F.col("low") + F.col("high") - 1) / 2).alias("center"))


def degree_rank(freq: DataFrame) -> DataFrame:
    """degree, rank: nodes of at least that degree. The histogram is small, one row a degree."""
    return freq.select("degree", F.sum("freq").over(Window.orderBy(F.col("degree").desc())).alias("rank"))


def indegree_split(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """id, inner, outer, is_root: links from the same host and from others; the root is the host's least id."""
    root = nodes.groupBy("host").agg(F.min("id").alias("root"))
    own, other = nodes.select(F.col("id").alias("src"), F.col("host").alias("a")), nodes.select(F.col("id").alias("dst"), F.col("host").alias("b"))
    counts = edges.join(own, "src").join(other, "dst").groupBy(F.col("dst").alias("id")).agg(F.count_if(F.col("a") == F.col("b")).alias("inner"), F.count_if(F.col("a") != F.col("b")).alias("outer"))
    return nodes.select("id", "host").join(counts, "id", "left").join(root, "host").select("id", F.coalesce("inner", F.lit(0)).alias("inner"), F.coalesce("outer", F.lit(0)).alias("outer"), (F.col("id") == F.col("root")).alias("is_root"))


def tail_step(rank: DataFrame, cap: int) -> DataFrame:
    """How much of the rank curve falls between 0.9 and 1.1 times the cap."""
    at = lambda d: F.coalesce(F.max(F.when(F.col("degree") >= d, F.col("rank"))), F.lit(0))
    return rank.agg(at(0.9 * cap).alias("before"), at(1.1 * cap).alias("after")).withColumn("step", F.round(F.col("before") / F.greatest("after", F.lit(1)), 6))


def bfs(edges: DataFrame, seeds: DataFrame, max_depth: int | None = None) -> DataFrame:
    """id, depth of what seeds (id) reach, up to max_depth if it is set; a level a round, each a table."""
    reached = step_table(seeds.select("id", F.lit(0).alias("depth")).distinct())
    border, depth = reached, 0
    while max_depth is None or depth < max_depth:
        depth += 1
        new = border.join(edges, border.id == edges.src).select(F.col("dst").alias("id")).distinct().join(reached, "id", "left_anti").select("id", F.lit(depth).alias("depth"))
        border = step_table(new)
        if border.isEmpty():
            break
        reached = reached.unionByName(border)
    return reached


def capped(nodes: DataFrame, order: str, cap: int) -> DataFrame:
    """At most `cap` nodes of each host, the first by order."""
    return nodes.withColumn("_k", F.row_number().over(Window.partitionBy("host").orderBy(order))).filter(F.col("_k") <= cap).drop("_k")


def by_depth(edges: DataFrame, nodes: DataFrame, levels: DataFrame) -> DataFrame:
    """depth, pages, mean outdegree, mean external outdegree, mean content."""
    own, other = nodes.select(F.col("id").alias("src"), F.col("host").alias("a")), nodes.select(F.col("id").alias("dst"), F.col("host").alias("b"))
    out = edges.join(own, "src").join(other, "dst").groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("d"), F.count_if(F.col("a") != F.col("b")).alias("x"))
    rows = levels.join(nodes.select("id", "content"), "id").join(out, "id", "left")
    return rows.groupBy("depth").agg(F.count(F.lit(1)).alias("pages"), F.round(F.avg(F.coalesce("d", F.lit(0))), 6).alias("out"), F.round(F.avg(F.coalesce("x", F.lit(0))), 6).alias("external"), F.round(F.avg("content"), 6).alias("content"))
