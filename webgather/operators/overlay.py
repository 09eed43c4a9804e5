"""Graphs over the given tables that stand in for a gathered web."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from webgather.catalog import table
from webgather.functions import html, suffix, urls
from webgather.operators.graph import step_table

#: The same construction in DuckDB: CTEs nodes(id, host, site, domain, spam) and edges(src, dst).
G1_SQL = r"""
    p0 AS (SELECT page_id AS id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, len(regexp_extract_all(html, '(?is)<a\s[^>]*?href\s*=\s*"[^"]*"')) AS links, url, length(html) AS content FROM pages),
    p1 AS (SELECT *, row_number() OVER (PARTITION BY host ORDER BY id) - 1 AS r, count(*) OVER (PARTITION BY host) AS h, count(*) OVER () AS n FROM p0),
    o AS (SELECT *, unnest(range(1, least(links, 6) + 1)) AS k FROM p1),
    near_ AS (SELECT o.id AS src, t.id AS dst FROM o JOIN p1 t ON t.host = o.host AND t.r = CASE WHEN k = 1 THEN 0 ELSE (o.r * k + 1) % o.h END WHERE k <= 3),
    far_ AS (SELECT id AS src, CASE WHEN k = 6 THEN (id * id + 11) % CAST(ceil(sqrt(n)) AS BIGINT) ELSE (id * id + 7 * k + 3 * id * k) % n END AS dst FROM o WHERE k > 3),
    edges AS (SELECT DISTINCT src, dst FROM (SELECT * FROM near_ UNION ALL SELECT * FROM far_) WHERE src <> dst),
    nodes AS (SELECT id, host, regexp_replace(host, '^(www|m|blog)\.', '') AS site, regexp_extract(host, '([^.]+\.[^.]+)$', 1) AS domain, (host LIKE '%pills%' OR host LIKE '%bets%' OR host LIKE '%spam%') AS spam, url, content FROM p0)"""


def nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _labelled(_read(spark, sf_dir))


def _read(spark: SparkSession, sf_dir: str, *more: Column) -> DataFrame:
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), urls.host("url").alias("host"), "url", F.length("html").cast("long").alias("content"), *more)


def _domain(host: Column) -> Column:
    return F.regexp_extract(host, r"([^.]+\.[^.]+)$", 1)


def _labelled(pages: DataFrame) -> DataFrame:
    host = F.col("host")
    return pages.select("id", "host", suffix.site(host).alias("site"), _domain(host).alias("domain"), host.rlike("pills|bets|spam").alias("spam"), "url", "content")


def web(spark: SparkSession, sf_dir: str, places: bool = False, domain: str | None = None) -> tuple[DataFrame, DataFrame]:
    """(nodes, edges) of the overlay on pages: as many arcs from a page as it has links, up to six. places: edges have pos, the link's first place on its page.

    domain: edges are those from its pages alone, so the links of others aren't parsed; nodes are all pages.
    """
    links = F.size(html.anchors("html"))
    inside = F.lit(True) if domain is None else _domain(urls.host("url")) == domain
    pages = _read(spark, sf_dir, (links if domain is None else F.when(inside, links)).alias("links"))
    by_host = Window.partitionBy("host")
    # written, as it is read four times, and conditions on links would find them anew
    ranked = step_table(pages.withColumn("r", F.row_number().over(by_host.orderBy("id")) - 1).withColumn("h", F.count(F.lit(1)).over(by_host)))
    total = ranked.agg(F.count(F.lit(1)).alias("n"))
    arcs = ranked.filter("links > 0").select("*", F.explode(F.expr("sequence(1, 6)")).alias("k")).filter("k <= links").crossJoin(F.broadcast(total))
    near = arcs.filter("k <= 3").select(F.col("id").alias("src"), "host", F.when(F.col("k") == 1, 0).otherwise((F.col("r") * F.col("k") + 1) % F.col("h")).alias("r"), "k")
    near = near.join(ranked.select("host", "r", F.col("id").alias("dst")), ["host", "r"]).select("src", "dst", "k")
    i, k = F.col("id"), F.col("k")
    far = arcs.filter("k > 3").select(i.alias("src"), F.when(k == 6, (i * i + 11) % F.ceil(F.sqrt("n")).cast("long")).otherwise((i * i + 7 * k + 3 * i * k) % F.col("n")).alias("dst"), "k")
    links = near.unionByName(far).filter("src <> dst")
    return _labelled(ranked), links.groupBy("src", "dst").agg(F.min("k").alias("pos")) if places else links.select("src", "dst").distinct()


G2_SQL = """
    nx AS (SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst FROM lineitem),
    edges AS (SELECT DISTINCT src, dst FROM nx WHERE dst IS NOT NULL AND src <> dst),
    nodes AS (SELECT p_partkey AS id, p_brand AS host, p_type AS domain FROM part)"""


def baskets(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Part to the next part of an order; labels are brand and type."""
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    edges = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(order).alias("dst")).filter("dst is not null and src <> dst").distinct()
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.col("p_brand").alias("host"), F.col("p_type").alias("domain")), edges


G3_SQL = """
    edges AS (SELECT DISTINCT o_custkey AS src, -1 - l_suppkey AS dst FROM orders JOIN lineitem ON l_orderkey = o_orderkey),
    nodes AS (SELECT c_custkey AS id, c_nationkey AS host FROM customer UNION ALL SELECT -1 - s_suppkey, s_nationkey FROM supplier)"""


def trade(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Customer to supplier (as negative numbers); the label is the nation."""
    orders, lines = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    edges = orders.join(lines, orders.o_orderkey == lines.l_orderkey).select(F.col("o_custkey").alias("src"), (-1 - F.col("l_suppkey")).alias("dst")).distinct()
    people = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), F.col("c_nationkey").alias("host"))
    return people.unionByName(table(spark, sf_dir, "supplier").select((-1 - F.col("s_suppkey")).alias("id"), F.col("s_nationkey").alias("host"))), edges


G4_SQL = """
    nx AS (SELECT user_id AS src, lead(user_id) OVER (ORDER BY event_id) AS dst FROM events),
    edges AS (SELECT DISTINCT src, dst FROM nx WHERE dst IS NOT NULL AND src <> dst),
    nodes AS (SELECT DISTINCT user_id AS id, user_id % 10 AS host FROM events)"""


def successions(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """A user to the user of the next event: event ids are dense, so the next one is found by a join."""
    events = table(spark, sf_dir, "events")
    one, two = events.select(F.col("user_id").alias("src"), (F.col("event_id") + 1).alias("event_id")), events.select("event_id", F.col("user_id").alias("dst"))
    return events.select(F.col("user_id").alias("id"), (F.col("user_id") % 10).alias("host")).distinct(), one.join(two, "event_id").select("src", "dst").filter("src <> dst").distinct()
