"""Queries on the general operators that users of the methods need around them."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from webgather.catalog import query, table
from webgather.functions import urls
from webgather.operators import asof

MICROS = "timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast({} as timestamp_ntz))"


@query("op_project_filter", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net, CASE WHEN l_quantity > 25 THEN 'large' ELSE 'small' END AS size FROM lineitem WHERE l_shipdate BETWEEN TIMESTAMP '1995-01-01' AND TIMESTAMP '1995-06-30' AND l_returnflag IN ('A', 'R')")
def op_project_filter(spark, sf):
    kept = table(spark, sf, "lineitem").filter("l_shipdate between timestamp_ntz'1995-01-01' and timestamp_ntz'1995-06-30' and l_returnflag in ('A', 'R')")
    return kept.select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"), F.when(F.col("l_quantity") > 25, "large").otherwise("small").alias("size"))


@query("op_equi_join", "SELECT n_name, count(*) AS orders, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE) AS total FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey GROUP BY 1")
def op_equi_join(spark, sf):
    o, c, n = (table(spark, sf, t) for t in ("orders", "customer", "nation"))
    joined = o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), c.c_nationkey == n.n_nationkey)
    return joined.groupBy("n_name").agg(F.count(F.lit(1)).alias("orders"), F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("total"))


@query("op_outer_join", "SELECT coalesce(c_custkey, o_custkey) AS custkey, count(o_orderkey) AS orders FROM customer FULL JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def op_outer_join(spark, sf):
    o, c = table(spark, sf, "orders"), table(spark, sf, "customer")
    return c.join(o, c.c_custkey == o.o_custkey, "full").groupBy(F.coalesce("c_custkey", "o_custkey").alias("custkey")).agg(F.count("o_orderkey").alias("orders"))


@query("op_semi_join", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def op_semi_join(spark, sf):
    o, c = table(spark, sf, "orders").filter("o_totalprice > 300000"), table(spark, sf, "customer")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi").select("c_custkey")


@query("op_anti_join", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def op_anti_join(spark, sf):
    o, c = table(spark, sf, "orders"), table(spark, sf, "customer")
    return c.join(o, c.c_custkey == o.o_custkey, "left_anti").select("c_custkey")


@query("op_range_join", "WITH b AS (SELECT * FROM (VALUES (0, 0.0, 50.0), (1, 50.0, 200.0), (2, 200.0, 1e12)) t(bin, lo, hi)) SELECT bin, count(*) AS events FROM events JOIN b ON value >= lo AND value < hi GROUP BY 1")
def op_range_join(spark, sf):
    bins = spark.createDataFrame([(0, 0.0, 50.0), (1, 50.0, 200.0), (2, 200.0, 1e12)], "bin int, lo double, hi double")
    return table(spark, sf, "events").join(F.broadcast(bins), F.expr("value >= lo and value < hi")).groupBy("bin").agg(F.count(F.lit(1)).alias("events"))


@query("op_asof_join", "SELECT e.event_id, p.event_id AS purchase FROM (SELECT * FROM events WHERE event_type = 'view') e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON e.user_id = p.user_id AND e.ts >= p.ts".replace("p.event_id AS", "coalesce(p.event_id, -1) AS"))
def op_asof_join(spark, sf):
    """Each view with the last purchase of its user before it."""
    e = table(spark, sf, "events")
    found = asof.join(e.filter("event_type = 'view'"), e.filter("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase")), "user_id", "ts", ["purchase"])
    return found.select("event_id", F.coalesce("purchase", F.lit(-1)).alias("purchase"))


@query("op_interval_join", "WITH a AS (SELECT user_id, event_id, epoch_us(ts) AS t FROM events) SELECT x.event_id, count(*) AS near FROM a x JOIN a y ON x.user_id = y.user_id AND y.t BETWEEN x.t - 3600000000 AND x.t + 3600000000 GROUP BY 1")
def op_interval_join(spark, sf):
    """Events within an hour of each other: by window frames, not pairs."""
    e = table(spark, sf, "events").select("user_id", "event_id", F.expr(MICROS.format("ts")).alias("t"))
    hour = 3_600_000_000
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("t").rangeBetween(-hour, hour)).alias("near"))


@query("op_lateral_top", "SELECT user_id, event_id FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS k FROM events) WHERE k <= 2")
def op_lateral_top(spark, sf):
    k = F.row_number().over(Window.partitionBy("user_id").orderBy(F.col("value").desc(), "event_id"))
    return table(spark, sf, "events").withColumn("k", k).filter("k <= 2").select("user_id", "event_id")


@query("op_aggregates", "SELECT event_type, count(*) AS n, count(DISTINCT user_id) AS users, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS sd, min(event_id) AS first_id, arg_max(event_id, (value, event_id)) AS best, count(*) FILTER (value > 100) AS large FROM events GROUP BY 1")
def op_aggregates(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(
        F.count(F.lit(1)).alias("n"), F.countDistinct("user_id").alias("users"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev_samp("value"), 6).alias("sd"),
        F.min("event_id").alias("first_id"), F.max_by("event_id", F.struct("value", "event_id")).alias("best"), F.count_if(F.col("value") > 100).alias("large"),
    )


@query("op_sketch_error", "SELECT true AS within")
def op_sketch_error(spark, sf):
    """A HyperLogLog estimate against the exact count of parts."""
    found = table(spark, sf, "lineitem").agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 12)).alias("e"), F.countDistinct("l_partkey").alias("n"))
    return found.select((F.abs(F.col("e") / F.col("n") - 1) < 0.05).alias("within"))


@query("op_rollup", "SELECT coalesce(d, '*') AS d, coalesce(h, '*') AS h, count(*) AS pages FROM (SELECT regexp_extract(host, '([^.]+\\.[^.]+)$', 1) AS d, host AS h FROM (SELECT regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host FROM pages)) GROUP BY ROLLUP (d, h)".replace("\\\\", "\\"))
def op_rollup(spark, sf):
    h = urls.host("url")
    rows = table(spark, sf, "pages").select(F.regexp_extract(h, r"([^.]+\.[^.]+)$", 1).alias("d"), h.alias("h"))
    return rows.rollup("d", "h").agg(F.count(F.lit(1)).alias("pages")).select(F.coalesce("d", F.lit("*")).alias("d"), F.coalesce("h", F.lit("*")).alias("h"), "pages")


@query("op_cube", "SELECT coalesce(l_returnflag, '*') AS flag, coalesce(l_linestatus, '*') AS status, grouping(l_returnflag) * 2 + grouping(l_linestatus) AS level, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def op_cube(spark, sf):
    rows = table(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n"))
    return rows.select(F.coalesce("l_returnflag", F.lit("*")).alias("flag"), F.coalesce("l_linestatus", F.lit("*")).alias("status"), "level", "n")


@query("op_pivot", "SELECT user_id, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY 1".replace("AS view,", 'AS "view",'))
def op_pivot(spark, sf):
    return table(spark, sf, "events").groupBy("user_id").pivot("event_type", ["view", "purchase"]).agg(F.count(F.lit(1))).na.fill(0)


@query("op_unpivot", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, m AS measure, v AS value FROM (SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_tax FROM lineitem) UNPIVOT (v FOR m IN (l_quantity, l_tax))")
def op_unpivot(spark, sf):
    ids = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    return table(spark, sf, "lineitem").unpivot(ids, ["l_quantity", "l_tax"], "measure", "value")


@query("op_windows", "SELECT event_id, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY user_id ORDER BY event_id) AS q, coalesce(lag(event_id) OVER (PARTITION BY user_id ORDER BY event_id), -1) AS before, first_value(event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS first_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS recent FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_type)")
def op_windows(spark, sf):
    t, e = Window.partitionBy("user_id").orderBy("event_type"), Window.partitionBy("user_id").orderBy("event_id")
    return table(spark, sf, "events").select(
        "event_id", F.rank().over(t).alias("r"), F.dense_rank().over(t).alias("dr"), F.ntile(4).over(e).alias("q"), F.coalesce(F.lag("event_id").over(e), F.lit(-1)).alias("before"), F.first("event_id").over(e).alias("first_id"),
        F.count(F.lit(1)).over(e.rowsBetween(-3, 0)).alias("recent"),
    )


@query("op_top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def op_top_k(spark, sf):
    return table(spark, sf, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


@query("op_set_ops", "(SELECT 'both' AS side, k FROM (SELECT DISTINCT o_custkey AS k FROM orders INTERSECT SELECT c_custkey FROM customer)) UNION ALL (SELECT 'none', k FROM (SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders))")
def op_set_ops(spark, sf):
    c, o = table(spark, sf, "customer").select(F.col("c_custkey").alias("k")), table(spark, sf, "orders").select(F.col("o_custkey").alias("k"))
    return o.intersect(c).select(F.lit("both").alias("side"), "k").unionByName(c.subtract(o).select(F.lit("none").alias("side"), "k"))


@query("op_strings", "SELECT p_partkey, upper(p_name) AS up, replace(p_brand, '#', '-') AS brand, levenshtein(p_brand, 'Brand#11') AS far, md5(p_name) AS m, sha256(p_name) AS s, strpos(p_type, ' ') AS at, length(trim(p_type)) AS n FROM part")
def op_strings(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.upper("p_name").alias("up"), F.replace("p_brand", F.lit("#"), F.lit("-")).alias("brand"), F.levenshtein("p_brand", F.lit("Brand#11")).alias("far"), F.md5("p_name").alias("m"), F.sha2("p_name", 256).alias("s"), F.instr("p_type", " ").alias("at"), F.length(F.trim("p_type")).alias("n"))


@query("op_dates", "SELECT o_orderkey, year(o_orderdate) AS y, quarter(o_orderdate) AS q, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, epoch_us(o_orderdate) AS us, dayofweek(o_orderdate) + 1 AS dow FROM orders")
def op_dates(spark, sf):
    d = F.col("o_orderdate")
    return table(spark, sf, "orders").select("o_orderkey", F.year(d).alias("y"), F.quarter(d).alias("q"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("month"), F.expr(MICROS.format("o_orderdate")).alias("us"), F.dayofweek(d).alias("dow"))


@query("op_arrays", "SELECT vec_id, round(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x)), 4) AS norm2, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(CAST(list_max(embedding) AS DOUBLE), 5) AS most FROM embeddings")
def op_arrays(spark, sf):
    v = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, sf, "embeddings").select("vec_id", F.round(F.aggregate(v, F.lit(0.0), lambda a, x: a + x * x), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.array_max(v), 5).alias("most"))


@query("op_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def op_json(spark, sf):
    return table(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("op_variant", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def op_variant(spark, sf):
    k = F.try_variant_get(F.try_parse_json("props"), "$.k", "bigint")
    return table(spark, sf, "events").groupBy(k.alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("op_sample_hash", "SELECT page_id FROM pages WHERE CAST('0x' || substr(md5(url), 1, 15) AS BIGINT) % 4 = 0")
def op_sample_hash(spark, sf):
    """A sample by hash: the same pages whatever the partitions."""
    from webgather.functions.fingerprints import fp60

    return table(spark, sf, "pages").filter(fp60("url") % 4 == 0).select("page_id")


@query("op_sql_surface", "SELECT o_orderpriority AS priority, count(*) AS n FROM orders WHERE o_totalprice > 100000 GROUP BY 1")
def op_sql_surface(spark, sf):
    """The same tables by SQL text with parameters."""
    return spark.sql("SELECT o_orderpriority AS priority, count(*) AS n FROM {orders} WHERE o_totalprice > :least GROUP BY 1", {"least": 100_000}, orders=table(spark, sf, "orders"))


@query("op_grouped_arrow", "SELECT user_id, count(*) AS n, round(median(value), 6) AS middle FROM events GROUP BY 1")
def op_grouped_arrow(spark, sf):
    @F.pandas_udf("double")
    def middle(v: pd.Series) -> float:
        return float(v.median())

    events = table(spark, sf, "events")
    counts = events.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    return events.groupBy("user_id").agg(middle("value").alias("middle")).join(counts, "user_id").select("user_id", "n", F.round("middle", 6).alias("middle"))


@query("op_sql_function", "SELECT o_orderkey, CAST(floor(o_totalprice / 100.0) AS BIGINT) AS reduced FROM orders")
def op_sql_function(spark, sf):
    """A function defined in SQL: Catalyst inlines it."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION in_steps(x DOUBLE, step DOUBLE) RETURNS BIGINT RETURN floor(x / step)")
    return table(spark, sf, "orders").select("o_orderkey", F.expr("in_steps(o_totalprice, 100D)").alias("reduced"))


@query("op_cogroup", "SELECT coalesce(a.k, b.k) AS k, coalesce(n_orders, 0) AS n_orders, coalesce(n_events, 0) AS n_events FROM (SELECT o_custkey AS k, count(*) AS n_orders FROM orders GROUP BY 1) a FULL JOIN (SELECT user_id AS k, count(*) AS n_events FROM events GROUP BY 1) b ON a.k = b.k")
def op_cogroup(spark, sf):
    """Two tables' groups side by side in one task."""
    a = table(spark, sf, "orders").select(F.col("o_custkey").alias("k")).groupBy("k")
    b = table(spark, sf, "events").select(F.col("user_id").alias("k")).groupBy("k")

    def sizes(key, x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"k": [key[0]], "n_orders": [len(x)], "n_events": [len(y)]})

    return a.cogroup(b).applyInPandas(sizes, "k long, n_orders long, n_events long")


@query("op_join_hints", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def op_join_hints(spark, sf):
    """The same join sorted, hashed and broadcast gives the same rows."""
    o, c = table(spark, sf, "orders"), table(spark, sf, "customer")
    out = [o.join(c.hint(h), o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")) for h in ("merge", "shuffle_hash", "broadcast")]
    return out[0].intersect(out[1]).intersect(out[2])


@query("op_kll_quantile", "SELECT true AS within")
def op_kll_quantile(spark, sf):
    """An approximate median against the exact one, by rank."""
    e = table(spark, sf, "events")
    found = e.agg(F.percentile_approx("value", 0.5, 1000).alias("m"))
    rank = e.crossJoin(F.broadcast(found)).agg((F.count_if(F.col("value") <= F.col("m")) / F.count(F.lit(1))).alias("r"))
    return rank.select((F.abs(F.col("r") - 0.5) < 0.01).alias("within"))


@query("op_explode_outer", "SELECT event_id, coalesce(w, '-') AS w FROM (SELECT event_id, unnest(CASE WHEN event_type = 'view' THEN ['v', 'w'] ELSE [NULL] END) AS w FROM events)")
def op_explode_outer(spark, sf):
    parts = F.when(F.col("event_type") == "view", F.array(F.lit("v"), F.lit("w")))
    return table(spark, sf, "events").select("event_id", F.explode_outer(parts).alias("w")).select("event_id", F.coalesce("w", F.lit("-")).alias("w"))


@query("op_sample_by", "SELECT true AS as_asked")
def op_sample_by(spark, sf):
    """A stratified sample: none of one kind, all of another."""
    found = table(spark, sf, "events").sampleBy("event_type", {"view": 1.0, "purchase": 0.0}, 7)
    whole = table(spark, sf, "events").filter("event_type = 'view'")
    return found.agg(F.count(F.lit(1)).alias("a")).crossJoin(whole.agg(F.count(F.lit(1)).alias("b"))).select((F.col("a") == F.col("b")).alias("as_asked"))
