"""Queries on streams, sources and sinks."""

from __future__ import annotations

import uuid
from urllib.parse import urlparse

from pyspark.sql import functions as F

from webgather.catalog import ORACLES, query, table
from webgather.operators import graph, measures, overlay
from webgather.operators.graph import shared_folder
from webgather.operators.overlay import G2_SQL
from webgather.plans import store
from webgather.plans.gather import BATCHED_SQL, HOUR, REQUESTS_SQL, STARTS_SQL, _bloom_sql, requests
from webgather.sources import archive
from webgather.streaming import stream


def place(spark) -> str:
    base = shared_folder(spark)
    # the archive source opens files by itself, so a file: URL is taken as its path
    base = urlparse(base).path if base.startswith("file:") else base
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


@query("once_stream", f"WITH {REQUESTS_SQL} SELECT DISTINCT host FROM q")
def once_stream(spark, sf):
    live = stream.replay(spark, requests(spark, sf), place(spark), 5, "seq")
    return stream.run(stream.once(live.select("host"), "host"))


@query("once_stream_table", f"WITH {REQUESTS_SQL} SELECT DISTINCT host FROM q")
def once_stream_table(spark, sf):
    live = stream.replay(spark, requests(spark, sf), place(spark), 4, "seq")
    return stream.once_by_table(live.select("host"), "host", place(spark)).select("host")


@query("once_stream_within", "SELECT true AS covers")
def once_stream_within(spark, sf):
    """With a horizon of three days: no host is missing."""
    rows = requests(spark, sf).withColumn("ts", F.timestamp_micros("arrive_us"))
    live = stream.replay(spark, rows, place(spark), 5, "seq")
    found = stream.run(stream.once_within(live.select("host", "ts"), "host", "ts", "3 days"))
    return found.agg(F.countDistinct("host").alias("a")).crossJoin(rows.agg(F.countDistinct("host").alias("b"))).select((F.col("a") == F.col("b")).alias("covers"))


@query("polite_stream", f"WITH {STARTS_SQL} SELECT seq, host, start_us FROM st")
def polite_stream(spark, sf):
    live = stream.replay(spark, requests(spark, sf), place(spark), 4, "seq")
    return stream.run(stream.polite(live, 6 * HOUR))


@query("stream_windows", f"WITH {REQUESTS_SQL} SELECT arrive_us // {24 * HOUR} * {24 * HOUR} AS from_us, count(*) AS fetched, CAST(sum(length) AS BIGINT) AS bytes FROM q GROUP BY 1")
def stream_windows(spark, sf):
    """Requests and bytes by day, in tumbling windows."""
    rows = requests(spark, sf).withColumn("ts", F.timestamp_micros("arrive_us"))
    live = stream.replay(spark, rows, place(spark), 4, "seq")
    days = live.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("fetched"), F.sum("length").alias("bytes"))
    return stream.run(days.select(F.unix_micros("window.start").alias("from_us"), "fetched", "bytes"), "complete")


@query("stream_static_join", "SELECT event_type, count(*) AS n FROM events JOIN (SELECT DISTINCT c_custkey FROM customer) ON c_custkey = user_id GROUP BY 1")
def stream_static_join(spark, sf):
    live = stream.replay(spark, table(spark, sf, "events").select("event_id", "user_id", "event_type"), place(spark), 4, "event_id")
    people = table(spark, sf, "customer").select("c_custkey").distinct()
    return stream.run(live.join(people, live.user_id == people.c_custkey).groupBy("event_type").agg(F.count(F.lit(1)).alias("n")), "complete")


@query("store_archive", "SELECT url AS uri, 200 AS status, md5(html) AS digest FROM pages")
def store_archive(spark, sf):
    """Pages written as an archive and read again."""
    archive.register(spark)
    path = place(spark)
    table(spark, sf, "pages").select(F.col("url").alias("uri"), F.lit("2024-01-01T00:00:00Z").alias("date"), F.lit(200).alias("status"), F.col("html").alias("payload")).write.format("archive").mode("append").save(path)
    return spark.read.format("archive").load(path).select("uri", "status", F.md5("payload").alias("digest"))


@query("simweb_source", "SELECT n % 997 AS host, count(*) AS pages FROM (SELECT unnest(range(0, 5000)) AS n) GROUP BY 1")
def simweb_source(spark, sf):
    archive.register(spark)
    return spark.read.format("simweb").option("pages", 5000).load().groupBy((F.col("n") % 997).alias("host")).agg(F.count(F.lit(1)).alias("pages"))


@query("store_columnar", "SELECT fmt, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events, (SELECT unnest(['parquet', 'orc', 'json', 'csv']) AS fmt) GROUP BY 1")
def store_columnar(spark, sf):
    """The same rows through four formats."""
    rows, out = table(spark, sf, "events").select("event_id", "user_id", "event_type"), None
    for fmt in ("parquet", "orc", "json", "csv"):
        path = place(spark)
        rows.write.format(fmt).partitionBy("event_type").save(path)
        one = spark.read.schema(rows.schema).format(fmt).load(path).agg(F.lit(fmt).alias("fmt"), F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("ids"))
        out = one if out is None else out.unionByName(one)
    return out


@query("pipeline_stage_stats", f"WITH {REQUESTS_SQL} SELECT ip % 4 AS part, count(*) AS fetched, CAST(sum(length) AS BIGINT) AS bytes, round(count(*) / ((max(arrive_us) - min(arrive_us)) / 1e6), 6) AS rate, round(sum(length) / 1e6 / ((max(arrive_us) - min(arrive_us)) / 1e6), 9) AS mb_rate, round(sum(length) / count(*), 6) AS bytes_a_page FROM q GROUP BY 1")
def pipeline_stage_stats(spark, sf):
    return measures.speed(requests(spark, sf), F.col("ip") % 4)


@query("measure_link_use", f"WITH {REQUESTS_SQL}, w AS (SELECT arrive_us // {HOUR} AS h, sum(length) * 8 / 3600.0 / 1000.0 AS u FROM q GROUP BY 1) SELECT round(avg(u), 9) AS mean_use, round(max(u), 9) AS peak_use FROM w")
def measure_link_use(spark, sf):
    """Of a link of a thousand bits a second, hour by hour."""
    return measures.link_use(requests(spark, sf), HOUR, 1000.0)


@query("measure_scaling")
def measure_scaling(spark, sf):
    return measures.scaling(store.wl_scale(spark, sf).select("shards", "rate"))


@query("measure_rank_correlation", f"WITH {G2_SQL}, i AS (SELECT n.id, count(e.src) AS d FROM nodes n LEFT JOIN edges e ON e.dst = n.id GROUP BY 1), o AS (SELECT n.id, count(e.dst) AS d FROM nodes n LEFT JOIN edges e ON e.src = n.id GROUP BY 1), r AS (SELECT row_number() OVER (ORDER BY i.d DESC, i.id) AS ra, row_number() OVER (ORDER BY o.d DESC, i.id) AS rb FROM i JOIN o USING (id)) SELECT count(*) AS n, round(corr(ra, rb), 6) AS correlation FROM r")
def measure_rank_correlation(spark, sf):
    """How in- and outdegree rank the parts alike."""
    nodes, edges = overlay.baskets(spark, sf)
    both = graph.degrees(edges, nodes).withColumnRenamed("degree", "i").join(graph.degrees(edges, nodes, "out").withColumnRenamed("degree", "o"), "id")
    return measures.rank_correlation(both, "i", "o")


@query("measure_sketch_error")
def measure_sketch_error(spark, sf):
    """Harmonic centrality of the parts by sketches of 2^10 registers, which balls here exceed, against the exact values."""
    from webgather.operators import balls, centrality, reach

    nodes, edges = overlay.baskets(spark, sf)
    edges, nodes = graph.step_table(edges), graph.step_table(nodes.select("id"))
    sketched = balls.harmonic(edges, nodes, 10) if reach.fits(edges) else centrality.harmonic_sketch(edges, nodes, 10)[0]
    return measures.relative_error(sketched, centrality.harmonic_exact(edges, nodes), "harmonic")


@query("peak_speed", f"WITH {REQUESTS_SQL}, w AS (SELECT arrive_us // {HOUR} AS h, count(*) AS n FROM q GROUP BY 1) SELECT max(n) AS peak, round((SELECT count(*) FROM q) / (max(h) - min(h) + 1), 6) AS mean FROM w")
def peak_speed(spark, sf):
    hours = requests(spark, sf).groupBy(F.floor(F.col("arrive_us") / HOUR).alias("h")).agg(F.count(F.lit(1)).alias("n"))
    return hours.agg(F.max("n").alias("peak"), F.round(F.sum("n") / (F.max("h") - F.min("h") + 1), 6).alias("mean"))


@query("filter_runtime", r"SELECT 0 AS round, count(*) FILTER (regexp_matches(url, '^https?://')) AS kept FROM pages UNION ALL SELECT 1, count(*) FILTER (regexp_matches(url, '^[a-z]+://([^/?#]*\.)?example\.org([/?#:]|$)')) FROM pages")
def filter_runtime(spark, sf):
    """A filter that is read anew each round from a control table."""
    from webgather.operators import filters

    control = spark.createDataFrame([(0, "scheme_in(http, https)"), (1, "domain_in(example.org)")], "round int, text string")
    out = None
    for r in (0, 1):
        text = control.filter(F.col("round") == r).first()["text"]
        one = filters.parse(text).apply(table(spark, sf, "pages")).agg(F.lit(r).alias("round"), F.count(F.lit(1)).alias("kept"))
        out = one if out is None else out.unionByName(one)
    return out


@query("wl_noio", r"""SELECT n AS partitions, count(*) AS pages, CAST(sum(len(regexp_extract_all(html, '(?is)<a\s[^>]*?href\s*=\s*"[^"]*"'))) AS BIGINT) AS links FROM pages, (SELECT unnest([1, 2, 4, 8]) AS n) GROUP BY 1""")
def wl_noio(spark, sf):
    """Parse, digest and count without a sink, by partitions: how many pages and links."""
    from webgather.functions import digests, html

    out = None
    for n in (1, 2, 4, 8):
        pages = table(spark, sf, "pages").repartition(n)
        one = pages.select(F.size(html.links("html")).alias("l"), digests.digest("html").alias("d")).agg(F.lit(n).alias("partitions"), F.count(F.lit(1)).alias("pages"), F.sum("l").alias("links"))
        out = one if out is None else out.unionByName(one)
    return out


@query("wl_powerlaw")
def wl_powerlaw(spark, sf):
    """Exponent, cut, distance and, of 50 replicas, the share that fits no better, for indegrees of pages, of their domains and of the parts."""
    from webgather.operators import powerlaw

    nodes, edges = overlay.web(spark, sf)
    sites = graph.quotient(edges, nodes, "site").select("src", "dst"), nodes.select(F.col("site").alias("id")).distinct()
    parts, next_parts = overlay.baskets(spark, sf)
    out = None
    for name, (arcs, of) in {"web": (edges, nodes), "domains": sites, "baskets": (next_parts, parts)}.items():
        freq = graph.step_table(graph.degree_freq(arcs, of))
        law = powerlaw.fit(freq).select(F.lit(name).alias("graph"), F.round("alpha", 4).alias("alpha"), "xmin", F.round("ks", 4).alias("ks"))
        one = law.crossJoin(F.broadcast(powerlaw.pvalue(freq, 50).select("p")))
        out = one if out is None else out.unionByName(one)
    return out


@query("wl_cache")
def wl_cache(spark, sf):
    """Discarded share by capacity, exact and windowed: over nine tenths once the cache holds what is in use."""
    from webgather.operators import cache
    from webgather.plans.gather import stream as references

    s, out = references(spark, sf), None
    for c in (16, 256, 1024, 4096):
        both = [cache.summary(f(s, c)).select(F.lit(k).alias("form"), F.lit(c).alias("capacity"), "share") for k, f in (("windowed", cache.windowed), ("exact", cache.exact_lru))]
        for one in both:
            out = one if out is None else out.unionByName(one)
    return out


@query("wl_once_variants", f"WITH {BATCHED_SQL.replace('r AS (', 'rel AS (')}, {_bloom_sql('4096', '3')} SELECT 'exact' AS variant, count(*) AS released FROM f UNION ALL SELECT 'batched', count(*) FROM rel UNION ALL SELECT 'bloom', count(*) FILTER (released) FROM r UNION ALL SELECT 'fingerprints', count(DISTINCT CAST('0x' || substr(md5(CAST(key AS VARCHAR)), 1, 15) AS BIGINT) % 4096) FROM f")
def wl_once_variants(spark, sf):
    """What each once-filter releases of the same stream, and what it loses."""
    from webgather.operators import seen
    from webgather.plans.gather import stream as references

    s = references(spark, sf)
    n = F.count(F.lit(1))
    rows = {"exact": seen.exact(s).agg(n.alias("released")), "batched": seen.batched(s, 4096).agg(n.alias("released")), "bloom": seen.bloom(s, 4096, 3).agg(F.count_if("released").alias("released")), "fingerprints": seen.fingerprint_set(s, 12).agg(n.alias("released"))}
    out = None
    for name, one in rows.items():
        one = one.select(F.lit(name).alias("variant"), "released")
        out = one if out is None else out.unionByName(one)
    return out


@query("wl_ring", f"SELECT b.*, c.*, l.share AS locality FROM ({ORACLES['ring_balance']}) b, ({ORACLES['ring_change']}) c, ({ORACLES['link_locality']}) l")
def wl_ring(spark, sf):
    b, m = store.ring_balance(spark, sf), store.ring_change(spark, sf)
    return b.crossJoin(m).crossJoin(store.link_locality(spark, sf).select(F.col("share").alias("locality")))


@query("wl_centrality")
def wl_centrality(spark, sf):
    """Top tens by three measures on the host, site and brand graphs."""
    from webgather.operators import centrality, graph, overlay
    from webgather.plans import snapshot

    out = None
    for name, (nodes, edges) in {"host": snapshot.host_web(spark, sf), "site": snapshot.host_web(spark, sf, "site"), "brand": ((lambda g: (g[0].select(F.col("host").alias("id")).distinct(), graph.quotient(g[1], g[0], "host")))(overlay.baskets(spark, sf)))}.items():
        one = centrality.table(graph.step_table(edges.select("src", "dst")), graph.step_table(nodes), iterations=12).select(F.lit(name).alias("graph"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query("stream_sessions", f"WITH {REQUESTS_SQL}, g AS (SELECT host, arrive_us, CASE WHEN arrive_us - lag(arrive_us) OVER (PARTITION BY host ORDER BY arrive_us) < {6 * HOUR} THEN 0 ELSE 1 END AS new FROM q), s AS (SELECT host, arrive_us, sum(new) OVER (PARTITION BY host ORDER BY arrive_us ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM g) SELECT host, min(arrive_us) AS from_us, count(*) AS n FROM s GROUP BY host, k")
def stream_sessions(spark, sf):
    """A host's activity, parted where it rests for six hours."""
    rows = requests(spark, sf).withColumn("ts", F.timestamp_micros("arrive_us"))
    live = stream.replay(spark, rows, place(spark), 2, "seq")
    sessions = live.withWatermark("ts", "31 days").groupBy(F.session_window("ts", "6 hours"), "host").agg(F.count(F.lit(1)).alias("n"))
    return stream.run(sessions.select("host", F.unix_micros("session_window.start").alias("from_us"), "n"), "complete")


@query("stream_stream_join", f"WITH {REQUESTS_SQL}, b AS (SELECT host, arrive_us AS t FROM q) SELECT seq, count(*) AS near FROM q JOIN b ON q.host = b.host AND t BETWEEN arrive_us AND arrive_us + {24 * HOUR} GROUP BY 1")
def stream_stream_join(spark, sf):
    """Each request with those of its host in the day that follows, itself among them."""
    rows = requests(spark, sf).withColumn("ts", F.timestamp_micros("arrive_us"))
    a = stream.replay(spark, rows.select("seq", "host", "ts"), place(spark), 2, "seq").withWatermark("ts", "2 days")
    b = stream.replay(spark, rows.select("seq", F.col("host").alias("h"), F.col("ts").alias("t")), place(spark), 2, "seq").drop("seq").withWatermark("t", "2 days")
    joined = a.join(b, F.expr("host = h AND t >= ts AND t <= ts + INTERVAL 1 DAY")).select("seq", "h")
    return stream.run(joined).groupBy("seq").agg(F.count(F.lit(1)).alias("near"))
