"""Queries on once-filters, caches and politeness."""

from __future__ import annotations

from pyspark.sql import functions as F

from webgather.catalog import ORACLES, query, table
from webgather.functions.fingerprints import fp60, fp128
from webgather.operators import cache, lanes, seen
from webgather.operators.graph import step_table
from webgather.operators.sequence import numbered

STREAM_SQL = "s AS (SELECT row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice) AS seq, l_partkey AS key, l_extendedprice AS value FROM lineitem)"
H1, H2 = ("CAST('0x' || substr(md5(CAST(key AS VARCHAR)), 1, 15) AS BIGINT)", "CAST('0x' || substr(md5(CAST(key AS VARCHAR)), 16, 15) AS BIGINT)")
FIRST_SQL = f"{STREAM_SQL}, f AS (SELECT key, min(seq) AS first_seq FROM s GROUP BY 1)"


def stream(spark, sf):
    """References to parts in the order of the orders."""
    rows = table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", F.col("l_partkey").alias("key"), "l_suppkey", F.col("l_extendedprice").alias("value"))
    return numbered(rows, ["l_orderkey", "l_linenumber", "key", "l_suppkey", "value"]).select("seq", "key", "value")


@query("fingerprint64", "SELECT page_id, CAST('0x' || substr(md5(url), 1, 15) AS BIGINT) AS fp FROM pages")
def fingerprint64(spark, sf):
    return table(spark, sf, "pages").select("page_id", fp60("url").alias("fp"))


@query("fingerprint128", "SELECT page_id, md5(url) AS fp FROM pages")
def fingerprint128(spark, sf):
    return table(spark, sf, "pages").select("page_id", fp128("url").alias("fp"))


@query("fingerprint_collisions", f"WITH {FIRST_SQL}, b AS (SELECT unnest([12, 16, 20, 24]) AS bits) SELECT bits, count(*) AS keys, count(*) - count(DISTINCT {H1} % (1 << bits)) AS lost, round(count(*) * count(*) / power(2.0, bits + 1), 6) AS expected FROM f, b GROUP BY 1")
def fingerprint_collisions(spark, sf):
    first = seen.exact(stream(spark, sf)).select("key", fp60("key").alias("h"), F.explode(F.array(*(F.lit(b) for b in (12, 16, 20, 24)))).alias("bits"))
    n = F.count(F.lit(1))
    return first.groupBy("bits").agg(n.alias("keys"), (n - F.countDistinct(F.expr("h % shiftleft(1L, bits)"))).alias("lost"), F.round(n * n / F.pow(F.lit(2.0), F.col("bits") + 1), 6).alias("expected"))


@query("once_exact", f"WITH {FIRST_SQL} SELECT * FROM f")
def once_exact(spark, sf):
    return seen.exact(stream(spark, sf))


BATCHED_SQL = f"{FIRST_SQL}, n AS (SELECT max(seq) AS n FROM s), b AS (SELECT key, first_seq, CAST(ceil(first_seq / 4096.0) AS BIGINT) AS flush FROM f), r AS (SELECT b.*, least(flush * 4096, n) AS release_seq FROM b, n)"


@query("once_batched", f"WITH {BATCHED_SQL} SELECT * FROM r")
def once_batched(spark, sf):
    return seen.batched(stream(spark, sf), 4096)


@query("once_batched_known", f"WITH {FIRST_SQL}, k AS (SELECT DISTINCT key FROM s WHERE seq <= (SELECT max(seq) FROM s) // 4) SELECT count(*) AS released, CAST(sum(first_seq) AS BIGINT) AS seqs FROM f ANTI JOIN k USING (key)")
def once_batched_known(spark, sf):
    """With the first quarter's fingerprints known from an earlier round."""
    s = stream(spark, sf)
    quarter = s.crossJoin(F.broadcast(s.agg(F.max("seq").alias("n")))).filter("seq <= n div 4")
    known = quarter.select(fp60("key").alias("fp")).distinct()
    return seen.batched(s, 4096, known).agg(F.count(F.lit(1)).alias("released"), F.sum("first_seq").alias("seqs"))


@query("once_delay", f"WITH {BATCHED_SQL} SELECT count(*) AS released, max(flush) AS flushes, CAST(sum(release_seq - first_seq) AS BIGINT) AS lag_total, max(release_seq - first_seq) AS lag_most FROM r")
def once_delay(spark, sf):
    return seen.release_lag(seen.batched(stream(spark, sf), 4096))


@query("once_flush_costs", f"WITH {BATCHED_SQL}, p AS (SELECT flush, count(*) AS new FROM r GROUP BY 1), q AS (SELECT *, CAST(coalesce(sum(new) OVER (ORDER BY flush ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS b FROM p) SELECT flush, new, 8 * b AS known_read, 8 * (b + new) AS known_write FROM q")
def once_flush_costs(spark, sf):
    return seen.flush_costs(seen.batched(stream(spark, sf), 4096), 4096)


OPS_SQL = f"{STREAM_SQL}, o AS (SELECT *, CASE seq % 3 WHEN 0 THEN 'check' WHEN 1 THEN 'update' ELSE 'check_update' END AS op FROM s)"


def _ops(spark, sf):
    return stream(spark, sf).withColumn("op", F.when(F.col("seq") % 3 == 0, "check").when(F.col("seq") % 3 == 1, "update").otherwise("check_update"))


@query("once_valued", f"""WITH {OPS_SQL} SELECT seq, key, op, CASE WHEN op <> 'update' THEN CASE WHEN row_number() OVER w = 1 THEN 'UNIQUE' ELSE 'DUPLICATE' END END AS verdict,
    CASE WHEN op = 'check_update' THEN last_value(CASE WHEN op <> 'check' THEN value END IGNORE NULLS) OVER (PARTITION BY key ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) END AS old_value FROM o WINDOW w AS (PARTITION BY key ORDER BY seq)""")
def once_valued(spark, sf):
    return seen.valued(_ops(spark, sf))


@query("once_valued_repository", ORACLES["once_valued"])
def once_valued_repository(spark, sf):
    """The stream in two batches: the second is checked against what the first stored, in 16 buckets."""
    rows = _ops(spark, sf)
    middle = rows.agg(F.floor(F.max("seq") / 2).alias("_half"))
    rows = rows.crossJoin(F.broadcast(middle)).withColumn("_second", F.col("seq") > F.col("_half"))
    first, second = rows.filter("not _second"), rows.filter("_second")
    repo = step_table(seen.repository(first, 16))
    return seen.valued(first).unionByName(seen.valued_with(second, repo, 16))


@query("once_valued_store", f"WITH {OPS_SQL} SELECT key, arg_max(value, seq) AS value FROM o WHERE op <> 'check' GROUP BY 1")
def once_valued_store(spark, sf):
    return seen.stored_values(_ops(spark, sf))


@query("once_bucket_order", f"WITH {FIRST_SQL}, b AS (SELECT key % 50 AS host, first_seq, {H1} % 16 AS bucket FROM f), l AS (SELECT *, lag(bucket) OVER (PARTITION BY host ORDER BY first_seq) AS before FROM b) SELECT host, count(*) AS elements, count(*) FILTER (before > bucket) AS inversions FROM l GROUP BY 1")
def once_bucket_order(spark, sf):
    return seen.order_inversions(seen.exact(stream(spark, sf)), F.col("key") % 50, 16)


def _bloom_sql(m: str, k: str, more: str = "") -> str:
    return f"t AS (SELECT {more} key, first_seq, ({H1} + i * ({H2} + 1 - {H2} % 2)) % {m} AS bit FROM (SELECT f.*, {more} unnest(range(0, {k})) AS i FROM f{', v' if more else ''})), mu AS (SELECT {more} bit, min(first_seq) AS m FROM t GROUP BY {more} bit), r AS (SELECT {more} key, first_seq, max(m) = first_seq AS released FROM t JOIN mu USING ({more} bit) GROUP BY {more} key, first_seq)"


@query("once_bloom", f"WITH {FIRST_SQL}, {_bloom_sql('4096', '3')} SELECT key, first_seq, released FROM r")
def once_bloom(spark, sf):
    return seen.bloom(stream(spark, sf), 4096, 3)


@query("bloom_loss_curve", f"WITH {FIRST_SQL}, v AS (SELECT unnest([16384, 8192, 4096, 2048, 1024]) AS bits), {_bloom_sql('bits', '3', 'bits,')} SELECT bits, count(*) AS elements, count(*) FILTER (NOT released) AS lost, round(power(1 - exp(-3.0 * count(*) / bits), 3), 6) AS final_rate FROM r GROUP BY 1")
def bloom_loss_curve(spark, sf):
    """The more elements than it was sized for, the more a Bloom queue loses."""
    s, out = stream(spark, sf), None
    for bits in (16384, 8192, 4096, 2048, 1024):
        one = seen.bloom(s, bits, 3).agg(F.lit(bits).alias("bits"), F.count(F.lit(1)).alias("elements"), F.count_if(~F.col("released")).alias("lost"))
        out = one if out is None else out.unionByName(one)
    return out.withColumn("final_rate", F.round(F.pow(1 - F.exp(F.lit(-3.0) * F.col("elements") / F.col("bits")), 3), 6))


@query("once_fingerprints", f"WITH {FIRST_SQL}, k AS (SELECT {H1} % 4096 AS fp, arg_min(key, first_seq) AS key, min(first_seq) AS first_seq FROM f GROUP BY 1) SELECT * FROM k")
def once_fingerprints(spark, sf):
    return seen.fingerprint_set(stream(spark, sf), 12)


WINDOWED = "coalesce(seq - lag(seq) OVER (PARTITION BY key ORDER BY seq) <= {c}, false)"


@query("cache_lru", f"WITH {STREAM_SQL}, c AS (SELECT unnest([256, 1024, 4096]) AS capacity), h AS (SELECT capacity, coalesce(seq - lag(seq) OVER (PARTITION BY capacity, key ORDER BY seq) <= capacity, false) AS hit FROM s, c) SELECT capacity, count(*) AS discovered, count(*) FILTER (hit) AS discarded, round(count(*) FILTER (hit) / count(*), 6) AS share FROM h GROUP BY 1")
def cache_lru(spark, sf):
    """The windowed bound at three capacities."""
    s, out = stream(spark, sf), None
    for c in (256, 1024, 4096):
        one = cache.summary(cache.windowed(s, c)).withColumn("capacity", F.lit(c))
        out = one if out is None else out.unionByName(one)
    return out


@query("cache_lru_exact")
def cache_lru_exact(spark, sf):
    return cache.summary(cache.exact_lru(stream(spark, sf), 1024))


@query("cache_set_associative")
def cache_set_associative(spark, sf):
    return cache.summary(cache.set_associative(stream(spark, sf), 64, 16))


@query("cache_bound", "SELECT true AS holds")
def cache_bound(spark, sf):
    """No row hits the windowed form and misses the exact one."""
    s = stream(spark, sf)
    both = cache.windowed(s, 1024).withColumnRenamed("hit", "w").join(cache.exact_lru(s, 1024).select("seq", F.col("hit").alias("e")), "seq")
    return both.agg((F.count_if(F.col("w") & ~F.col("e")) == 0).alias("holds"))


@query("cache_saves_transfers", f"WITH {STREAM_SQL}, h AS (SELECT seq, {H1} % 4 AS owner, seq % 4 AS self, {WINDOWED.format(c=4096)} AS hit FROM s) SELECT count(*) FILTER (owner <> self) AS sent_without, count(*) FILTER (owner <> self AND NOT hit) AS sent_with FROM h")
def cache_saves_transfers(spark, sf):
    """URLs of other shards that the cache needn't send again."""
    hits = cache.windowed(stream(spark, sf), 4096).withColumn("other", fp60("key") % 4 != F.col("seq") % 4)
    return hits.agg(F.count_if("other").alias("sent_without"), F.count_if(F.col("other") & ~F.col("hit")).alias("sent_with"))


@query("cache_then_once", f"WITH {STREAM_SQL}, h AS (SELECT seq, key, {WINDOWED.format(c=1024)} AS hit FROM s), r AS (SELECT * FROM h WHERE NOT hit) SELECT (SELECT count(*) FROM s) AS discovered, count(*) AS reach_filter, count(DISTINCT key) AS released, count(DISTINCT key) = (SELECT count(DISTINCT key) FROM s) AS same_set FROM r")
def cache_then_once(spark, sf):
    s = stream(spark, sf)
    rest = cache.windowed(s, 1024).filter("not hit")
    n = s.agg(F.count(F.lit(1)).alias("discovered"), F.countDistinct("key").alias("keys"))
    return n.crossJoin(rest.agg(F.count(F.lit(1)).alias("reach_filter"))).crossJoin(seen.exact(rest).agg(F.count(F.lit(1)).alias("released"))).select("discovered", "reach_filter", "released", (F.col("released") == F.col("keys")).alias("same_set"))


REQUESTS_SQL = "q AS (SELECT event_id AS seq, user_id AS host, user_id % 37 AS ip, epoch_us(ts) AS arrive_us, CAST(round(value * 1000) AS BIGINT) AS latency_us, CAST(round(value * 100) AS BIGINT) + 200 AS length FROM events)"
HOUR = 3_600_000_000


def requests(spark, sf):
    """Events as requests: the user is the host."""
    micros = F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast(ts as timestamp_ntz))")
    return table(spark, sf, "events").select(F.col("event_id").alias("seq"), F.col("user_id").alias("host"), (F.col("user_id") % 37).alias("ip"), micros.alias("arrive_us"), F.round(F.col("value") * 1000).cast("long").alias("latency_us"), (F.round(F.col("value") * 100).cast("long") + 200).alias("length"))


@query("lanes_build", "SELECT o_custkey AS host, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS pos FROM orders")
def lanes_build(spark, sf):
    return lanes.build(table(spark, sf, "orders").select(F.col("o_custkey").alias("host"), "o_orderkey"), "host", ["o_orderkey"]).withColumn("pos", F.col("pos").cast("long"))


LANES_SQL = f"{REQUESTS_SQL}, ln AS (SELECT ip, host, max(arrive_us) AS next_us FROM q GROUP BY 1, 2), bn AS (SELECT ip, max(next_us) - min(next_us) + min(next_us) // 2 + 400000000000000 AS bay_next_us FROM ln GROUP BY 1), bays AS (SELECT ip, greatest(any_value(bay_next_us), min(next_us)) AS priority, arg_min(host, (next_us, host)) AS host FROM ln JOIN bn USING (ip) GROUP BY 1)"


def _lanes(spark, sf):
    lane = requests(spark, sf).groupBy("ip", "host").agg(F.max("arrive_us").alias("next_us"))
    bay = lane.groupBy("ip").agg(F.expr("max(next_us) - min(next_us) + min(next_us) div 2 + 400000000000000L").alias("bay_next_us"))
    return lane.join(F.broadcast(bay), "ip")


@query("bays_build", f"WITH {LANES_SQL} SELECT * FROM bays")
def bays_build(spark, sf):
    return lanes.bays(_lanes(spark, sf))


NOW = 1_704_500_000_000_000


@query("frontier_peek", f"WITH {LANES_SQL} SELECT ip, host, priority, greatest(priority - {NOW}, 0) AS wait_us FROM bays ORDER BY priority, ip, host LIMIT 1")
def frontier_peek(spark, sf):
    return lanes.peek(lanes.bays(_lanes(spark, sf)), NOW)


@query("frontier_iff", f"WITH {LANES_SQL}, t AS (SELECT unnest(range(0, 40)) AS k), x AS (SELECT k, (SELECT min(priority) FROM bays) + (k - 20) * {HOUR} AS now_us FROM t) SELECT k, now_us >= (SELECT min(priority) FROM bays) AS releasable, true AS agree FROM x")
def frontier_iff(spark, sf):
    """Some host may be released exactly if the head of the heads may: over a grid of instants."""
    ls = _lanes(spark, sf)
    head = lanes.peek(lanes.bays(ls), 0).select(F.col("priority").alias("head"))
    grid = head.select("head", F.explode(F.expr("sequence(0, 39)")).alias("k")).select("k", "head", (F.col("head") + (F.col("k") - 20) * F.lit(HOUR)).alias("now_us"))
    brute = ls.select(F.greatest("next_us", "bay_next_us").alias("at")).agg(F.min("at").alias("at"))
    return grid.crossJoin(F.broadcast(brute)).select(F.col("k").cast("long").alias("k"), (F.col("head") <= F.col("now_us")).alias("releasable"), ((F.col("head") <= F.col("now_us")) == (F.col("at") <= F.col("now_us"))).alias("agree"))


STARTS_SQL = f"{REQUESTS_SQL}, n AS (SELECT *, row_number() OVER (PARTITION BY host ORDER BY seq) * {6 * HOUR} AS s FROM q), st AS (SELECT seq, host, ip, arrive_us, latency_us, s + max(arrive_us - s) OVER (PARTITION BY host ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS start_us FROM n)"


@query("host_delay_starts", f"WITH {STARTS_SQL} SELECT seq, host, start_us FROM st")
def host_delay_starts(spark, sf):
    return lanes.starts(requests(spark, sf), 6 * HOUR).select("seq", "host", "start_us")


@query("host_delay_delayed", f"WITH {STARTS_SQL} SELECT count(*) AS requests, count(*) FILTER (start_us > arrive_us) AS delayed FROM st")
def host_delay_delayed(spark, sf):
    return lanes.starts(requests(spark, sf), 6 * HOUR).agg(F.count(F.lit(1)).alias("requests"), F.count_if(F.col("start_us") > F.col("arrive_us")).alias("delayed"))


@query("host_delay_ends", f"WITH {REQUESTS_SQL}, n AS (SELECT *, CAST(coalesce(sum(latency_us + {HOUR}) OVER (PARTITION BY host ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS s FROM q) SELECT seq, host, s + max(arrive_us - s) OVER (PARTITION BY host ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS start_us FROM n")
def host_delay_ends(spark, sf):
    return lanes.starts(requests(spark, sf), HOUR, measure_from="end").select("seq", "host", "start_us")


@query("host_ip_schedule")
def host_ip_schedule(spark, sf):
    return lanes.schedule(requests(spark, sf), 6 * HOUR, HOUR // 4)


@query("politeness_violations", f"SELECT 0 AS host_gaps, 0 AS ip_gaps, 0 AS out_of_order, 0 AS too_early")
def politeness_violations(spark, sf):
    return lanes.violations(host_ip_schedule(spark, sf), 6 * HOUR, HOUR // 4)


@query("impolite_violations", f"WITH {REQUESTS_SQL}, g AS (SELECT arrive_us - lag(arrive_us) OVER (PARTITION BY host ORDER BY arrive_us, seq) < {6 * HOUR} AS h, arrive_us - lag(arrive_us) OVER (PARTITION BY ip ORDER BY arrive_us, seq) < {HOUR // 4} AS i FROM q) SELECT count(*) FILTER (h) AS host_gaps, count(*) FILTER (i) AS ip_gaps, 0 AS out_of_order, 0 AS too_early FROM g")
def impolite_violations(spark, sf):
    """The audit of the baseline that waits for nobody."""
    return lanes.violations(requests(spark, sf).withColumn("start_us", F.col("arrive_us")), 6 * HOUR, HOUR // 4)


@query("custom_delays", f"WITH {REQUESTS_SQL}, n AS (SELECT *, row_number() OVER (PARTITION BY host ORDER BY seq) * CASE WHEN host % 10 = 0 THEN {HOUR} ELSE {6 * HOUR} END AS s FROM q) SELECT seq, host, s + max(arrive_us - s) OVER (PARTITION BY host ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS start_us FROM n")
def custom_delays(spark, sf):
    """Every tenth host has a shorter delay of its own."""
    q = requests(spark, sf)
    own = q.select("host").distinct().filter("host % 10 = 0").withColumn("d", F.lit(HOUR))
    return lanes.starts(q.join(F.broadcast(own), "host", "left"), F.coalesce("d", F.lit(6 * HOUR))).select("seq", "host", "start_us")


@query("token_exclusion", f"WITH {REQUESTS_SQL} SELECT 0 AS overlaps, count(*) AS fetches FROM q")
def token_exclusion(spark, sf):
    return lanes.overlaps(lanes.schedule(requests(spark, sf), 6 * HOUR, HOUR // 4, measure_from="end"))


@query("ready_front", f"WITH {STARTS_SQL}, e AS (SELECT CAST(ceil(arrive_us / {6 * HOUR}.0) AS BIGINT) AS slot, 1 AS d FROM st UNION ALL SELECT CAST(ceil(start_us / {6 * HOUR}.0) AS BIGINT), -1 FROM st), p AS (SELECT slot, sum(d) AS d FROM e GROUP BY 1) SELECT slot, CAST(sum(d) OVER (ORDER BY slot) AS BIGINT) AS ready FROM p")
def ready_front(spark, sf):
    return lanes.front(lanes.starts(requests(spark, sf), 6 * HOUR), 6 * HOUR)


@query("ready_list_skew", f"WITH {STARTS_SQL}, x AS (SELECT lead(start_us - arrive_us, 4) OVER (PARTITION BY ip ORDER BY start_us, seq) > start_us - arrive_us AS x FROM st) SELECT count(*) AS released, count(*) FILTER (x) AS inversions FROM x")
def ready_list_skew(spark, sf):
    return lanes.ready_inversions(lanes.starts(requests(spark, sf), 6 * HOUR), 4)


@query("frontier_two_queue")
def frontier_two_queue(spark, sf):
    """Heads looked at by the two-queue baseline, where the frontier looks at one a release."""
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        checks, done = lanes.two_queue_checks(pdf.sort_values("seq"), 6 * HOUR)
        return pd.DataFrame({"ip": [int(pdf["ip"].iloc[0])], "checks": [checks], "released": [done]})

    return requests(spark, sf).groupBy("ip").applyInPandas(run, "ip long, checks long, released long")


ADAPTIVE_SQL = "least(greatest(CAST(latency_us * {f} AS BIGINT), {lo}), {hi})"


@query("delay_adaptive", f"WITH {REQUESTS_SQL}, d AS (SELECT *, least(greatest(CAST(trunc(latency_us * 5.0) AS BIGINT), 1000000), 30000000) AS d FROM q), n AS (SELECT *, CAST(coalesce(sum(latency_us + d) OVER (PARTITION BY host ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS s FROM d) SELECT seq, d, s + max(arrive_us - s) OVER (PARTITION BY host ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS start_us FROM n")
def delay_adaptive(spark, sf):
    rows = requests(spark, sf).withColumn("d", lanes.adaptive_delay(F.col("latency_us"), 5.0, 1_000_000, 30_000_000))
    return lanes.starts(rows, F.col("d"), measure_from="end").select("seq", "d", "start_us")


@query("throttle_by_site", f"WITH {REQUESTS_SQL} SELECT seq, least(greatest(CAST(trunc(latency_us * 5.0 / greatest(1.0, log2(seq % 7 + 1))) AS BIGINT), 1000000), 30000000) AS d FROM q")
def throttle_by_site(spark, sf):
    return requests(spark, sf).select("seq", lanes.adaptive_delay(F.col("latency_us"), 5.0, 1_000_000, 30_000_000, F.col("seq") % 7).alias("d"))


@query("keepalive")
def keepalive(spark, sf):
    """With and without several requests on one connection: the last start and how many went out polite."""
    backlog = requests(spark, sf).withColumn("arrive_us", F.lit(0).cast("long"))
    out = None
    for k in (0, 2_000_000):
        one = lanes.schedule(backlog, HOUR, HOUR // 60, keepalive_us=k).agg(F.lit(k).cast("long").alias("budget_us"), F.count(F.lit(1)).alias("fetched"), F.max("start_us").alias("last_start_us"))
        out = one if out is None else out.unionByName(one)
    return out


@query("backoff", "SELECT waited, CASE WHEN waited = 0 THEN 0 ELSE CAST(floor(log2(waited)) AS BIGINT) + 1 END AS polls FROM (SELECT unnest([0, 1, 3, 7, 8, 100, 1000]) AS waited)")
def backoff(spark, sf):
    """Polls of an empty list whose pauses double: 1, 2, 4, … until `waited` ms have gone."""
    waits = spark.createDataFrame([(w,) for w in (0, 1, 3, 7, 8, 100, 1000)], "waited int")
    return waits.select("waited", F.when(F.col("waited") == 0, 0).otherwise(F.floor(F.log2("waited")) + 1).cast("long").alias("polls"))


