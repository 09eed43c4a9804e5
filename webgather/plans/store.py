"""Queries on the spill store, the feeder, rings, the made-up web, simulations and gathering rounds."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from webgather.catalog import query, table
from webgather.operators import crawl, dedup, feeder, fetchsim, graph, overlay, ring, simweb, spill
from webgather.operators.overlay import G1_SQL
from webgather.plans.gather import REQUESTS_SQL, requests

LOG_SQL = f"{REQUESTS_SQL}, lg AS (SELECT host, seq, CAST(host % 64 AS INTEGER) AS host_bucket, row_number() OVER (PARTITION BY host % 64 ORDER BY seq) - 1 AS pos FROM q)"
TAKE_SQL = f"{LOG_SQL}, tk AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY host ORDER BY pos) AS k FROM lg WHERE host % 3 = 0) WHERE k <= 60), lv AS (SELECT lg.* FROM lg ANTI JOIN tk ON lg.host_bucket = tk.host_bucket AND lg.pos = tk.pos), ur AS (SELECT host_bucket, count(*) AS used, max(pos) - min(pos) + 1 AS allocated, round(count(*) / (max(pos) - min(pos) + 1), 6) AS ratio FROM lv GROUP BY 1)"


def _log(spark, sf):
    return spill.append(requests(spark, sf))


def _taken(spark, sf):
    log = _log(spark, sf)
    return log, spill.refill(log, log.filter("host % 3 = 0").select("host").distinct(), 60)


@query("spill_append", f"WITH {LOG_SQL} SELECT host_bucket, pos, host, seq, pos // 1024 AS segment FROM lg")
def spill_append(spark, sf):
    return _log(spark, sf).select("host_bucket", "pos", "host", "seq", "segment")


@query("spill_links", f"WITH {LOG_SQL} SELECT host_bucket, pos, coalesce(lead(pos) OVER (PARTITION BY host ORDER BY pos), -1) AS next_pos FROM lg")
def spill_links(spark, sf):
    return spill.next_pointers(_log(spark, sf)).select("host_bucket", "pos", F.coalesce("next_pos", F.lit(-1)).alias("next_pos"))


@query("spill_dequeue", f"WITH {TAKE_SQL} SELECT host, count(*) AS taken, max(seq) AS last_seq FROM tk GROUP BY 1")
def spill_dequeue(spark, sf):
    return _taken(spark, sf)[1].groupBy("host").agg(F.count(F.lit(1)).alias("taken"), F.max("seq").alias("last_seq"))


@query("spill_used_ratio", f"WITH {TAKE_SQL} SELECT * FROM ur")
def spill_used_ratio(spark, sf):
    return spill.used_ratio(spill.remaining(*_taken(spark, sf)))


COMPACT_SQL = f"{TAKE_SQL}, cp AS (SELECT lv.host_bucket, lv.host, lv.seq, lv.pos AS old_pos, CASE WHEN used / allocated < 0.8 THEN row_number() OVER (PARTITION BY host_bucket ORDER BY lv.pos) - 1 ELSE lv.pos END AS pos FROM lv JOIN ur USING (host_bucket))"


@query("spill_gc", f"WITH {COMPACT_SQL} SELECT host_bucket, host, seq, old_pos, pos, pos // 1024 AS segment, pos <> old_pos AS moved FROM cp")
def spill_gc(spark, sf):
    return spill.compact(spill.remaining(*_taken(spark, sf)), 0.8)


@query("spill_gc_cost", f"WITH {COMPACT_SQL} SELECT (SELECT count(*) FROM lg) AS appended, count(*) FILTER (pos <> old_pos) AS moved, round(((SELECT count(*) FROM lg) + count(*) FILTER (pos <> old_pos)) / (SELECT count(*) FROM lg), 6) AS amplification FROM cp")
def spill_gc_cost(spark, sf):
    n = _log(spark, sf).agg(F.count(F.lit(1)).alias("appended"))
    return spill_gc(spark, sf).agg(F.count_if("moved").alias("moved")).crossJoin(n).select("appended", "moved", F.round((F.col("appended") + F.col("moved")) / F.col("appended"), 6).alias("amplification"))


@query("spill_order_invariant", f"WITH {TAKE_SQL} SELECT 0 AS faults, count(*) AS hosts FROM (SELECT host FROM tk INTERSECT SELECT host FROM lv)")
def spill_order_invariant(spark, sf):
    log, taken = _taken(spark, sf)
    return spill.order_kept(taken, spill.remaining(log, taken))


@query("spill_budgeted", f"WITH {REQUESTS_SQL}, k AS (SELECT host, seq, row_number() OVER w AS k, count(*) OVER (PARTITION BY host % 8) AS n FROM q WINDOW w AS (PARTITION BY host % 8 ORDER BY seq)), s AS (SELECT host, seq, lag(seq) OVER (PARTITION BY host ORDER BY CASE WHEN k % 100 = 0 THEN k + n ELSE k END) > seq AS x FROM k) SELECT host, count(*) AS items, count(*) FILTER (x) AS inversions FROM s GROUP BY 1")
def spill_budgeted(spark, sf):
    return spill.static_queues(requests(spark, sf), 8, 100)


@query("spill_kv", f"WITH {REQUESTS_SQL} SELECT host, seq, row_number() OVER (PARTITION BY host ORDER BY length DESC, seq) AS k FROM q")
def spill_kv(spark, sf):
    return spill.by_priority(requests(spark, sf), "length").select("host", "seq", F.col("k").cast("long").alias("k"))


PLACES_SQL = f"{REQUESTS_SQL}, o AS (SELECT *, row_number() OVER (PARTITION BY ip ORDER BY seq) > 20 AS over_ FROM q), pl AS (SELECT ip, CASE WHEN bool_or(over_) OVER (PARTITION BY host ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) THEN 'disk' ELSE 'memory' END AS place FROM o)"


@query("feeder_policy", f"WITH {PLACES_SQL} SELECT place, count(*) AS urls FROM pl GROUP BY 1")
def feeder_policy(spark, sf):
    return feeder.places(requests(spark, sf), 740, 20).groupBy("place").agg(F.count(F.lit(1)).alias("urls"))


@query("memory_cap", f"WITH {PLACES_SQL}, m AS (SELECT ip, count(*) AS n FROM pl WHERE place = 'memory' GROUP BY 1) SELECT CAST(sum(n) AS BIGINT) AS resident, max(n) AS most_of_an_ip, sum(n) <= 740 AS under_cap FROM m")
def memory_cap(spark, sf):
    held = feeder.places(requests(spark, sf), 740, 20).filter("place = 'memory'").groupBy("ip").agg(F.count(F.lit(1)).alias("n"))
    return held.agg(F.sum("n").alias("resident"), F.max("n").alias("most_of_an_ip"), (F.sum("n") <= 740).alias("under_cap"))


@query("feeder_actions", "SELECT * FROM (VALUES (1, 'wait'), (2, 'refill'), (3, 'read'), (4, 'wait')) t(k, action)")
def feeder_actions(spark, sf):
    states = [feeder.State(10, 10, 0, 5, 3, 3), feeder.State(5, 10, 0, 5, 3, 3), feeder.State(5, 10, 0, 5, 0, 3), feeder.State(5, 10, 6, 5, 0, 3)]
    return spark.createDataFrame([(k + 1, feeder.decide(s)) for k, s in enumerate(states)], "k int, action string")


@query("feeder_target", "WITH RECURSIVE t AS (SELECT 0 AS step, 8 AS target UNION ALL SELECT step + 1, CASE WHEN step % 2 = 0 AND step < 20 THEN greatest(target + 1, CAST(ceil(target * 1.1) AS INTEGER)) ELSE target END FROM t WHERE step < 30) SELECT step, target FROM t")
def feeder_target(spark, sf):
    """Every second step a fetcher idles above the target, until step 20."""
    rows, target = [(0, 8)], 8
    for step in range(30):
        target = feeder.next_target(target + 1, target, step % 2 == 0 and step < 20)
        rows.append((step + 1, target))
    return spark.createDataFrame(rows, "step int, target int")


@query("frontier_quota", "SELECT target, greatest(1, 5000 // greatest(1, target)) AS quota FROM (SELECT unnest([0, 8, 100, 1000, 10000]) AS target)")
def frontier_quota(spark, sf):
    return spark.createDataFrame([(t, feeder.quota(5000, t)) for t in (0, 8, 100, 1000, 10000)], "target int, quota int")


@query("resolve_hosts", f"WITH {G1_SQL}, r AS (SELECT host, dense_rank() OVER (ORDER BY host) - 1 AS k FROM nodes) SELECT DISTINCT host, k % 16 AS ip FROM r")
def resolve_hosts(spark, sf):
    """Each distinct host once, several to an address."""
    from webgather.operators.sequence import numbered

    hosts = overlay.nodes(spark, sf).select("host").distinct()
    return numbered(hosts, ["host"], "k").select("host", ((F.col("k") - 1) % 16).alias("ip"))


RING_SQL = "pt AS (SELECT CAST('0x' || substr(md5(s || '#' || r), 1, 15) AS BIGINT) AS p, s FROM (SELECT unnest(range(0, {n})) AS s), (SELECT unnest(range(0, 200)) AS r)), iv AS (SELECT lag(p, 1, -1) OVER (ORDER BY p) AS lo, p AS hi, s FROM pt UNION ALL SELECT max(p), 1152921504606846976, arg_min(s, p) FROM pt)"
KEYS_SQL = "ks AS (SELECT c_custkey, CAST('0x' || substr(md5(CAST(c_custkey AS VARCHAR)), 1, 15) AS BIGINT) AS h FROM customer)"


def _ring(spark, n):
    return ring.build(spark, dict.fromkeys(range(n), 1))


@query("ring_assign", f"WITH {RING_SQL.format(n=4)}, {KEYS_SQL} SELECT c_custkey, CAST(s AS INTEGER) AS shard FROM ks JOIN iv ON h > lo AND h <= hi")
def ring_assign(spark, sf):
    return ring.assign(table(spark, sf, "customer").select("c_custkey"), "c_custkey", _ring(spark, 4))


@query("ring_balance", f"WITH {RING_SQL.format(n=4)}, {KEYS_SQL}, b AS (SELECT s, count(*) AS n FROM ks JOIN iv ON h > lo AND h <= hi GROUP BY 1) SELECT count(*) AS shards, max(n) AS most, round(max(n) / avg(n), 6) AS max_over_mean FROM b")
def ring_balance(spark, sf):
    return ring.balance(ring_assign(spark, sf))


def _two_rings(a, b):
    x, y = RING_SQL.format(n=a), RING_SQL.format(n=b).replace("pt AS", "pt2 AS").replace("FROM pt", "FROM pt2").replace("iv AS", "iv2 AS")
    return f"WITH {x}, {y}, {KEYS_SQL}, m AS (SELECT ks.c_custkey, h, iv.s AS a, iv2.s AS b FROM ks JOIN iv ON h > iv.lo AND h <= iv.hi JOIN iv2 ON h > iv2.lo AND h <= iv2.hi)"


@query("ring_change", f"{_two_rings(4, 5)} SELECT count(*) AS keys, count(*) FILTER (a <> b) AS moved_ring, count(*) FILTER (h % 4 <> h % 5) AS moved_modulo FROM m")
def ring_change(spark, sf):
    return ring.moved(table(spark, sf, "customer"), "c_custkey", _ring(spark, 4), _ring(spark, 5), 4, 5)


@query("ring_change_target", f"{_two_rings(4, 5)} SELECT count(*) FILTER (a <> b AND b <> 4) AS moved_elsewhere FROM m")
def ring_change_target(spark, sf):
    """A new shard takes keys from others; none move between the others."""
    one = ring.assign(table(spark, sf, "customer").select("c_custkey"), "c_custkey", _ring(spark, 4), "a")
    return ring.assign(one, "c_custkey", _ring(spark, 5), "b").agg(F.count_if((F.col("a") != F.col("b")) & (F.col("b") != 4)).alias("moved_elsewhere"))


@query("link_locality", f"WITH {RING_SQL.format(n=4)}, {G1_SQL}, hs AS (SELECT DISTINCT host, CAST('0x' || substr(md5(host), 1, 15) AS BIGINT) AS h FROM nodes), sh AS (SELECT host, s FROM hs JOIN iv ON h > lo AND h <= hi), l AS (SELECT x.s AS a, y.s AS b FROM edges e JOIN nodes m ON m.id = e.src JOIN nodes n ON n.id = e.dst JOIN sh x ON x.host = m.host JOIN sh y ON y.host = n.host) SELECT count(*) AS links, count(*) FILTER (a = b) AS local, round(count(*) FILTER (a = b) / count(*), 6) AS share FROM l".replace("AS local,", 'AS "local",'))
def link_locality(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    own = ring.assign(nodes.select("host").distinct(), "host", _ring(spark, 4))
    at = nodes.join(own, "host").select("id", "shard")
    both = edges.join(at.select(F.col("id").alias("src"), F.col("shard").alias("a")), "src").join(at.select(F.col("id").alias("dst"), F.col("shard").alias("b")), "dst")
    same = F.count_if(F.col("a") == F.col("b"))
    return both.agg(F.count(F.lit(1)).alias("links"), same.alias("local"), F.round(same / F.count(F.lit(1)), 6).alias("share"))


@query("exchange_urls", f"WITH {RING_SQL.format(n=4)}, {G1_SQL}, hs AS (SELECT DISTINCT host, CAST('0x' || substr(md5(host), 1, 15) AS BIGINT) AS h FROM nodes), sh AS (SELECT host, CAST(s AS INTEGER) AS s FROM hs JOIN iv ON h > lo AND h <= hi) SELECT s AS owner, count(DISTINCT e.dst) AS urls FROM edges e JOIN nodes n ON n.id = e.dst JOIN sh USING (host) GROUP BY 1")
def exchange_urls(spark, sf):
    """Found URLs folded before they go to their owners."""
    nodes, edges = overlay.web(spark, sf)
    found = edges.select(F.col("dst").alias("id")).distinct().join(nodes.select("id", "host"), "id")
    own = ring.assign(nodes.select("host").distinct(), "host", _ring(spark, 4), "owner")
    return found.join(own, "host").repartition("owner").groupBy("owner").agg(F.count(F.lit(1)).alias("urls"))


def _mix(n: str, salt: int) -> str:
    return f"(((({n} % 2147483648 * 1103515245 + 12345 + {salt * 7919}) % 2147483648) * 1103515245 + 12345) % 2147483648 // 65536)"


ANSWER_SQL = f"an AS (SELECT n, CASE WHEN {_mix('n', 1)} % 100 < 3 THEN 503 WHEN {_mix('n', 1)} % 100 < 6 THEN 404 ELSE 200 END AS status, 20000 + {_mix('n', 2)} * 10 AS latency_us, 500 + {_mix('n', 3)} AS length, {_mix('n', 4)} % 12 AS out FROM (SELECT unnest(range(0, 20000)) AS n))"


@query("simweb_page", f"WITH {ANSWER_SQL} SELECT * FROM an")
def simweb_page(spark, sf):
    return simweb.respond(spark.range(20_000).withColumnRenamed("id", "n"))


@query("simweb_links", f"WITH {ANSWER_SQL} SELECT n AS src, pos, (n * 31 + pos * 1009 + n * pos) % 20000 AS dst FROM (SELECT n, unnest(range(1, out + 1)) AS pos FROM an)")
def simweb_links(spark, sf):
    return simweb.links(simweb_page(spark, sf), 20_000)


@query("fetch_errors", f"WITH {ANSWER_SQL} SELECT status, count(*) AS answers, round(avg(length), 6) AS mean_length FROM an GROUP BY 1")
def fetch_errors(spark, sf):
    return simweb_page(spark, sf).groupBy("status").agg(F.count(F.lit(1)).alias("answers"), F.round(F.avg("length"), 6).alias("mean_length"))


@query("fetch_buffer_spill", f"WITH {REQUESTS_SQL} SELECT b AS buffer, count(*) AS requests, count(*) FILTER (length <= b) AS in_memory FROM q, (SELECT unnest([1000, 5000, 20000]) AS b) GROUP BY 1")
def fetch_buffer_spill(spark, sf):
    sizes = F.explode(F.array(*(F.lit(b) for b in (1000, 5000, 20000))))
    return requests(spark, sf).select("length", sizes.alias("buffer")).groupBy("buffer").agg(F.count(F.lit(1)).alias("requests"), F.count_if(F.col("length") <= F.col("buffer")).alias("in_memory"))


def backlog(spark, sf, shards: int = 1):
    """Orders as a backlog: the customer is the host, 37 addresses a shard, all there at the start."""
    o = table(spark, sf, "orders").select("o_orderkey", F.col("o_custkey").alias("host"))
    shard = ring.modulo("host", shards)
    return o.select(shard.cast("long").alias("shard"), F.col("o_orderkey").alias("seq"), "host", (F.col("host") % 997).alias("ip"), (20_000 + simweb.mixed(F.col("o_orderkey"), 2) * 10).alias("latency_us"), (500 + simweb.mixed(F.col("o_orderkey"), 3)).alias("length"))


POINT = "point long, threads long, slots long, d_host long, d_ip long, adaptive double, horizon_us long"
FOREVER = 1 << 60


@query("fetch_sim")
def fetch_sim(spark, sf):
    return fetchsim.run(backlog(spark, sf), spark.createDataFrame([(0, 100, 300, 200_000, 50_000, 0.0, FOREVER)], POINT))


@query("fetch_law", "SELECT threads, least(threads, 300) * 1e6 / 200000.0 AS rate FROM (SELECT unnest([25, 100, 300, 600]) AS threads)")
def fetch_law(spark, sf):
    return spark.createDataFrame([(t, fetchsim.law(t, 300, 200_000.0, 10**6, 10**6, 0, 0)) for t in (25, 100, 300, 600)], "threads int, rate double")


@query("wl_threads")
def wl_threads(spark, sf):
    """Rate by fetchers with 300 proxy slots and no delays: in proportion, then flat."""
    points = spark.createDataFrame([(t, t, 300, 0, 0, 0.0, FOREVER) for t in (25, 50, 100, 200, 300, 400, 600)], POINT)
    free = backlog(spark, sf).withColumn("host", F.col("seq")).withColumn("ip", F.col("seq"))
    return fetchsim.run(free, points).select(F.col("point").alias("threads"), "fetched", F.round("rate", 3).alias("rate"), F.round("busy", 4).alias("busy"))


@query("wl_delay")
def wl_delay(spark, sf):
    """Addresses that must be held in their delay, rate and load, by address delay and fetchers; host delays eight times as long, and equal at 64 fetchers.

    Rates are those of the first twenty simulated seconds, while the backlog is deep.
    """
    unit, cases = 100_000, [(32, 8), (64, 8), (128, 8), (64, 1)]
    points = spark.createDataFrame([(t * 1000 + d * 10 + r, t, 4096, d * unit * r, d * unit, 0.0, 20_000_000) for d in (1, 2, 4, 8, 16) for t, r in cases], POINT)
    point = F.col("point")
    return fetchsim.run(backlog(spark, sf), points).select(F.floor(point / 1000).alias("threads"), F.floor(point % 1000 / 10).alias("delay"), (point % 10).alias("ratio"), F.round("rate", 3).alias("rate"), F.round("mean_delayed", 3).alias("mean_delayed"), F.round("busy", 4).alias("busy"))


@query("wl_scale")
def wl_scale(spark, sf):
    """Rate of 1, 2, 4 and 8 shards that gather one backlog to its end: the ring deals its hosts, each shard has 25 fetchers and its own politeness."""
    pages, out = backlog(spark, sf).drop("shard"), None
    for s in (1, 2, 4, 8):
        own = ring.assign(pages, "host", _ring(spark, s)).withColumn("shard", F.col("shard").cast("long"))
        ran = fetchsim.run(own, spark.createDataFrame([(s, 25, 1000, 200_000, 50_000, 0.0, FOREVER)], POINT))
        one = ran.groupBy(F.col("point").alias("shards")).agg(F.sum("fetched").alias("fetched"), F.round(F.sum("rate"), 3).alias("rate"), F.round(F.sum("fetched") * 1e6 / F.max("horizon_us"), 3).alias("rate_to_last"), F.round(F.max("fetched") / F.avg("fetched"), 6).alias("max_over_mean"))
        out = one if out is None else out.unionByName(one)
    return out


@query("wl_fixed_delay")
def wl_fixed_delay(spark, sf):
    """A fixed ten-second delay, one from download times, and short delays of host and address."""
    points = spark.createDataFrame([(0, 200, 1000, 10_000_000, 10_000_000, 0.0, 60_000_000), (1, 200, 1000, 0, 0, 5.0, 60_000_000), (2, 200, 1000, 400_000, 50_000, 0.0, 60_000_000)], POINT)
    names = F.element_at(F.array(F.lit("fixed"), F.lit("adaptive"), F.lit("two levels")), F.col("point").cast("int") + 1)
    return fetchsim.run(backlog(spark, sf), points).select(names.alias("policy"), "fetched", F.round("rate", 3).alias("rate"), F.round("mb_rate", 4).alias("mb_rate"))


@query("wl_target_front")
def wl_target_front(spark, sf):
    """How far the target grows over longer runs: it stops once no fetcher idles."""
    points = spark.createDataFrame([(h, 64, 4096, 400_000, 50_000, 0.0, h * 1_000_000) for h in (1, 5, 20, 60)], POINT)
    return fetchsim.run(backlog(spark, sf), points).select(F.col("point").alias("seconds"), "target", "polls")


def _ip():
    return F.pmod(F.crc32("host"), F.lit(16)).alias("ip")


def _web(spark, sf):
    nodes, edges = overlay.web(spark, sf, places=True)
    named = nodes.withColumn("ip", _ip())
    return graph.step_table(named), graph.step_table(edges)


def _seed(spark):
    return spark.createDataFrame([(0,)], "id long")


BFS = "w AS (SELECT 0 AS id, 0 AS depth UNION SELECT e.dst, w.depth + 1 FROM w JOIN edges e ON e.src = w.id WHERE w.depth < 16), lv AS (SELECT id, min(depth) AS depth FROM w GROUP BY 1)"


@query("crawl_run", f"WITH RECURSIVE {G1_SQL}, {BFS} SELECT id, depth, depth + 1 AS round FROM lv")
def crawl_run(spark, sf):
    """Without quotas a round is a level."""
    nodes, edges = _web(spark, sf)
    return crawl.gather(edges, nodes, _seed(spark)).select("id", "depth", "round")


def _polite_log(spark, sf):
    nodes, edges = _web(spark, sf)
    return crawl.gather(edges, nodes, _seed(spark), crawl.Config(per_host=2, per_ip=4))


@query("crawl_round", f"WITH RECURSIVE {G1_SQL}, {BFS} SELECT count(*) AS fetched, true AS once FROM lv")
def crawl_round(spark, sf):
    """With quotas the set is the same, and no page is visited twice."""
    return _polite_log(spark, sf).agg(F.count(F.lit(1)).alias("fetched"), (F.count(F.lit(1)) == F.countDistinct("id")).alias("once"))


@query("no_refresh", "SELECT 0 AS again")
def no_refresh(spark, sf):
    return _polite_log(spark, sf).groupBy("id").agg(F.count(F.lit(1)).alias("n")).agg(F.count_if(F.col("n") > 1).alias("again"))


@query("bfs_hostwise", f"WITH RECURSIVE {G1_SQL}, {BFS} SELECT count(*) AS fetched, 0 AS inversions FROM lv")
def bfs_hostwise(spark, sf):
    return crawl.hostwise_inversions(_polite_log(spark, sf))


def _deviation(spark, sf, config):
    nodes, edges = _web(spark, sf)
    return crawl.deviation(*crawl.gather_each(edges, nodes, _seed(spark), [config, crawl.Config()]))


@query("bfs_global_distance")
def bfs_global_distance(spark, sf):
    return _deviation(spark, sf, crawl.Config(per_host=2, per_ip=4))


@query("visit_priority")
def visit_priority(spark, sf):
    """Lanes served by id instead of discovery."""
    return _deviation(spark, sf, crawl.Config(per_host=2, per_ip=4, order=("id",)))


SNAPSHOTS = {"regional": (50, True), "deep": (1 << 30, False), "shallow": (5, False)}


def snapshot(spark, sf, name):
    """(pages, edges among them) of a snapshot by its cap and, for regional, its domain."""
    cap, regional = SNAPSHOTS[name]
    nodes, edges = _web(spark, sf)
    if regional:
        nodes = nodes.filter("domain = 'example.org'")
    first = nodes.agg(F.min("id").alias("id"))
    log = graph.step_table(crawl.gather(edges, nodes, first, crawl.Config(cap=cap)))
    kept = nodes.join(log.select("id"), "id", "left_semi")
    inside = edges.join(log.select(F.col("id").alias("src")), "src", "left_semi").join(log.select(F.col("id").alias("dst")), "dst", "left_semi").select("src", "dst")
    return graph.step_table(kept), graph.step_table(inside)


def _snapshot_query(name):
    def run(spark, sf):
        return snapshot(spark, sf, name)[0].select("id", "host")

    return run


query("wl_deep", f"WITH RECURSIVE {G1_SQL}, {BFS} SELECT id, host FROM lv JOIN nodes USING (id)")(_snapshot_query("deep"))
query("wl_regional", f"WITH RECURSIVE {G1_SQL.replace('edges AS', 'edges0 AS').replace('nodes AS', 'nodes0 AS')}, nodes AS (SELECT * FROM nodes0 WHERE domain = 'example.org'), edges AS (SELECT e.* FROM edges0 e JOIN nodes a ON a.id = e.src JOIN nodes b ON b.id = e.dst), w AS (SELECT min(id) AS id, 0 AS depth FROM nodes UNION SELECT e.dst, w.depth + 1 FROM w JOIN edges e ON e.src = w.id WHERE w.depth < 16) SELECT DISTINCT id, host FROM w JOIN nodes USING (id)")(_snapshot_query("regional"))
query("wl_shallow")(_snapshot_query("shallow"))


@query("wl_basic_table")
def wl_basic_table(spark, sf):
    """Basic data, and distances, of the three snapshots."""
    from webgather.functions import digests
    from webgather.operators import centrality, dedup

    copies = graph.step_table(dedup.first_copies(table(spark, sf, "pages"), "page_id", digests.digest("html", "summary", "article")))
    out = None
    for name in SNAPSHOTS:
        nodes, edges = snapshot(spark, sf, name)
        far = centrality.summary(centrality.spread(edges, nodes), nodes)
        one = graph.basic(nodes, edges, copies).crossJoin(far).select(F.lit(name).alias("snapshot"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def _binned(graph_name: str, base: str, end: str) -> str:
    fib = "RECURSIVE fb AS (SELECT CAST(1 AS BIGINT) AS low, CAST(2 AS BIGINT) AS high UNION ALL SELECT high, low + high FROM fb WHERE high < 1000000000)"
    way = "in" if end == "dst" else "out"
    return f"SELECT * FROM (WITH {fib}, {base}, dg AS (SELECT n.id, count(e.{end}) AS degree FROM nodes n LEFT JOIN edges e ON e.{end} = n.id GROUP BY 1), fr AS (SELECT degree, count(*) AS freq FROM dg GROUP BY 1) SELECT '{graph_name}' AS graph, '{way}' AS way, low, CAST(sum(freq) AS BIGINT) AS nodes, round(sum(freq) / (high - low), 6) AS mean_freq, (SELECT CAST(sum(freq) AS BIGINT) FROM fr r WHERE r.degree >= low) AS rank FROM fr JOIN fb ON degree >= low AND degree < high GROUP BY low, high)"


@query("wl_degrees", " UNION ALL ".join(_binned(n, b, e) for n, b in (("web", G1_SQL), ("baskets", overlay.G2_SQL), ("trade", overlay.G3_SQL)) for e in ("dst", "src")))
def wl_degrees(spark, sf):
    """In- and outdegrees of three graphs by Fibonacci bins: nodes, mean frequency, and the rank of each bin's lowest degree."""
    out = None
    for name, made in (("web", overlay.web), ("baskets", overlay.baskets), ("trade", overlay.trade)):
        nodes, edges = made(spark, sf)
        for way in ("in", "out"):
            bins = graph.fibonacci_bins(graph.degree_freq(edges, nodes, way))
            # nodes of at least a bin's lowest degree: some 90 bins at most, whatever the graph
            rank = F.sum("nodes").over(Window.orderBy(F.col("low").desc()))
            one = bins.select(F.lit(name).alias("graph"), F.lit(way).alias("way"), "low", "nodes", "mean_freq", rank.alias("rank"))
            out = one if out is None else out.unionByName(one)
    return out


def _root_sql(cap: int) -> str:
    kept = f"{G1_SQL.replace('edges AS', 'edges0 AS').replace('nodes AS', 'nodes0 AS')}, nodes AS (SELECT * FROM nodes0 QUALIFY row_number() OVER (PARTITION BY host ORDER BY id) <= {cap}), edges AS (SELECT e.* FROM edges0 e JOIN nodes a ON a.id = e.src JOIN nodes b ON b.id = e.dst)"
    return f"SELECT * FROM (WITH {kept}, c AS (SELECT dst AS id, count(*) AS d FROM edges GROUP BY 1), x AS (SELECT n.id, coalesce(d, 0) AS d, n.id = min(n.id) OVER (PARTITION BY host) AS root FROM nodes n LEFT JOIN c USING (id)), t AS (SELECT * FROM x ORDER BY d DESC, id LIMIT 20), s AS (SELECT count(*) FILTER (d >= 0.9 * {cap}) AS before, count(*) FILTER (d >= 1.1 * {cap}) AS after FROM x WHERE d > 0) SELECT {cap} AS cap, count(*) AS pages, count(*) FILTER (root) AS roots, any_value(round(before / greatest(after, 1), 6)) AS step FROM t, s)"


@query("wl_root_effect", " UNION ALL ".join(_root_sql(c) for c in (5, 20, 1 << 30)))
def wl_root_effect(spark, sf):
    """Of the twenty pages of highest indegree, how many are roots of their hosts, and the rank curve's step at the cap, for snapshots of so many pages a host."""
    whole, links = _web(spark, sf)
    out = None
    for cap in (5, 20, 1 << 30):
        nodes = graph.step_table(graph.capped(whole, "id", cap))
        ids = nodes.select("id")
        edges = links.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
        degrees = graph.step_table(graph.indegree_split(edges, nodes).withColumn("degree", F.col("inner") + F.col("outer")))
        top = degrees.orderBy(F.col("degree").desc(), "id").limit(20)
        rank = graph.degree_rank(degrees.filter("degree > 0").groupBy("degree").agg(F.count(F.lit(1)).alias("freq")))
        one = top.agg(F.lit(cap).alias("cap"), F.count(F.lit(1)).alias("pages"), F.count_if("is_root").alias("roots")).crossJoin(graph.tail_step(rank, cap).select("step"))
        out = one if out is None else out.unionByName(one)
    return out


@query("wl_spill", f"WITH {TAKE_SQL} SELECT count(*) AS buckets, count(*) FILTER (used / allocated < 0.5) AS under_half, round(min(ratio), 6) AS least FROM ur")
def wl_spill(spark, sf):
    return spill_used_ratio(spark, sf).agg(F.count(F.lit(1)).alias("buckets"), F.count_if(F.col("used") / F.col("allocated") < 0.5).alias("under_half"), F.round(F.min("ratio"), 6).alias("least"))


@query("wl_feeder", f"WITH {REQUESTS_SQL}, o AS (SELECT q.*, c, row_number() OVER (PARTITION BY c, ip ORDER BY seq) > c // 37 AS over_ FROM q, (SELECT unnest([370, 3700, 37000]) AS c)), p AS (SELECT c, bool_or(over_) OVER (PARTITION BY c, host ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS disk FROM o) SELECT c AS capacity, count(*) AS urls, count(*) FILTER (disk) AS on_disk FROM p GROUP BY 1")
def wl_feeder(spark, sf):
    """What goes to disk by the memory there is."""
    out = None
    for c in (370, 3700, 37000):
        one = feeder.places(requests(spark, sf), c, feeder.quota(c, 37)).agg(F.lit(c).alias("capacity"), F.count(F.lit(1)).alias("urls"), F.count_if(F.col("place") == "disk").alias("on_disk"))
        out = one if out is None else out.unionByName(one)
    return out


DOMAIN_SQL = f"{G1_SQL.replace('edges AS', 'edges0 AS').replace('nodes AS', 'nodes0 AS')}, nodes AS (SELECT * FROM nodes0 WHERE domain = 'example.org'), edges AS (SELECT e.* FROM edges0 e JOIN nodes a ON a.id = e.src JOIN nodes b ON b.id = e.dst), w AS (SELECT min(id) AS id, 0 AS depth FROM nodes UNION SELECT e.dst, w.depth + 1 FROM w JOIN edges e ON e.src = w.id WHERE w.depth < 16), dm AS (SELECT * FROM nodes WHERE id IN (SELECT id FROM w))"


@query("wl_domain", f"WITH RECURSIVE {DOMAIN_SQL} SELECT count(*) AS pages, CAST(sum(content) AS BIGINT) AS bytes, CAST(ceil(sum(content) / 100000.0) AS BIGINT) AS seconds, true AS under_cap FROM dm")
def wl_domain(spark, sf):
    """One domain gathered politely over a link of 100 kB a second: a page is sent when those fetched before it are through."""
    nodes, edges = overlay.web(spark, sf, places=True, domain="example.org")
    inside = nodes.filter(F.col("domain") == "example.org").select("id", "host", _ip(), F.coalesce("content", F.lit(0)).alias("content"))
    log = crawl.gather(graph.step_table(edges), inside, inside.agg(F.min("id").alias("id")), crawl.Config(per_host=2, per_ip=4), summed="content")
    # bytes of each second a page is on the link; a page of none is in the second that ends there
    cap, through = 100_000, F.col("through")
    sent = log.select((through - F.col("content")).alias("from"), "through")
    first, last = (F.greatest(F.lit(0), x).cast("long") for x in (F.least(F.floor(F.col("from") / cap), F.ceil(through / cap) - 1), F.ceil(through / cap) - 1))
    part = F.least("through", (F.col("s") + 1) * cap) - F.greatest("from", F.col("s") * cap)
    per = sent.select("from", "through", first.alias("first"), F.explode(F.sequence(first, last)).alias("s")).groupBy("s").agg(F.sum(part).alias("b"), F.count_if(F.col("s") == F.col("first")).alias("pages"))
    return per.agg(F.coalesce(F.sum("pages"), F.lit(0)).alias("pages"), F.sum("b").alias("bytes"), F.max(F.when(F.col("b") > 0, F.col("s") + 1).otherwise(0)).alias("seconds"), F.coalesce(F.max("b") <= cap, F.lit(True)).alias("under_cap"))


@query("wl_compare")
def wl_compare(spark, sf):
    """Half of all pages gathered from one seed by policy: pages, bytes, rounds, pages and bytes a round, the fullest of 4 shards, and lanes looked at a page.

    two levels is the frontier; two-queue releases the same but looks at every lane each round;
    global order and indegree take as many pages a round as all addresses may give, politeness aside.
    """
    nodes, edges = _web(spark, sf)
    half, own = max(1, nodes.count() // 2), ring.assign(nodes.select("host").distinct(), "host", _ring(spark, 4))
    configs = {"two levels": crawl.Config(2, 4, budget=half), "by id": crawl.Config(2, 4, budget=half, order=("id",)), "global order": crawl.Config(per_round=64, budget=half), "indegree": crawl.Config(per_round=64, budget=half, priority="indegree")}
    out = None
    for name, c in configs.items():
        log = graph.step_table(crawl.gather(edges, nodes, _seed(spark), c).join(nodes.select("id", "content"), "id").join(own, "host"))
        fullest = log.groupBy("shard").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("most_of_a_shard"))
        total = log.agg(F.count(F.lit(1)).alias("pages"), F.sum("content").alias("bytes"), F.max("round").alias("rounds"), F.countDistinct("host", "round").alias("lanes")).crossJoin(fullest)
        total = total.withColumn("pages_a_round", F.round(F.col("pages") / F.col("rounds"), 6)).withColumn("bytes_a_round", F.round(F.col("bytes") / F.col("rounds"), 6))
        policies = [(name, F.round(F.col("lanes") / F.col("pages"), 6))]
        if name == "two levels":
            total = total.crossJoin(crawl.heads_examined(log).select("heads"))
            policies.append(("two-queue", F.round(F.col("heads") / F.col("pages"), 6)))
        for policy, looked in policies:
            one = total.select(F.lit(policy).alias("policy"), "pages", "bytes", "rounds", "pages_a_round", "bytes_a_round", "most_of_a_shard", looked.alias("looked_at"))
            out = one if out is None else out.unionByName(one)
    return out


@query("wl_policy")
def wl_policy(spark, sf):
    """Pages of the five largest hosts among a quarter of all, gathered in discovery order and by indegree so far, a twentieth of the pages a round."""
    nodes, edges = _web(spark, sf)
    nodes, edges = graph.step_table(nodes), graph.step_table(edges)
    large = nodes.groupBy("host").agg(F.count(F.lit(1)).alias("n")).orderBy(F.col("n").desc(), "host").limit(5).select("host", F.lit(True).alias("large"))
    n = nodes.count()
    out = None
    for name in ("discovery", "indegree"):
        log = crawl.gather(edges, nodes, _seed(spark), crawl.Config(per_round=max(1, n // 20), budget=max(1, n // 4), priority=name)).join(F.broadcast(large), "host", "left")
        one = log.agg(F.lit(name).alias("policy"), F.count(F.lit(1)).alias("pages"), F.count_if("large").alias("of_large_hosts"), F.max("round").alias("rounds"), F.round(F.avg("depth"), 6).alias("mean_depth"))
        out = one if out is None else out.unionByName(one)
    return out


@query("baseline_batch_rounds", f"WITH RECURSIVE {G1_SQL}, {BFS}, c AS (SELECT depth, count(*) AS n FROM lv GROUP BY 1), k AS (SELECT depth, n, sum(n) OVER (ORDER BY depth) AS known FROM c) SELECT count(*) AS rounds, CAST(sum(n) AS BIGINT) AS rows_ours, CAST(sum(known) AS BIGINT) AS rows_resorted FROM k")
def baseline_batch_rounds(spark, sf):
    """Rows that rounds move: a batch gatherer sorts its whole table of URLs each round, ours only what a round found."""
    nodes, edges = _web(spark, sf)
    per = crawl.gather(edges, nodes, _seed(spark)).groupBy("found").agg(F.count(F.lit(1)).alias("n"))
    known = per.select("n", F.sum("n").over(Window.orderBy("found")).alias("known"))
    return known.agg(F.count(F.lit(1)).alias("rounds"), F.sum("n").alias("rows_ours"), F.sum("known").alias("rows_resorted"))


@query("copy_graph", "WITH r AS (SELECT doc_id AS src, min(doc_id) OVER (PARTITION BY text) AS dst FROM documents) SELECT src, dst FROM r WHERE src <> dst")
def copy_graph(spark, sf):
    """Repeats and their first copies as a graph."""
    copies = dedup.first_copies(table(spark, sf, "documents"), "doc_id", F.md5("text"))
    return copies.filter("is_repeat").select(F.col("id").alias("src"), F.col("first_id").alias("dst"))
