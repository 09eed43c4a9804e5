"""Queries on graphs of snapshots: building, degrees, distances, centralities."""

from __future__ import annotations

from pyspark.sql import functions as F

from webgather.catalog import query, table
from webgather.functions import html, suffix
from webgather.operators import centrality, graph, overlay, powerlaw
from webgather.operators.overlay import G1_SQL, G2_SQL, G3_SQL, G4_SQL
from webgather.plans.web import LINKS_SQL

HOST_SQL = "ha AS (SELECT a.host AS src, b.host AS dst, count(*) AS links FROM edges e JOIN nodes a ON a.id = e.src JOIN nodes b ON b.id = e.dst WHERE a.host <> b.host GROUP BY 1, 2)"
FREQ_SQL = "dg AS (SELECT n.id, count(e.{end}) AS degree FROM nodes n LEFT JOIN edges e ON e.{end} = n.id GROUP BY 1), fr AS (SELECT degree, count(*) AS freq FROM dg GROUP BY 1)"
DIST_SQL = "RECURSIVE {g}, w AS (SELECT id AS source, id AS node, 0 AS d FROM nodes UNION SELECT w.source, e.dst, w.d + 1 FROM w JOIN edges e ON e.src = w.node WHERE w.d < 16), ds AS (SELECT source, node, min(d) AS d FROM w GROUP BY 1, 2)"


def host_web(spark, sf, label="host"):
    """(nodes, edges) of the quotient of the overlay by a label."""
    nodes, edges = overlay.web(spark, sf)
    return nodes.select(F.col(label).alias("id")).distinct(), graph.quotient(edges, nodes, label)


@query("page_graph", f"WITH {LINKS_SQL} SELECT page_id AS src, count(DISTINCT target) AS targets FROM t GROUP BY 1")
def page_graph(spark, sf):
    pages = table(spark, sf, "pages")
    return graph.page_graph(html.exploded_links(pages), pages, closed=False).groupBy("src").agg(F.count(F.lit(1)).alias("targets"))


@query("page_graph_overlay", f"WITH {G1_SQL} SELECT src, dst FROM edges")
def page_graph_overlay(spark, sf):
    return overlay.web(spark, sf)[1]


@query("host_graph", f"WITH {G1_SQL}, {HOST_SQL} SELECT * FROM ha")
def host_graph(spark, sf):
    return host_web(spark, sf)[1]


@query("site_graph", f"WITH {G1_SQL}, {HOST_SQL.replace('a.host', 'a.site').replace('b.host', 'b.site')} SELECT * FROM ha")
def site_graph(spark, sf):
    return host_web(spark, sf, "site")[1]


@query("domain_graph", f"WITH {G1_SQL}, {HOST_SQL.replace('a.host', 'a.domain').replace('b.host', 'b.domain')} SELECT * FROM ha")
def domain_graph(spark, sf):
    """By registrable domain, found for distinct hosts and joined back."""
    nodes, edges = overlay.web(spark, sf)
    domains = suffix.registrable(nodes, "host", suffix.rules(spark, private=False)).withColumnRenamed("domain", "registrable")
    return graph.quotient(edges, nodes.join(domains, "host"), "registrable")


@query("basket_graph", f"WITH {G2_SQL}, {HOST_SQL} SELECT * FROM ha")
def basket_graph(spark, sf):
    nodes, edges = overlay.baskets(spark, sf)
    return graph.quotient(edges, nodes, "host")


@query("trade_graph", f"WITH {G3_SQL}, {HOST_SQL} SELECT * FROM ha")
def trade_graph(spark, sf):
    nodes, edges = overlay.trade(spark, sf)
    return graph.quotient(edges, nodes, "host")


@query("succession_graph", f"WITH {G4_SQL} SELECT src, dst FROM edges")
def succession_graph(spark, sf):
    return overlay.successions(spark, sf)[1]


BASIC_SQL = "SELECT count(*) AS overall, {fc} AS first_copies, round(avg(content), 6) AS mean_content, round(avg(coalesce(d, 0)), 6) AS mean_outdegree, round(avg(coalesce(x, 0)), 6) AS mean_external FROM nodes LEFT JOIN (SELECT e.src AS id, count(*) AS d, count(*) FILTER (a.host <> b.host) AS x FROM edges e JOIN nodes a ON a.id = e.src JOIN nodes b ON b.id = e.dst GROUP BY 1) o USING (id)"


@query("basic_stats", f"WITH {G1_SQL} {BASIC_SQL.format(fc='count(*)')}")
def basic_stats(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    return graph.basic(nodes, edges)


@query("degree_freq", f"WITH {G1_SQL}, {FREQ_SQL.format(end='dst')} SELECT * FROM fr")
def degree_freq(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    return graph.degree_freq(edges, nodes)


@query("degree_freq_out", f"WITH {G1_SQL}, {FREQ_SQL.format(end='src')} SELECT * FROM fr")
def degree_freq_out(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    return graph.degree_freq(edges, nodes, "out")


FIB_SQL = "RECURSIVE fb AS (SELECT CAST(1 AS BIGINT) AS low, CAST(2 AS BIGINT) AS high UNION ALL SELECT high, low + high FROM fb WHERE high < 1000000000), "


@query("degree_fibonacci", f"WITH {FIB_SQL}{G2_SQL}, {FREQ_SQL.format(end='dst')} SELECT low, high, CAST(sum(freq) AS BIGINT) AS nodes, round(sum(freq) / (high - low), 6) AS mean_freq, (low + high - 1) / 2 AS center FROM fr JOIN fb ON degree >= low AND degree < high GROUP BY 1, 2")
def degree_fibonacci(spark, sf):
    nodes, edges = overlay.baskets(spark, sf)
    return graph.fibonacci_bins(graph.degree_freq(edges, nodes))


RANK_SQL = "rk AS (SELECT degree, CAST(sum(freq) OVER (ORDER BY degree DESC) AS BIGINT) AS rank FROM fr)"


@query("degree_rank", f"WITH {G1_SQL}, {FREQ_SQL.format(end='dst')}, {RANK_SQL} SELECT * FROM rk")
def degree_rank(spark, sf):
    return graph.degree_rank(degree_freq(spark, sf))


@query("indegree_split", f"WITH {G1_SQL}, c AS (SELECT e.dst AS id, count(*) FILTER (a.host = b.host) AS inner_, count(*) FILTER (a.host <> b.host) AS outer_ FROM edges e JOIN nodes a ON a.id = e.src JOIN nodes b ON b.id = e.dst GROUP BY 1) SELECT n.id, coalesce(inner_, 0) AS inner, coalesce(outer_, 0) AS outer, n.id = min(n.id) OVER (PARTITION BY host) AS is_root FROM nodes n LEFT JOIN c USING (id)".replace("AS inner,", 'AS "inner",').replace("AS outer,", 'AS "outer",'))
def indegree_split(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    return graph.indegree_split(edges, nodes)


@query("tail_step", f"WITH {G1_SQL}, {FREQ_SQL.format(end='dst')}, {RANK_SQL}, s AS (SELECT coalesce(max(rank) FILTER (degree >= 9), 0) AS before, coalesce(max(rank) FILTER (degree >= 11), 0) AS after FROM rk) SELECT *, round(before / greatest(after, 1), 6) AS step FROM s")
def tail_step(spark, sf):
    return graph.tail_step(degree_rank(spark, sf), 10)


@query("powerlaw_fit")
def powerlaw_fit(spark, sf):
    return powerlaw.fit(degree_freq(spark, sf))


@query("powerlaw_approx", f"WITH {G2_SQL}, {FREQ_SQL.format(end='dst')} SELECT CAST(sum(freq) AS BIGINT) AS tail, round(1 + sum(freq) / sum(freq * ln(degree / (20 - 0.5))), 6) AS alpha FROM fr WHERE degree >= 20")
def powerlaw_approx(spark, sf):
    nodes, edges = overlay.baskets(spark, sf)
    return powerlaw.approximate_alpha(graph.degree_freq(edges, nodes), 20)


@query("powerlaw_pvalue")
def powerlaw_pvalue(spark, sf):
    nodes, edges = overlay.baskets(spark, sf)
    return powerlaw.pvalue(graph.degree_freq(edges, nodes), 100)


@query("bfs_levels", f"WITH RECURSIVE {G1_SQL}, w AS (SELECT 0 AS id, 0 AS depth UNION SELECT e.dst, w.depth + 1 FROM w JOIN edges e ON e.src = w.id WHERE w.depth < 16) SELECT id, min(depth) AS depth FROM w GROUP BY 1")
def bfs_levels(spark, sf):
    _, edges = overlay.web(spark, sf)
    return graph.bfs(graph.step_table(edges), spark.createDataFrame([(0,)], "id long"))


@query("indegree_top", f"WITH {G1_SQL}, {HOST_SQL}, t AS (SELECT dst AS node, count(*) AS value FROM ha GROUP BY 1) SELECT row_number() OVER (ORDER BY value DESC, node) AS place, node, CAST(value AS DOUBLE) AS value FROM t ORDER BY value DESC, node LIMIT 10")
def indegree_top(spark, sf):
    nodes, edges = host_web(spark, sf)
    return centrality.top(centrality.indegree(edges, nodes), "indegree")


#: What a node adds to its inflow for rank without out-edges, by treatment; p is the round before.
DANGLING_SQL = {"preference": "(SELECT coalesce(sum(r), 0) FROM {p} ANTI JOIN od ON od.src = {p}.id) / (SELECT count(*) FROM pn)", "self": "coalesce((SELECT r FROM {p} WHERE {p}.id = n.id AND NOT EXISTS (SELECT 1 FROM od WHERE od.src = n.id)), 0)", "drop": "0"}


def _pagerank_sql(base: str, edges: str, nodes: str, rounds: int, alpha: str = "0.85", dangling: str = "preference") -> str:
    parts = [f"{base}", f"pe AS MATERIALIZED (SELECT DISTINCT src, dst FROM {edges})", f"pn AS MATERIALIZED (SELECT DISTINCT {nodes} AS id FROM nodes)", "od AS MATERIALIZED (SELECT src, count(*) AS t FROM pe GROUP BY 1)", "r0 AS (SELECT id, 1.0::DOUBLE / (SELECT count(*) FROM pn) AS r FROM pn)"]
    for k in range(1, rounds + 1):
        more = DANGLING_SQL[dangling].format(p=f"r{k - 1}")
        parts.append(f"r{k} AS MATERIALIZED (SELECT n.id, {alpha} * (coalesce(i.s, 0) + {more}) + (1 - {alpha}) / (SELECT count(*) FROM pn) AS r FROM pn n LEFT JOIN (SELECT e.dst AS id, sum(p.r / o.t) AS s FROM pe e JOIN r{k - 1} p ON p.id = e.src JOIN od o ON o.src = e.src GROUP BY 1) i ON i.id = n.id)")
    return ", ".join(parts)


@query("pagerank", f"WITH {_pagerank_sql(G1_SQL, 'edges', 'id', 20)} SELECT id, round(CAST(r AS DOUBLE), 9) AS rank FROM r20")
def pagerank(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    return centrality.pagerank(edges, nodes, iterations=20).select("id", F.round("rank", 9).alias("rank"))


@query("pagerank_damping", " UNION ALL ".join(f"SELECT * FROM (WITH {_pagerank_sql(G1_SQL + ', ' + HOST_SQL, 'ha', 'host', 8, a)} SELECT {a} AS alpha, round(CAST(max(r) AS DOUBLE), 9) AS highest FROM r8)" for a in ("0.5", "0.85", "0.95")))
def pagerank_damping(spark, sf):
    nodes, edges = host_web(spark, sf)
    edges, nodes, out = graph.step_table(edges), graph.step_table(nodes), None
    for a in (0.5, 0.85, 0.95):
        one = centrality.pagerank(edges, nodes, a, 8).agg(F.lit(a).alias("alpha"), F.round(F.max("rank"), 9).alias("highest"))
        out = one if out is None else out.unionByName(one)
    return out


@query("pagerank_residual", "SELECT true AS solved, true AS sums_to_one")
def pagerank_residual(spark, sf):
    """Iterated until changes are at rounding: the equation holds."""
    nodes, edges = host_web(spark, sf)
    edges, nodes = graph.step_table(edges), graph.step_table(nodes)
    ranks = graph.step_table(centrality.pagerank(edges, nodes, iterations=240, tol=1e-13))
    return centrality.residual(edges, nodes, ranks).select((F.col("residual") < 1e-11).alias("solved"), (F.abs(F.col("total") - 1) < 1e-11).alias("sums_to_one"))


@query("pagerank_dangling", " UNION ALL ".join(f"SELECT * FROM (WITH {_pagerank_sql(overlay.G3_SQL, 'edges', 'id', 8, dangling=m)} SELECT '{m}' AS mode, round(CAST(max(r) AS DOUBLE), 9) AS highest, round(CAST(sum(r) AS DOUBLE), 6) AS total FROM r8)" for m in ("preference", "self", "drop")))
def pagerank_dangling(spark, sf):
    """The highest rank under each treatment of nodes without out-edges, on the graph of parts and their orders."""
    nodes, edges = overlay.trade(spark, sf)
    edges, nodes, out = graph.step_table(edges), graph.step_table(nodes), None
    for mode in ("preference", "self", "drop"):
        one = centrality.pagerank(edges, nodes, iterations=8, dangling=mode).agg(F.lit(mode).alias("mode"), F.round(F.max("rank"), 9).alias("highest"), F.round(F.sum("rank"), 6).alias("total"))
        out = one if out is None else out.unionByName(one)
    return out


def _preferred_sql(rounds: int) -> str:
    parts = [G1_SQL, HOST_SQL, "pe AS MATERIALIZED (SELECT src, dst, links FROM ha)", "pn AS MATERIALIZED (SELECT host AS id, CAST(count(*) AS DOUBLE) / (SELECT count(*) FROM nodes) AS v FROM nodes GROUP BY 1)", "od AS MATERIALIZED (SELECT src, CAST(sum(links) AS DOUBLE) AS t FROM pe GROUP BY 1)", "r0 AS (SELECT id, v AS r FROM pn)"]
    for k in range(1, rounds + 1):
        p = f"r{k - 1}"
        parts.append(f"r{k} AS MATERIALIZED (SELECT n.id, 0.85::DOUBLE * (coalesce(i.s, 0) + (SELECT coalesce(sum(r), 0) FROM {p} ANTI JOIN od ON od.src = {p}.id) * v) + 0.15::DOUBLE * v AS r FROM pn n LEFT JOIN (SELECT e.dst AS id, sum(p.r * e.links / o.t) AS s FROM pe e JOIN {p} p ON p.id = e.src JOIN od o ON o.src = e.src GROUP BY 1) i ON i.id = n.id)")
    return ", ".join(parts)


@query("pagerank_weighted", f"WITH {_preferred_sql(12)} SELECT id, round(r, 9) AS rank FROM r12")
def pagerank_weighted(spark, sf):
    """Hosts by how many of their pages link, preferred by how many pages they have: the weighted and personalised form."""
    nodes, edges = overlay.web(spark, sf)
    arcs = graph.step_table(graph.quotient(edges, nodes, "host"))
    total = nodes.agg(F.count(F.lit(1)).alias("n"))
    hosts = graph.step_table(nodes.groupBy(F.col("host").alias("id")).agg(F.count(F.lit(1)).alias("k")).crossJoin(F.broadcast(total)).select("id", (F.col("k") / F.col("n")).alias("v")))
    return centrality.pagerank(arcs, hosts, iterations=12, preference=hosts, weighted=True).select("id", F.round("rank", 9).alias("rank"))


@query("harmonic_exact", f"WITH {DIST_SQL.format(g=G1_SQL)} SELECT n.id, round(coalesce(h, 0), 6) AS harmonic FROM nodes n LEFT JOIN (SELECT node AS id, sum(1.0 / d) AS h FROM ds WHERE d > 0 GROUP BY 1) USING (id)")
def harmonic_exact(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    return centrality.harmonic_exact(graph.step_table(edges), nodes).select("id", F.round("harmonic", 6).alias("harmonic"))


@query("harmonic_approx")
def harmonic_approx(spark, sf):
    """By sketches, with the relative error against the exact values."""
    nodes, edges = host_web(spark, sf)
    edges, nodes = graph.step_table(edges.select("src", "dst")), graph.step_table(nodes)
    approx, _ = centrality.harmonic_sketch(edges, nodes, 12)
    both = approx.join(centrality.harmonic_exact(edges, nodes).withColumnRenamed("harmonic", "exact"), "id")
    return both.select("id", F.round("harmonic", 6).alias("harmonic"), F.round("exact", 6).alias("exact"), F.round(F.abs(F.col("harmonic") - F.col("exact")) / F.greatest("exact", F.lit(1e-9)), 6).alias("error"))


@query("harmonic_sampled")
def harmonic_sampled(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    return centrality.harmonic_exact(graph.step_table(edges), nodes, nodes.filter("id % 5 = 0").select("id")).select("id", F.round("harmonic", 6).alias("harmonic"))


@query("distance_distribution", f"WITH {DIST_SQL.format(g=G1_SQL)} SELECT d, count(*) AS pairs FROM ds GROUP BY 1")
def distance_distribution(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    return centrality.spread(graph.step_table(edges), nodes)


SUMMARY_SQL = "SELECT round(sum(d) FILTER (d > 0) / count(*) FILTER (d > 0), 6) AS mean_distance, round(any_value(n) * (any_value(n) - 1) / sum(1.0 / d) FILTER (d > 0), 6) AS harmonic_diameter, round(count(*) / (any_value(n) * any_value(n)), 6) AS reachable FROM ds, (SELECT count(*) AS n FROM nodes)"


@query("distance_summary", f"WITH {DIST_SQL.format(g=G1_SQL)} {SUMMARY_SQL}")
def distance_summary(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    return centrality.summary(centrality.spread(graph.step_table(edges), nodes), nodes)


for _name in ("avg_distance", "harmonic_diameter", "reachable_pairs"):
    _col = {"avg_distance": "mean_distance", "harmonic_diameter": "harmonic_diameter", "reachable_pairs": "reachable"}[_name]
    query(_name, f"WITH {DIST_SQL.format(g=G1_SQL)}, sm AS ({SUMMARY_SQL}) SELECT {_col} FROM sm")(lambda spark, sf, c=_col: distance_summary(spark, sf).select(c))


@query("distance_host_graph", f"WITH {DIST_SQL.format(g=G1_SQL.replace('edges AS', 'pe AS').replace('nodes AS', 'pn AS') + ', ' + HOST_SQL.replace('edges', 'pe').replace('nodes', 'pn') + ', edges AS (SELECT src, dst FROM ha), nodes AS (SELECT DISTINCT host AS id FROM pn)')} {SUMMARY_SQL}")
def distance_host_graph(spark, sf):
    nodes, edges = host_web(spark, sf)
    edges, nodes = graph.step_table(edges.select("src", "dst")), graph.step_table(nodes)
    return centrality.summary(centrality.spread(edges, nodes), nodes)


@query("distance_sketch")
def distance_sketch(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    _, at = centrality.harmonic_sketch(graph.step_table(edges), nodes, 11)
    return centrality.summary(at, nodes)


def _table_sql() -> str:
    rank = _pagerank_sql(G1_SQL + ", " + HOST_SQL, "ha", "host", 20)
    dist = "w AS (SELECT id AS source, id AS node, 0 AS d FROM pn UNION SELECT w.source, e.dst, w.d + 1 FROM w JOIN pe e ON e.src = w.node WHERE w.d < 12), ds AS (SELECT node AS id, source, min(d) AS d FROM w GROUP BY 1, 2)"
    tops = "ti AS (SELECT row_number() OVER (ORDER BY v DESC, id) AS place, id, v FROM (SELECT pn.id, CAST(count(dst) AS DOUBLE) AS v FROM pn LEFT JOIN pe ON dst = id GROUP BY 1)), tr AS (SELECT row_number() OVER (ORDER BY v DESC, id) AS place, id, v FROM (SELECT id, round(CAST(r AS DOUBLE), 6) AS v FROM r20)), th AS (SELECT row_number() OVER (ORDER BY v DESC, id) AS place, id, v FROM (SELECT pn.id, round(coalesce(h, 0), 6) AS v FROM pn LEFT JOIN (SELECT id, sum(1.0 / d) AS h FROM ds WHERE d > 0 GROUP BY 1) USING (id)))"
    return f"WITH RECURSIVE {rank}, {dist}, {tops} SELECT place, ti.id AS indegree_node, ti.v AS indegree, tr.id AS rank_node, tr.v AS rank, th.id AS harmonic_node, th.v AS harmonic FROM ti JOIN tr USING (place) JOIN th USING (place) WHERE place <= 10"


@query("centrality_table", _table_sql())
def centrality_table(spark, sf):
    nodes, edges = host_web(spark, sf)
    return centrality.table(graph.step_table(edges.select("src", "dst")), graph.step_table(nodes))


_LISTS = f"tb AS (SELECT * FROM ({_table_sql()})), ls AS (SELECT 'indegree' AS m, indegree_node AS n FROM tb UNION ALL SELECT 'rank', rank_node FROM tb UNION ALL SELECT 'harmonic', harmonic_node FROM tb)"


@query("centrality_noise", f"WITH {_LISTS} SELECT m AS measure, round(avg(CAST(regexp_matches(n, 'pills|bets|spam') AS INT)), 6) AS spam_share FROM ls GROUP BY 1")
def centrality_noise(spark, sf):
    """The share of spam hosts in each list."""
    best = graph.step_table(centrality_table(spark, sf))
    out = None
    for name in ("indegree", "rank", "harmonic"):
        one = best.agg(F.lit(name).alias("measure"), F.round(F.avg(F.col(f"{name}_node").rlike("pills|bets|spam").cast("int")), 6).alias("spam_share"))
        out = one if out is None else out.unionByName(one)
    return out


@query("rank_agreement", f"WITH {_LISTS} SELECT a.m || '-' || b.m AS measures, count(*) FILTER (a.n = b.n) AS common FROM ls a, ls b WHERE (a.m, b.m) IN (('indegree', 'rank'), ('indegree', 'harmonic'), ('rank', 'harmonic')) GROUP BY 1")
def rank_agreement(spark, sf):
    """How many of the top ten two measures share."""
    best = graph.step_table(centrality_table(spark, sf))
    names, out = ("indegree", "rank", "harmonic"), None
    for i, a in enumerate(names):
        for b in names[i + 1 :]:
            one = best.select(F.col(f"{a}_node").alias("n")).join(best.select(F.col(f"{b}_node").alias("n")), "n").agg(F.lit(f"{a}-{b}").alias("measures"), F.count(F.lit(1)).alias("common"))
            out = one if out is None else out.unionByName(one)
    return out


@query("depth_profile", f"WITH RECURSIVE {G1_SQL}, w AS (SELECT 0 AS id, 0 AS depth UNION SELECT e.dst, w.depth + 1 FROM w JOIN edges e ON e.src = w.id WHERE w.depth < 16), lv AS (SELECT id, min(depth) AS depth FROM w GROUP BY 1), ox AS (SELECT e.src AS id, count(*) AS d, count(*) FILTER (a.host <> b.host) AS x FROM edges e JOIN nodes a ON a.id = e.src JOIN nodes b ON b.id = e.dst GROUP BY 1) SELECT depth, count(*) AS pages, round(avg(coalesce(d, 0)), 6) AS out, round(avg(coalesce(x, 0)), 6) AS external, round(avg(content), 6) AS content FROM lv JOIN nodes USING (id) LEFT JOIN ox USING (id) GROUP BY 1")
def depth_profile(spark, sf):
    nodes, edges = overlay.web(spark, sf)
    edges = graph.step_table(edges)
    return graph.by_depth(edges, nodes, graph.bfs(edges, spark.createDataFrame([(0,)], "id long")))


@query("host_cap", f"WITH {G1_SQL} SELECT id FROM (SELECT id, row_number() OVER (PARTITION BY host ORDER BY id) AS k FROM nodes) WHERE k <= 5")
def host_cap(spark, sf):
    return graph.capped(overlay.nodes(spark, sf), "id", 5).select("id")
