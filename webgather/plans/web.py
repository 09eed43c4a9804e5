"""Queries on URLs, parsing and filters."""

from __future__ import annotations

from pyspark.sql import functions as F

from webgather.catalog import query, table
from webgather.functions import html, suffix, urls
from webgather.operators import filters, robots
from webgather.operators.filters import ResponseFilter as R
from webgather.operators.filters import UrlFilter as U

PARTS = r"""regexp_extract(url, '^(?:([A-Za-z][A-Za-z0-9+.\-]*):)?(?://([^/?#]*))?([^?#]*)(?:\?([^#]*))?(?:#(.*))?$', %d)"""
HREF = r"""(?is)<a\s[^>]*?href\s*=\s*"([^"]*)"[^>]*>"""
VISIBLE = r"""regexp_replace(html, '(?is)<script\b.*?</script\s*>|<style\b.*?</style\s*>|<!--.*?-->', ' ', 'g')"""
LINKS_SQL = f"""
    v AS (SELECT page_id, url, {VISIBLE} AS body FROM pages),
    x AS (SELECT page_id, url, regexp_extract_all(body, '{HREF}', 1) AS hrefs FROM v),
    l AS (SELECT page_id, url, CAST(pos AS INTEGER) AS pos, replace(hrefs[pos], '&amp;', '&') AS href FROM (SELECT *, unnest(range(1, len(hrefs) + 1)) AS pos FROM x)),
    t AS (SELECT *, CASE WHEN href = '' THEN regexp_extract(url, '^([^#]*)', 1) WHEN regexp_matches(href, '^[A-Za-z][A-Za-z0-9+.-]*:') THEN href WHEN href LIKE '//%' THEN regexp_extract(url, '^([a-z]+):', 1) || ':' || href
        WHEN href LIKE '/%' THEN regexp_extract(url, '^([a-z]+://[^/?#]*)', 1) || href WHEN href LIKE '?%' THEN regexp_extract(url, '^([^?#]*)', 1) || href WHEN href LIKE '#%' THEN regexp_extract(url, '^([^#]*)', 1) || href
        ELSE regexp_extract(url, '^([a-z]+://[^?#]*/)', 1) || href END AS target FROM l)"""


@query("url_parts", f"SELECT page_id, lower({PARTS % 1}) AS scheme, lower({PARTS % 2}) AS host, {PARTS % 3} AS path, {PARTS % 4} AS query, {PARTS % 5} AS fragment FROM pages")
def url_parts(spark, sf):
    return table(spark, sf, "pages").select("page_id", urls.split("url").alias("u")).select("page_id", "u.scheme", "u.host", "u.path", "u.query", "u.fragment")


@query("url_normalise", r"SELECT page_id, CASE WHEN regexp_matches(u, '^[a-z]+://[^/?]+$') THEN u || '/' ELSE regexp_replace(u, '^([a-z]+://[^/?]+)\?', '\1/?') END AS normal FROM (SELECT page_id, regexp_replace(url, '#.*$', '') AS u FROM pages)")
def url_normalise(spark, sf):
    return table(spark, sf, "pages").select("page_id", urls.normalise("url").alias("normal"))


@query("url_unescape_reserved", r"SELECT event_id, '/u%2F' || user_id || '%3Fx~' || upper(event_type) || '%C3%A9' AS stays FROM events")
def url_unescape_reserved(spark, sf):
    made = F.concat(F.lit("/%75%2f"), F.col("user_id"), F.lit("%3fx%7e"), F.upper("event_type"), F.lit("é"))
    return table(spark, sf, "events").select("event_id", urls.unescape(made).alias("stays"))


@query("url_resolve", f"WITH {LINKS_SQL} SELECT page_id, pos, target FROM t")
def url_resolve(spark, sf):
    return html.exploded_links(table(spark, sf, "pages")).select("page_id", F.col("pos").cast("int").alias("pos"), "target")


@query("host_key", r"SELECT page_id, regexp_extract(url, '^([a-z]+://[^/?#]*)', 1) AS lane, regexp_extract(url, '^[a-z]+://[^/?#]*([^#]*)', 1) AS rest FROM pages")
def host_key(spark, sf):
    return table(spark, sf, "pages").select("page_id", urls.lane_key("url").alias("lane"), urls.remainder("url").alias("rest"))


@query("path_query", r"SELECT count(*) AS urls, count(DISTINCT regexp_extract(url, '^([a-z]+://[^/?#]*)', 1)) AS lanes, CAST(sum(strlen(url)) AS BIGINT) AS bytes_whole, CAST(sum(strlen(regexp_extract(url, '^[a-z]+://[^/?#]*([^#]*)', 1))) AS BIGINT) AS bytes_rest FROM pages")
def path_query(spark, sf):
    """What leaving out the lane's key saves."""
    pages = table(spark, sf, "pages")
    return pages.agg(F.count(F.lit(1)).alias("urls"), F.countDistinct(urls.lane_key("url")).alias("lanes"), F.sum(F.octet_length("url")).alias("bytes_whole"), F.sum(F.octet_length(urls.remainder("url"))).alias("bytes_rest"))


@query("registrable_domain", r"""
    SELECT DISTINCT h AS host, CASE WHEN h = 'pages.example.net' THEN NULL WHEN h LIKE '%.pages.example.net' THEN regexp_extract(h, '([^.]+\.pages\.example\.net)$', 1) ELSE regexp_extract(h, '([^.]+\.[^.]+)$', 1) END AS domain
    FROM (SELECT regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS h FROM pages)""")
def registrable_domain(spark, sf):
    return suffix.registrable(table(spark, sf, "pages").select(urls.host("url").alias("h")), "h", suffix.rules(spark))


@query("extract_links", f"WITH {LINKS_SQL} SELECT page_id, pos, href FROM t")
def extract_links(spark, sf):
    return html.exploded_links(table(spark, sf, "pages")).select("page_id", F.col("pos").cast("int").alias("pos"), "href")


@query("extract_text", rf"""SELECT page_id, md5(trim(regexp_replace(replace(replace(replace(replace(replace(replace(regexp_replace({VISIBLE}, '(?s)<[^>]*>', ' ', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&'), '\s+', ' ', 'g'))) AS text_md5 FROM pages""")
def extract_text(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.md5(html.text("html")).alias("text_md5"))


@query("extract_title", r"SELECT page_id, trim(regexp_replace(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title', 1), '\s+', ' ', 'g')) AS title FROM pages")
def extract_title(spark, sf):
    return table(spark, sf, "pages").select("page_id", html.title("html").alias("title"))


@query("parser_consistency", "SELECT CAST(0 AS BIGINT) AS differ, true AS same")
def parser_consistency(spark, sf):
    return html.consistency(table(spark, sf, "pages")).agg(F.count(F.lit(1)).alias("differ")).withColumn("same", F.col("differ") == 0)


@query("parser_naive_ablation", r"SELECT CAST(sum(len(regexp_extract_all(html, '(?i)href\s*=\s*[^>]+'))) AS BIGINT) AS naive, CAST(sum(len(regexp_extract_all(html, '(?is)<a\s[^>]*?href\s*=\s*\"[^\"]*\"[^>]*>'))) AS BIGINT) AS parsed FROM pages")
def parser_naive_ablation(spark, sf):
    """A second, careless parser sees other links."""
    pages = table(spark, sf, "pages")
    return pages.agg(F.sum(F.size(F.regexp_extract_all("html", F.lit(r"(?i)href\s*=\s*[^>]+"), F.lit(0)))).alias("naive"), F.sum(F.size(html.anchors("html"))).alias("parsed"))


PREFETCH = "scheme_in(http, https) and domain_in(example.com, example.org) and not has_param(utm_source) and not longer_than(200) and not deeper_than(6)"


@query("filter_prefetch", r"""
    SELECT page_id FROM pages WHERE regexp_matches(url, '^https?://') AND regexp_matches(url, '^[a-z]+://([^/?#]*\.)?example\.(com|org)([/?#]|$)')
    AND NOT regexp_matches(url, '[?&]utm_source(=|&|#|$)') AND length(url) <= 200 AND len(list_filter(string_split(regexp_extract(url, '^[a-z]+://[^/?#]*([^?#]*)', 1), '/'), lambda s: s <> '')) <= 6""")
def filter_prefetch(spark, sf):
    return filters.parse(PREFETCH).apply(table(spark, sf, "pages")).select("page_id")


def responses(spark, sf):
    """A made-up fetch result for each page."""
    return table(spark, sf, "pages").select("page_id", "url", F.when(F.col("page_id") % 10 == 0, 404).when(F.col("page_id") % 10 == 1, 301).otherwise(200).alias("status"), F.lit("text/html").alias("content_type"), F.col("html").alias("body"), F.length("html").cast("long").alias("length"))


RESPONSES_SQL = "r AS (SELECT page_id, url, CASE page_id % 10 WHEN 0 THEN 404 WHEN 1 THEN 301 ELSE 200 END AS status, 'text/html' AS content_type, html AS body, length(html) AS length FROM pages)"


@query("filter_postfetch", f"WITH {RESPONSES_SQL} SELECT page_id, length FROM r WHERE status = 200 AND content_type = 'text/html' AND length BETWEEN 500 AND 5000 AND NOT regexp_matches(body, '(?i)viagra')")
def filter_postfetch(spark, sf):
    keep = R.status_in(200) & R.type_is("text/html") & R.length_between(500, 5000) & ~R.body_like("(?i)viagra")
    return keep.apply(responses(spark, sf)).select("page_id", "length")


@query("filter_algebra", r"""SELECT page_id, (a AND NOT b) OR (b AND NOT a) AS either, NOT (a AND b) AS not_both, (NOT a) OR (NOT b) AS by_law FROM (SELECT page_id, url LIKE 'https:%' AS a, regexp_matches(url, '^[a-z]+://[^/?#]*example\.org([/?#]|$)') AS b FROM pages)""")
def filter_algebra(spark, sf):
    a, b = U.scheme_in("https"), U.domain_in("example.org")
    return table(spark, sf, "pages").select("page_id", (a ^ b).make().alias("either"), (~(a & b)).make().alias("not_both"), (~a | ~b).make().alias("by_law"))


STAGES = filters.Pipeline(U.scheme_in("http", "https"), ~U.has_param("utm_source"), R.status_in(200), R.length_between(0, 4000), ~R.body_like("(?i)<article[^>]*></article>"))


@query("filter_stages", rf"""WITH {RESPONSES_SQL},
    f AS (SELECT NOT regexp_matches(url, '[?&]utm_source(=|&|#|$)') AS b, status = 200 AS c, length BETWEEN 0 AND 4000 AS d, NOT regexp_matches(body, '(?i)<article[^>]*></article>') AS e FROM r)
    SELECT count(*) AS n_input, count(*) AS n_schedule, count(*) FILTER (b) AS n_fetch, count(*) FILTER (b AND c) AS n_parse, count(*) FILTER (b AND c AND d) AS n_follow, count(*) FILTER (b AND c AND d AND e) AS n_store FROM f""")
def filter_stages(spark, sf):
    return STAGES.counts(responses(spark, sf))


@query("robots_rules", r"""
    WITH u AS (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]*([^?#]*)', 1) AS path FROM pages)
    SELECT page_id, NOT (path LIKE '/fr/%' AND NOT path LIKE '/fr/1%') AS allowed FROM u""")
def robots_rules(spark, sf):
    text = "User-agent: *\nDisallow: /fr/\nAllow: /fr/1\nCrawl-delay: 2\n\nUser-agent: other\nDisallow: /\n"
    rules = spark.createDataFrame(robots.parse(text), robots.RULES)
    asked = table(spark, sf, "pages").select("page_id", urls.host("url").alias("host"), urls.path("url").alias("path"))
    every = asked.select("host").distinct().crossJoin(F.broadcast(rules.drop("host")))
    return robots.allowed(asked, every, "gatherer").select("page_id", "allowed")


@query("robots_disallowed_count", r"SELECT count(*) AS asked, count(*) FILTER (path LIKE '/fr/%' AND NOT path LIKE '/fr/1%') AS refused FROM (SELECT regexp_extract(url, '^[a-z]+://[^/?#]*([^?#]*)', 1) AS path FROM pages)")
def robots_disallowed_count(spark, sf):
    return robots_rules(spark, sf).agg(F.count(F.lit(1)).alias("asked"), F.count_if(~F.col("allowed")).alias("refused"))


@query("trap_guard", r"SELECT page_id, page_id % 9 <= 5 AND d <= 3 AS safe FROM (SELECT page_id, len(list_filter(string_split(regexp_extract(url, '^[a-z]+://[^/?#]*([^?#]*)', 1), '/'), lambda s: s <> '')) AS d FROM pages)")
def trap_guard(spark, sf):
    guarded = table(spark, sf, "pages").withColumn("hops", F.col("page_id") % 9)
    return guarded.select("page_id", filters.trap_guard(5, 3, 4).make().alias("safe"))


@query("domain_restrict", r"SELECT page_id FROM pages WHERE regexp_matches(url, '^[a-z]+://([^/?#]*\.)?example\.org([/?#:]|$)')")
def domain_restrict(spark, sf):
    return U.domain_in("example.org").apply(table(spark, sf, "pages")).select("page_id")


@query("filter_quality", """
    WITH f AS (SELECT quality = 1 AS good, regexp_matches(text, '\\*\\*\\*|\\| ') = false AS pass FROM documents JOIN labels USING (doc_id))
    SELECT count(*) AS n, count(*) FILTER (pass) AS passed, round(count(*) FILTER (pass AND good) / count(*) FILTER (pass), 6) AS precision, round(count(*) FILTER (pass AND good) / count(*) FILTER (good), 6) AS recall FROM f""".replace("\\\\", "\\"))
def filter_quality(spark, sf):
    keep = ~R.body_like(r"\*\*\*|\| ")
    joined = table(spark, sf, "documents").select("doc_id", F.col("text").alias("body")).join(table(spark, sf, "labels"), "doc_id").select((F.col("quality") == 1).alias("good"), keep.make().alias("pass"))
    both = F.count_if(F.col("good") & F.col("pass"))
    return joined.agg(F.count(F.lit(1)).alias("n"), F.count_if("pass").alias("passed"), F.round(both / F.count_if("pass"), 6).alias("precision"), F.round(both / F.count_if("good"), 6).alias("recall"))
