"""What gathering reads, collects and joins: pages and arcs once, and no join of the log with the pages."""

import re

import pytest
from helpers import SMALL, rows_of
from pyspark.sql import functions as F

from webgather import catalog, plans  # noqa: F401
from webgather.functions import html
from webgather.operators import crawl, overlay


def _plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_pages_are_read_once(spark):
    """The labels of pages come from what parsing wrote, so no page is read again for its length."""
    nodes, edges = overlay.web(spark, SMALL, places=True)
    assert "html" not in _plan(nodes) and "html" not in _plan(edges)
    assert sorted(map(tuple, nodes.collect())) == sorted(map(tuple, overlay.nodes(spark, SMALL).collect()))


def test_the_log_needs_no_join(spark):
    edges, nodes = spark.createDataFrame([(0, 1), (1, 2)], "src long, dst long"), spark.createDataFrame([(i, f"h{i}", i) for i in range(3)], "id long, host string, ip int")
    log = crawl.gather(edges, nodes, spark.createDataFrame([(0,)], "id long"))
    assert "Join" not in _plan(log) and [tuple(r)[:4] for r in log.orderBy("id").collect()] == [(0, "h0", 0, 0), (1, "h1", 1, 1), (2, "h2", 2, 2)]


@pytest.mark.parametrize("name", ["visit_priority", "bfs_global_distance"])
def test_arcs_are_collected_once(spark, monkeypatch, name):
    calls, fits = [], crawl.reach.fits
    monkeypatch.setattr(crawl.reach, "fits", lambda edges: calls.append(1) or fits(edges))
    assert catalog.QUERIES[name](spark, SMALL).count() == 1 and len(calls) == 1


def test_each_config_as_alone(spark):
    """Also where one of them needs rounds as tables."""
    edges, nodes = spark.createDataFrame([(i, (i * 7 + j) % 30, j) for i in range(30) for j in range(3)], "src long, dst long, pos long"), spark.createDataFrame([(i, f"h{i % 4}", i % 2) for i in range(30)], "id long, host string, ip int")
    configs, seed = [crawl.Config(2, 3), crawl.Config(per_round=4), crawl.Config()], spark.createDataFrame([(0,)], "id long")
    for log, c in zip(crawl.gather_each(edges, nodes, seed, configs), configs, strict=True):
        assert sorted(map(tuple, log.collect())) == sorted(map(tuple, crawl.gather(edges, nodes, seed, c).select(*log.columns).collect()))


def test_hidden_parts_as_before(spark):
    plain = r"(?is)<script\b.*?</script\s*>|<style\b.*?</style\s*>|<!--.*?-->"
    texts = ["a<script>x</SCRIPT >b", "<scripts>x</script>", "<STYLE a='<!--'>\n</style>c-->", "<!-- <script> -->d</script>", "<script>e", "<!--->f-->", "<<style></style>>", "<style></script></style\n>g", ""]
    got = spark.createDataFrame([(x,) for x in texts], "t string").select(F.regexp_replace("t", plain, " "), html.visible("t")).collect()
    assert all(a == b for a, b in got) and [b for _, b in got] == [re.sub(plain, " ", x) for x in texts]


@pytest.mark.parametrize("name", ["wl_domain", "no_refresh", "visit_priority"])
def test_queries_read_pages_once(spark, duck, monkeypatch, name):
    def refused(*_):
        raise AssertionError("pages are read a second time, for their labels")

    monkeypatch.setattr(overlay, "nodes", refused)
    own = catalog.QUERIES[name](spark, SMALL).toPandas()
    assert len(own) and (name not in catalog.ORACLES or rows_of(own) == rows_of(duck.sql(catalog.ORACLES[name]).df()))


def test_domain_needs_no_ranges(spark, monkeypatch):
    """The task that gathers adds up the bytes, and only the domain's pages are parsed for links."""
    from webgather.operators import sequence

    def refused(*_, **__):
        raise AssertionError("the log is dealt by range for a sum that its task can make")

    monkeypatch.setattr(sequence, "running", refused)
    monkeypatch.setattr(crawl, "running", refused, raising=False)
    assert catalog.QUERIES["wl_domain"](spark, SMALL).first()["pages"] > 0
    nodes, edges = overlay.web(spark, SMALL, places=True, domain="example.org")
    own = nodes.filter("domain = 'example.org'").select("id")
    whole = overlay.web(spark, SMALL, places=True)
    assert sorted(map(tuple, edges.collect())) == sorted(map(tuple, whole[1].join(own.withColumnRenamed("id", "src"), "src").select(*edges.columns).collect()))
    assert sorted(map(tuple, nodes.collect())) == sorted(map(tuple, whole[0].collect()))


@pytest.mark.parametrize("sizes", [[], [0], [100_000, 0], [40_000, 70_000, 0, 90_000, 350_000]])
def test_seconds_on_the_link(spark, duck, tmp_path, sizes):
    """Also a domain without pages, and an empty page where a second ends."""
    rows = [(i, f"http://a.example.org/{i}", ('<a href="x">' + " " * n)[:n]) for i, n in enumerate(sizes)] + [(90, "http://b.net/", "x")]
    spark.createDataFrame(rows, "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    con = duck.cursor()
    con.sql(f"create temp view pages as select * from '{tmp_path}/pages.parquet/*.parquet'")
    assert rows_of(catalog.QUERIES["wl_domain"](spark, str(tmp_path)).toPandas()) == rows_of(con.sql(catalog.ORACLES["wl_domain"]).df())


def test_sums_as_by_tables(spark, monkeypatch):
    edges, nodes = spark.createDataFrame([(i, (i * 7 + j) % 30, j) for i in range(30) for j in range(3)], "src long, dst long, pos long"), spark.createDataFrame([(i, f"h{i % 4}", i % 2, i * i) for i in range(30)], "id long, host string, ip int, n long")
    one = crawl.gather(edges, nodes, spark.createDataFrame([(0,)], "id long"), crawl.Config(2, 3), summed="n")
    monkeypatch.setattr(crawl.reach, "fits", lambda _: False)
    two = crawl.gather(edges, nodes, spark.createDataFrame([(0,)], "id long"), crawl.Config(2, 3), summed="n").select(*one.columns)
    got = sorted(map(tuple, one.collect()))
    assert len(got) == 30 and got == sorted(map(tuple, two.collect()))
