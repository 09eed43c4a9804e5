"""Gathering in one task against the loop over lists, and against rounds as tables."""

import random

import pytest
from helpers import SMALL, rows_of
from test_methods import gathered_in_turn

from webgather import catalog, plans  # noqa: F401
from webgather.operators import crawl

CONFIGS = [crawl.Config(), crawl.Config(2, 3), crawl.Config(1, 2, cap=4), crawl.Config(2, 3, order=("id",)), crawl.Config(3, 4, cap=5, order=("id",)), crawl.Config(1, 2, rounds=5), crawl.Config(2, 4, budget=20), crawl.Config(cap=6), crawl.Config(per_ip=3)]


def _web(seed, n=60, hosts=9, ips=3):
    rng = random.Random(seed)
    nodes = [(i, f"h{i % hosts}", i % hosts % ips) for i in rng.sample(range(n), n)]
    arcs = sorted({(rng.randrange(n), rng.randrange(n) if rng.random() < 0.6 else rng.randrange(6)) for _ in range(4 * n)})
    # several links may have one place, and some pages are not known
    return nodes[:-3], [(a, b, rng.randrange(40)) for a, b in arcs]


def _frames(spark, nodes, edges, seed):
    return spark.createDataFrame(edges, "src long, dst long, pos long"), spark.createDataFrame(nodes, "id long, host string, ip int"), spark.createDataFrame([(seed,)], "id long")


@pytest.fixture
def no_tables(monkeypatch):
    def refused(*_):
        raise AssertionError("a job a round: time grows with the rounds, not with the pages")

    monkeypatch.setattr(crawl, "_by_tables", refused)


@pytest.mark.parametrize("k", range(len(CONFIGS)))
def test_one_task_is_the_loop(spark, no_tables, k):
    nodes, edges = _web(k)
    ids = {i for i, _, _ in nodes}
    known = [e for e in sorted(edges, key=lambda e: (e[0], e[2], e[1])) if e[0] in ids and e[1] in ids]
    log = crawl.gather(*_frames(spark, nodes, edges, nodes[0][0]), CONFIGS[k]).collect()
    assert {x["id"]: (x["depth"], x["round"], x["found"], x["seq"]) for x in log} == gathered_in_turn(known, nodes, nodes[0][0], CONFIGS[k])
    assert len(log) == len({x["id"] for x in log})


def test_one_task_is_the_tables(spark):
    nodes, edges = _web(40)
    e, n, s = _frames(spark, nodes, edges, nodes[0][0])
    one, other = crawl.gather(e, n, s, CONFIGS[2]), crawl._by_tables(e, n, s, CONFIGS[2])
    assert one.dtypes == other.select(*one.columns).dtypes and rows_of(one.toPandas()) == rows_of(other.toPandas())
    assert crawl.gather(e, n, s.filter("id < 0"), CONFIGS[2]).count() == 0


def test_deeper_than_the_sql(spark, no_tables):
    """A chain of 40 pages on a host: gathered to its end, which SQL of 16 steps leaves out."""
    e, n, s = _frames(spark, [(i, "h", 0) for i in range(40)], [(i, i + 1, 0) for i in range(39)], 0)
    assert crawl.gather(e, n, s).agg({"depth": "max"}).first()[0] == 39


@pytest.mark.parametrize("name", ["bfs_hostwise", "crawl_round", "no_refresh", "wl_domain", "bfs_global_distance", "visit_priority"])
def test_queries_without_tables(spark, duck, no_tables, name):
    own = catalog.QUERIES[name](spark, SMALL).toPandas()
    assert len(own)
    if name in catalog.ORACLES:
        assert rows_of(own) == rows_of(duck.sql(catalog.ORACLES[name]).df())


@pytest.mark.parametrize("name", ["crawl_round", "bfs_global_distance", "visit_priority", "wl_domain", "no_refresh"])
def test_queries_number_no_pages_by_jobs(spark, duck, monkeypatch, name):
    def refused(*_, **__):
        raise AssertionError("ids numbered by jobs: longer than the gathering")

    monkeypatch.setattr(crawl.reach, "coded", refused)
    own = catalog.QUERIES[name](spark, SMALL).toPandas()
    assert len(own) and (name not in catalog.ORACLES or rows_of(own) == rows_of(duck.sql(catalog.ORACLES[name]).df()))


def test_pages_are_parsed_once(spark):
    from webgather.operators import overlay

    plan = overlay.web(spark, SMALL, places=True)[1]._jdf.queryExecution().optimizedPlan().toString()
    assert "regexp_extract_all" not in plan


@pytest.mark.parametrize("form", ["string", "int"])
def test_ids_of_other_kinds(spark, no_tables, form):
    """A page of no id, a link to no page, and a seed that is none, with ids that aren't long."""
    e, n, s = _frames(spark, [(i, f"h{i % 2}", i % 2) for i in range(9)], [(i, i + 1, 0) for i in range(12)] + [(3, 0, 1)], 0)
    as_form = lambda df, *cs: df.withColumns({c: df[c].cast(form) for c in cs})
    n = as_form(n, "id").unionByName(spark.createDataFrame([(None, "h5", 0)], f"id {form}, host string, ip int"))
    log = crawl.gather(as_form(e, "src", "dst"), n, as_form(s.union(spark.createDataFrame([(77,)], "id long")), "id"))
    assert dict(log.dtypes)["id"] == form
    assert sorted((int(r["id"]), r["depth"], r["round"]) for r in log.collect()) == [(i, i, i + 1) for i in range(9)]


def test_basic_table_without_tables_or_pairs(spark, no_tables, monkeypatch):
    from webgather.operators import centrality

    monkeypatch.setattr(centrality, "distances", None)
    assert {r["snapshot"] for r in catalog.QUERIES["wl_basic_table"](spark, SMALL).collect()} == {"regional", "deep", "shallow"}
