"""Distances by sets of bits against a search from each source, and queries that must not make the table of pairs."""

import random
from collections import deque

import numpy as np
import pytest
from helpers import SMALL, rows_of

from webgather import catalog, plans  # noqa: F401
from webgather.operators import centrality, reach


def searched(arcs, source):
    far, queue = {source: 0}, deque([source])
    while queue:
        i = queue.popleft()
        for a, b in arcs:
            if a == i and b not in far:
                far[b] = far[i] + 1
                queue.append(b)
    return far


def _graph(kind):
    rng = random.Random(5)
    if kind == "chain":  # longer than a word of sources, and than the 16 steps of the SQL
        return [(i, i + 1) for i in range(90)], list(range(91)), list(range(91))
    if kind == "names":  # some without arcs, sources with strings as ids
        return [(f"n{rng.randrange(80)}", f"n{rng.randrange(80)}") for _ in range(120)], [f"n{i}" for i in range(100)], [f"n{i}" for i in range(0, 100, 3)]
    return [(rng.randrange(150), min(rng.randrange(150), rng.randrange(150))) for _ in range(500)], list(range(150)), list(range(150))


@pytest.mark.parametrize("kind", ["chain", "names", "dense"])
def test_levels_are_the_search(spark, kind):
    arcs, nodes, sources = _graph(kind)
    arcs = sorted({a for a in arcs if a[0] != a[1]})
    form = "string" if kind == "names" else "long"
    edges, own = spark.createDataFrame(arcs, f"src {form}, dst {form}"), spark.createDataFrame([(s,) for s in sources], f"id {form}")
    pairs, h = {}, {}
    for s in sources:
        for i, d in searched(arcs, s).items():
            pairs[d] = pairs.get(d, 0) + 1
            if d:
                h[i] = h.get(i, 0) + 1 / d
    assert {r["d"]: r["pairs"] for r in centrality.spread(edges, own).collect()} == pairs
    assert {r["id"]: r["h"] for r in reach.harmonic(edges, own).collect()} == pytest.approx(h)
    assert {r["d"]: r["pairs"] for r in centrality.distribution(centrality.distances(edges, own)).collect()} == pairs


def test_no_arcs(spark):
    edges, own = spark.createDataFrame([], "src long, dst long"), spark.createDataFrame([(3,), (4,)], "id long")
    assert [tuple(r) for r in centrality.spread(edges, own).collect()] == [(0, 2)] and reach.harmonic(edges, own).count() == 0
    assert centrality.spread(edges, own.filter("id > 9")).count() == 0


@pytest.mark.parametrize("name", ["distance_summary", "avg_distance", "harmonic_diameter", "reachable_pairs", "distance_distribution", "harmonic_exact"])
def test_without_pairs(spark, duck, monkeypatch, name):
    def refused(*_, **__):
        raise AssertionError("the table of pairs grows with the square of the pages")

    monkeypatch.setattr(centrality, "distances", refused)
    assert rows_of(catalog.QUERIES[name](spark, SMALL).toPandas()) == rows_of(duck.sql(catalog.ORACLES[name]).df())


def test_harmonic_by_sample_without_pairs(spark, monkeypatch):
    """A fifth of the sources, scaled to all: against a search from each of them."""
    monkeypatch.setattr(centrality, "distances", None)
    arcs, nodes, _ = _graph("dense")
    edges, own = spark.createDataFrame(sorted(set(arcs)), "src long, dst long"), spark.createDataFrame([(i,) for i in nodes], "id long")
    far = [searched(arcs, s) for s in nodes if s % 5 == 0]
    want = {i: 5 * sum(1 / f[i] for f in far if f.get(i)) for i in nodes}
    assert {r["id"]: r["harmonic"] for r in centrality.harmonic_exact(edges, own, own.filter("id % 5 = 0")).collect()} == pytest.approx(want)


def test_sketch_error_without_pairs(spark, monkeypatch):
    monkeypatch.setattr(centrality, "distances", None)
    assert catalog.QUERIES["measure_sketch_error"](spark, SMALL).count() == 1


def test_a_word_goes_through_its_components_alone():
    """Three rings whose nodes lie between each other's: a level of 64 sources takes the arcs of one."""
    n = 64
    s = np.concatenate([3 * np.arange(n) + k for k in range(3)])
    t = np.concatenate([3 * ((np.arange(n) + 1) % n) + k for k in range(3)])
    arcs = reach.Arcs(3 * n + 1, s, t, np.arange(3 * n))
    assert (arcs.spans[:, 1] - arcs.spans[:, 0]).tolist() == [n, n, n]
    for word in range(3):
        assert [(d, int(k.sum())) for d, _, k in arcs.levels(word)] == [(d, n) for d in range(n)]
    assert reach.components(5, np.array([4, 1]), np.array([3, 4])).tolist() == [0, 1, 2, 1, 1]


def test_balls_that_stay_are_not_sent_again(spark, monkeypatch):
    """The ends of a star settle at once and those of a chain one after the other; sums are exact for so few nodes."""
    arcs = [(100 + i, 200) for i in range(10)] + [(i, i + 1) for i in range(8)]
    edges = spark.createDataFrame(arcs, "src long, dst long")
    nodes = spark.createDataFrame([(i,) for i in sorted({x for a in arcs for x in a})], "id long")
    changed, write = [], centrality.step_table

    def watched(df):
        out = write(df)
        changed.append({r["id"] for r in out.filter("changed").collect()})
        return out

    monkeypatch.setattr(centrality, "step_table", watched)
    got = {r["id"]: r["harmonic"] for r in centrality.harmonic_sketch(edges, nodes)[0].collect()}
    ids = [r["id"] for r in nodes.collect()]
    far = {i: searched(arcs, i) for i in ids}
    assert got == pytest.approx({i: sum(1 / f[i] for f in far.values() if f.get(i)) for i in ids}, rel=1e-4)
    assert not any(100 <= i < 200 for own in changed[1:] for i in own)
    assert all(i in changed[i] and not any(i in own for own in changed[i + 1 :]) for i in range(7)) and 8 in changed[8]


def test_reached_ends_are_left_out():
    """A level that only two nodes are missing goes through their arcs, not through all; distances are those of a search."""
    n = 200
    arcs = [(i, (i + j) % n) for i in range(n) for j in range(1, 40)] + [(0, n), (n, n + 1)]
    s, t = np.array(arcs).T
    own = reach.Arcs(n + 2, s, t, np.arange(n + 2))
    found = {}
    for word in range(4):
        for d, nodes, k in own.levels(word):
            found[d] = found.get(d, 0) + int(k.sum())
    far = {i: searched(arcs, i) for i in range(n + 2)}
    assert found == {d: sum(x == d for f in far.values() for x in f.values()) for d in found} and sum(found.values()) == sum(map(len, far.values()))
