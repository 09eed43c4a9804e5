"""Queries against DuckDB on the smallest tables."""

import pytest
from helpers import SMALL, rows_of

from webgather import catalog, plans  # noqa: F401

SLOW = {"crawl_run", "crawl_round", "no_refresh", "bfs_hostwise", "pagerank_residual", "pagerank_damping", "wl_deep", "wl_regional", "avg_distance", "harmonic_diameter", "reachable_pairs", "distance_distribution", "polite_stream", "stream_static_join", "stream_windows"}


@pytest.mark.parametrize("name", [n for n in catalog.ORACLES if n not in SLOW])
def test_oracle(spark, duck, name):
    own, theirs = catalog.QUERIES[name](spark, SMALL).toPandas(), duck.sql(catalog.ORACLES[name]).df()
    assert rows_of(own) == rows_of(theirs)


@pytest.mark.parametrize("name", ["wl_threads", "wl_delay", "wl_scale", "powerlaw_fit", "shingle_minhash", "frontier_two_queue"])
def test_runs(spark, name):
    assert catalog.QUERIES[name](spark, SMALL).count() > 0
