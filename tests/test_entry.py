"""What the driver calls."""

import __spark_entry__ as entry


def test_names():
    queries, oracles = entry.queries(), entry.oracle_sql()
    assert set(oracles) <= set(queries) and len(queries) > 150


def test_flagship(spark):
    df = entry.entry(spark)
    assert df.count() > 0 and "harmonic" in df.columns


def test_scans_prune_columns(spark):
    plan = entry.queries()["url_parts"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()
    assert "html" not in plan.split("ReadSchema")[-1]
