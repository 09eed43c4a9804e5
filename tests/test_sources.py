"""Sources, sinks and streams."""

import os

from pyspark.sql import functions as F

from webgather.operators import asof, measures
from webgather.operators.sequence import numbered
from webgather.sources import archive
from webgather.streaming import stream


def test_archive_round_trip(spark, tmp_path):
    archive.register(spark)
    rows = [("http://a/é", "2024", 200, "<p>é\r\n\r\nWARC/1.0 x"), ("http://b", None, None, None), ("http://c", "d", 404, "")]
    df = spark.createDataFrame(rows, archive.RECORD)
    df.repartition(2).write.format("archive").option("roll_bytes", 10).mode("append").save(str(tmp_path / "w"))
    got = {r["uri"]: (r["status"], r["payload"]) for r in spark.read.format("archive").load(str(tmp_path / "w")).collect()}
    assert got == {"http://a/é": (200, rows[0][3]), "http://b": (0, ""), "http://c": (404, "")}
    assert len([n for n in os.listdir(tmp_path / "w") if n[0] != "."]) == 3


def test_a_broken_archive_ends(tmp_path):
    good = archive.encode("u", "d", 200, b"x" * 100)
    assert [r[3] for r in archive.decode(good + good + b"junk")] == [b"x" * 100] * 2 and list(archive.decode(b"")) == []


def test_link_list(spark, tmp_path):
    archive.register(spark)
    (tmp_path / "a.tsv").write_text("x\ty\nno tab\np\tq\n")
    assert sorted(tuple(r) for r in spark.read.format("linklist").load(str(tmp_path)).collect()) == [("p", "q"), ("x", "y")]


def test_numbers_are_dense(spark):
    df = spark.range(1000).select((F.col("id") * 7919 % 1000).alias("k")).repartition(5)
    got = numbered(df, ["k"]).orderBy("k").collect()
    assert [r["seq"] for r in got] == list(range(1, 1001))


def test_stream_is_the_batch(spark, tmp_path):
    rows = spark.range(200).select(F.col("id").alias("seq"), (F.col("id") % 7).alias("host"), (F.col("id") * 3).alias("arrive_us"))
    live = stream.replay(spark, rows, str(tmp_path / "s"), 3, "seq")
    got = {r["seq"]: r["start_us"] for r in stream.run(stream.polite(live, 50)).collect()}
    last, want = {}, {}
    for k in range(200):
        want[k] = last[k % 7] = max(3 * k, last.get(k % 7, -(10**9)) + 50)
    assert got == want


def test_asof(spark):
    left = spark.createDataFrame([(1, 5), (1, 1), (2, 9)], "k long, t long")
    right = spark.createDataFrame([(1, 2, "a"), (1, 5, "b"), (2, 10, "c")], "k long, t long, v string")
    assert {(r["k"], r["t"]): r["v"] for r in asof.join(left, right, "k", "t", ["v"]).collect()} == {(1, 5): "b", (1, 1): None, (2, 9): None}


def test_measures(spark):
    log = spark.createDataFrame([(0, 100, 0), (1_000_000, 300, 0)], "arrive_us long, length long, s int")
    r = measures.speed(log, "s").first()
    assert (r["rate"], r["bytes_a_page"]) == (2.0, 200.0)
    assert measures.link_use(log, 1_000_000, 4800.0).first()["peak_use"] == 0.5
