"""What is left on disk by steps whose result is elsewhere."""

import numpy as np

from webgather.llm import sketch


def _shuffled(spark):
    files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {n for i in range(files.size()) if (n := files.apply(i).getName()).startswith("shuffle_")}


def test_a_sketch_leaves_no_shuffle(spark):
    before = _shuffled(spark)
    rows = spark.range(0, 4000, 1, 4).selectExpr("id % 3000 as k")
    marked = sketch.marked_keys(rows, lambda b: [np.asarray(b.column(0)).astype("<u8") * sketch.ROWS[3]], 1, 18)
    assert marked(np.arange(1000, dtype="<u8") * sketch.ROWS[3]).all()
    assert not _shuffled(spark) - before
