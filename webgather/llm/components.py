"""Connected components of an edge table, by contraction in tasks and jumps to parents.

Edges run from the larger node a to the smaller node b. Edges with one a meet in a task, which
makes stars of all that it has: each node but the least of what the task connects gets one edge, to that least
node. A node that came as an a is of that task alone, so the edge that the task makes for it is its own: a
parent. Then each edge jumps from b to the parent of b, by a join of the table with its own edges.
Nothing changes further once all edges are stars.

A round is that one join and one deal of what it gives, written to the shared folder; of the
graph only totals reach the driver. What a task holds is the nodes of its share. After
contraction a node is the a of at most one edge a task. As a b it may have very many, which
are one side of a join whose other side has the node once, both read from tables: Spark splits these where they are skewed.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webgather.llm._shared import enter, let_go, written

EDGES = "a long, b long, own boolean"


def stars(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node it is connected with) for each node that isn't the least itself."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while len(x):
        # of two roots the larger takes the least that it meets as its parent
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(up := root[root], root):
            root = up
        x, y = root[x], root[y]
        x, y = x[x != y], y[x != y]
    rest = root != np.arange(len(nodes))
    return nodes[rest], nodes[root[rest]]


def _contracted(batches, most: int = 2_000_000) -> Iterator[pa.RecordBatch]:
    """The stars of all edges of a task; own: whether the node came as an a."""
    enter()
    a, b, came, held, n = np.empty(0, np.int64), np.empty(0, np.int64), [], [], 0

    def merged():
        own = np.unique(np.concatenate([*came, *(x for x, _ in held)]))
        return (*stars(np.concatenate([a, *(x for x, _ in held)]), np.concatenate([b, *(y for _, y in held)])), own)

    for batch in batches:
        held.append((np.asarray(batch.column(0)), np.asarray(batch.column(1))))
        n += batch.num_rows
        if n > most:
            a, b, own = merged()
            came, held, n = [own], [], 0
    if held or came:
        a, b, own = merged()
        own = np.isin(a, own, assume_unique=True)
        for k in range(0, len(a), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(x[k : k + 100_000]) for x in (a, b, own)], names=["a", "b", "own"])


def _dealt(edges: DataFrame) -> DataFrame:
    return written(edges.repartition("a").mapInArrow(_contracted, EDGES))


def components(edges: DataFrame, a: str = "a", b: str = "b", rounds: int = 60) -> DataFrame:
    """node, component_id (the least node reachable) for each node that has an edge."""

    def total(table: DataFrame) -> tuple:
        return tuple(table.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b", "own").cast("decimal(38,0)"))).first())

    let_go(edges.sparkSession)
    given = edges.select(F.greatest(a, b).cast("long").alias("a"), F.least(a, b).cast("long").alias("b")).filter("a <> b")
    now = _dealt(given.mapInArrow(_contracted, EDGES).select("a", "b"))
    last = total(now)
    for _ in range(rounds):
        parents = now.filter("own").select(F.col("a").alias("b"), F.col("b").alias("up"))
        now = _dealt(now.select("a", "b").join(parents, "b", "left").select("a", F.coalesce("up", "b").alias("b")))
        if (new := total(now)) == last:
            break
        last = new
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    # all edges are stars now: one for each node but the least
    return now.select(F.col("a").alias("node"), F.col("b").alias("component_id")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component_id")).distinct())
