"""Distances from many sources at once, by sets of bits: 64 sources are a word at each node.

The arcs go to every worker as arrays of node numbers, and the words of sources are dealt over
the tasks. A level hands the bits of what it found along the arcs, so no table of pairs is made:
what leaves a task is a sum a node, or a count a distance. The work grows with sources times
arcs, so graphs whose arcs don't fit a worker (MOST_ARCS) are beyond it in time as well.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webgather.operators.sequence import numbered

#: Arcs that are held as arrays in the driver and the workers, at some 20 bytes each.
MOST_ARCS = 1 << 23


def fits(edges: DataFrame) -> bool:
    """Whether the arcs may be held as arrays. Counts them, so edges should be a written table."""
    return edges.count() <= MOST_ARCS


def coded(ids: DataFrame) -> DataFrame:
    """The rows, whose ids are unique, with k: their place by id, from 0."""
    return numbered(ids, ["id"], "k").withColumn("k", (F.col("k") - 1).cast("int"))


def kind(edges: DataFrame, ids: DataFrame) -> str:
    """The type of both the ids and the ends of the edges."""
    both = ids.select("id").unionByName(edges.select(F.col("src").alias("id"))).unionByName(edges.select(F.col("dst").alias("id")))
    return dict(both.dtypes)["id"]


def column(rows: pa.Table, name: str) -> np.ndarray:
    return rows.column(name).combine_chunks().to_numpy(zero_copy_only=False)


def places(values: pa.ChunkedArray, ids: pa.Array) -> np.ndarray:
    """Where each value is among the ids, -1 where it isn't."""
    return pc.fill_null(pc.index_in(values, value_set=ids, skip_nulls=True), -1).to_numpy()


def components(n: int, s: np.ndarray, t: np.ndarray) -> np.ndarray:
    """For each of n nodes, the least node that arcs in either direction lead to."""
    low = np.arange(n)
    while True:
        a, b = low[s], low[t]
        apart = a != b
        if not apart.any():
            return low
        s, t, a, b = s[apart], t[apart], a[apart], b[apart]
        np.minimum.at(low, np.maximum(a, b), np.minimum(a, b))
        while (low[low] != low).any():
            low = low[low]


def by_first(a: np.ndarray, b: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of numbers under n, sorted: as one number each, which is faster than finding an order."""
    return np.divmod(np.sort(a.astype(np.int64) * n + b), max(n, 1))


class Arcs:
    """Arcs among nodes 0 to n - 1 by start, and by component and end; the sources, by component and node.

    So the sources of a word lie in few components, and a level goes through the arcs of those alone.
    """

    def __init__(self, n: int, s: np.ndarray, t: np.ndarray, sources: np.ndarray):
        self.n = n
        starts, self.to = by_first(s, t, n)
        self.first = np.searchsorted(starts, np.arange(n + 1))
        part = components(n, s, t)
        self.sources = sources[np.lexsort((sources, part[sources]))]
        nodes = np.argsort(part, kind="stable")
        rank = np.empty(n, np.int64)
        rank[nodes] = np.arange(n)
        t, self.start = by_first(rank[t], s, n)
        t = nodes[t]
        self.heads = np.flatnonzero(np.concatenate([[True], t[1:] != t[:-1]])) if len(t) else np.empty(0, np.int64)
        self.ends = t[self.heads]
        # of each word, from which to which of the ends its components are
        low, high = part[self.sources[::64]], part[self.sources[np.minimum(np.arange(63, len(self.sources) + 63, 64), len(self.sources) - 1)]]
        self.spans = np.column_stack([np.searchsorted(part[self.ends], low), np.searchsorted(part[self.ends], high, side="right")])

    def _out(self, nodes: np.ndarray, bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ends, bits) along the arcs of a few nodes."""
        n = self.first[nodes + 1] - self.first[nodes]
        t = self.to[np.repeat(self.first[nodes] - (np.cumsum(n) - n), n) + np.arange(n.sum())]
        order = np.argsort(t, kind="stable")
        t = t[order]
        heads = np.flatnonzero(np.concatenate([[True], t[1:] != t[:-1]])) if len(t) else np.empty(0, np.int64)
        return t[heads], np.bitwise_or.reduceat(np.repeat(bits, n)[order], heads) if len(t) else np.empty(0, np.uint64)

    def levels(self, word: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(distance, nodes, how many of the word's 64 sources have it to them), until a level finds nothing."""
        nodes = self.sources[64 * word : 64 * word + 64]
        if not len(nodes):
            return
        a, b = self.spans[word]
        begin, end = (self.heads[x] if x < len(self.heads) else len(self.start) for x in (a, b))
        pulled, heads, starts = self.ends[a:b], self.heads[a:b] - begin, self.start[begin:end].astype(np.intp)
        room, sizes = np.empty(len(starts), np.uint64), np.diff(heads, append=len(starts))
        every = np.uint64((1 << len(nodes)) - 1)
        seen, front = np.zeros(self.n, np.uint64), np.zeros(self.n, np.uint64)
        seen[nodes] = front[nodes] = np.uint64(1) << np.arange(len(nodes), dtype=np.uint64)
        d = 0
        while len(nodes):
            yield d, nodes, np.bitwise_count(front[nodes])
            d += 1
            # few arcs are sorted by their ends; many are gone through as they lie, but for those to ends that all sources have reached
            if 16 * (self.first[nodes + 1] - self.first[nodes]).sum() < len(starts):
                ends, bits = self._out(nodes, front[nodes])
            elif len(starts) and 4 * sizes[left := np.flatnonzero(seen[pulled] != every)].sum() < len(starts):
                k = sizes[left]
                before = np.cumsum(k) - k
                ends, bits = pulled[left], np.bitwise_or.reduceat(front[starts[np.repeat(heads[left] - before, k) + np.arange(k.sum())]], before) if len(left) else np.empty(0, np.uint64)
            elif len(starts):
                ends, bits = pulled, np.bitwise_or.reduceat(np.take(front, starts, out=room, mode="clip"), heads)
            else:
                ends, bits = pulled, np.empty(0, np.uint64)
            front[nodes] = 0
            bits = bits & ~seen[ends]
            new = bits != 0
            nodes = ends[new]
            front[nodes] = bits[new]
            seen[nodes] |= bits[new]


def _words(edges: DataFrame, sources: DataFrame):
    """(the broadcast ids, the broadcast arcs, a row for each word of sources). Ids are numbered on the driver, which holds the arcs anyway."""
    spark, form = edges.sparkSession, kind(edges, sources)
    own = sources.filter("id is not null").select(F.col("id").cast(form)).distinct().toArrow().column("id")
    ends = edges.select(*(F.col(c).cast(form).alias(c) for c in ("src", "dst"))).toArrow()
    ids = pc.drop_null(pc.unique(pa.chunked_array([*own.chunks, *ends.column("src").chunks, *ends.column("dst").chunks], own.type)))
    ids = ids.take(pc.sort_indices(ids))
    s, t = (places(ends.column(c), ids) for c in ("src", "dst"))
    known = (s >= 0) & (t >= 0)
    arcs = Arcs(len(ids), s[known], t[known], np.sort(places(own, ids)))
    words = -(-len(own) // 64)
    return spark.sparkContext.broadcast(ids), spark.sparkContext.broadcast(arcs), spark.range(0, words, 1, max(1, min(words, int(spark.conf.get("spark.sql.shuffle.partitions")))))


def distribution(edges: DataFrame, sources: DataFrame) -> DataFrame:
    """d, pairs: how many nodes are at each distance from a source, itself at 0."""
    _, shared, words = _words(edges, sources)

    def run(batches):
        pairs: dict[int, int] = {}
        for batch in batches:
            for word in batch.column(0).to_pylist():
                for d, _, n in shared.value.levels(word):
                    pairs[d] = pairs.get(d, 0) + int(n.sum())
        yield pa.RecordBatch.from_arrays([pa.array(pairs.keys(), pa.int32()), pa.array(pairs.values(), pa.int64())], names=["d", "pairs"])

    return words.mapInArrow(run, "d int, pairs long").groupBy("d").agg(F.sum("pairs").alias("pairs"))


def harmonic(edges: DataFrame, sources: DataFrame) -> DataFrame:
    """id, h: the sum over the other sources that reach a node of one over their distance to it; nodes that none reaches are left out."""
    held, shared, words = _words(edges, sources)

    def run(batches):
        h = np.zeros(shared.value.n)
        for batch in batches:
            for word in batch.column(0).to_pylist():
                for d, nodes, n in shared.value.levels(word):
                    if d:
                        h[nodes] += n / d
        k = np.flatnonzero(h)
        for a in range(0, len(k), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(k[a : a + 100_000], pa.int32()), pa.array(h[k[a : a + 100_000]])], names=["k", "h"])

    def named(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([held.value.take(batch.column(0)), batch.column(1)], names=["id", "h"])

    sums = words.mapInArrow(run, "k int, h double").groupBy("k").agg(F.sum("h").alias("h"))
    return sums.mapInArrow(named, f"id {kind(edges, sources)}, h double")
