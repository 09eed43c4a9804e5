"""Near duplicates by min-wise signatures, with sequential Bayesian verification.

Texts with equal shingle sets are folded first. Banded signatures give buckets; every member
of a bucket is paired with its least document. Signatures of a pair are compared in batches:
after each, the pair is dropped if the posterior chance that its similarity reaches the
threshold is under `miss`. Survivors are verified on their full shingle sets. Verified links
give components.

What is left are candidates of two components that share a bucket. A link across two of them
needs 3 / 7 of both set sizes (at 0.75) in common, out of shingles that more than one component
has, so documents are counted by those first: one that can't reach this exact bound has no
partner. The others are dealt in blocks within the pools that their buckets connect. A task
holds two blocks; the candidates among them, which share a band, go through the same batches of
signatures, and those that survive are verified on their sets. It sends on the links that join
components, and no pairs. So a hot bucket sends its members once a block, and no link that the
bands can see is left out.

A link at the threshold is unseen by all bands with chance (1 - t^rows)^bands, 5e-6 as set.

Defined cases: a null, empty or wordless text has an empty set, no links and stays; fewer than
`words` words are one shingle; rows with one id are one node; a row without an id takes the
component of its set, else null; equal sets get the least id; other columns are ignored.
"""

from __future__ import annotations

from functools import lru_cache
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webgather.llm import _text as X
from webgather.llm._shared import enter, joined, let_go, written
from webgather.llm.components import components

SCHEMA = "doc_id long, n_shingles long, k1 long, k2 long, sketch binary, bands array<long>"
LOWER = np.frombuffer(X.LOWER_ASCII, np.uint8)


def shingles(data: np.ndarray, offsets: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """(hash, row) of the distinct shingles of each row, sorted by row and hash."""
    data = LOWER[data]
    starts, ends, rows = X.word_spans(data, offsets)
    h = X.span_hash(X.load8(data), starts, ends, 11)
    g = X.grams(h, words)
    whole = rows[: len(g)] == rows[words - 1 :] if len(g) else np.empty(0, bool)
    bounds = X.row_bounds(rows, len(offsets) - 1)
    count = np.diff(bounds)
    few = np.flatnonzero((count > 0) & (count < words))
    acc = X.mix(count[few].astype(X.U64) * X.K2)
    for j in range(words - 1):
        has = count[few] > j
        acc[has] = X.mix(acc[has] * X.K1 + h[bounds[few[has]] + j])
    hashes, owner = np.concatenate([g[whole], acc]), np.concatenate([rows[: len(g)][whole], few])
    order = np.lexsort((hashes, owner))
    hashes, owner = hashes[order], owner[order]
    new = np.ones(len(hashes), bool)
    new[1:] = (hashes[1:] != hashes[:-1]) | (owner[1:] != owner[:-1])
    return hashes[new], owner[new]


@lru_cache(maxsize=4)
def _factors(n: int) -> np.ndarray:
    return np.random.default_rng(20_061).integers(1, 1 << 63, n, dtype=np.uint64) * X.U64(2) + X.U64(1)


def signatures(hashes: np.ndarray, owner: np.ndarray, n_rows: int, n: int) -> np.ndarray:
    """Min-wise values, n to a row that has shingles; zeros else."""
    out = np.zeros((n_rows, n), np.uint32)
    if len(hashes):
        at = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
        for i, factor in enumerate(_factors(n)):
            out[owner[at], i] = np.minimum.reduceat(((hashes * factor) >> X.U64(32)).astype(np.uint32), at)
    return out


def least_matches(n: int, threshold: float, miss: float) -> int:
    """Fewer matches of n than this leave a posterior chance under `miss`, from a uniform prior."""
    chance, m = 0.0, 0
    while m <= n:
        chance += comb(n + 1, m) * threshold**m * (1 - threshold) ** (n + 1 - m)
        if chance >= miss:
            break
        m += 1
    return m


def sketched(docs: DataFrame, words: int, n_hashes: int, rows_in_band: int, id_col: str, text_col: str) -> DataFrame:
    n_bands = n_hashes // rows_in_band

    def make(batches):
        enter()
        for batch in batches:
            data, offsets = X.buffer_of(batch.column(1))
            n = len(offsets) - 1
            size, k1, k2 = np.zeros(n, np.int64), np.zeros(n, np.uint64), np.zeros(n, np.uint64)
            sketch, bands = np.zeros((n, n_hashes), np.uint8), np.zeros((n, n_bands), np.uint64)
            for a, b in X.slices(offsets):
                h, owner = shingles(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], words)
                sig = signatures(h, owner, b - a, n_hashes)
                size[a:b] = np.bincount(owner, minlength=b - a)
                at = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]])) if len(h) else np.empty(0, int)
                if len(at):
                    k1[a + owner[at]] = np.add.reduceat(X.mix(h ^ X.K1), at)
                    k2[a + owner[at]] = np.add.reduceat(X.mix(h ^ X.K2), at)
                sketch[a:b] = (sig & 0xFF).astype(np.uint8)
                parts = sig.reshape(b - a, n_bands, rows_in_band)
                key = np.tile(X.mix(np.arange(n_bands, dtype=np.uint64) + X.K3), (b - a, 1))
                for j in range(rows_in_band):
                    key = X.mix(key * X.K1 + parts[:, :, j])
                bands[a:b] = key
            lists = pa.FixedSizeListArray.from_arrays(pa.array(bands.ravel().view(np.int64)), n_bands).cast(pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), pa.array([r.tobytes() for r in sketch], pa.binary()), lists], names=["doc_id", "n_shingles", "k1", "k2", "sketch", "bands"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("body")).mapInArrow(make, SCHEMA)


def _steps(n_hashes: int, threshold: float, miss: float, batch_size: int = 32) -> list[tuple[int, int]]:
    """After how many signature values which number of matches is needed to go on."""
    return [(n, least_matches(n, threshold, miss)) for n in range(batch_size, n_hashes + 1, batch_size)]


def survivors(x: np.ndarray, y: np.ndarray, steps: list[tuple[int, int]]) -> np.ndarray:
    """Which pairs (rows of x and y) the batches of signatures leave."""
    live, matches, done = np.arange(len(x)), np.zeros(len(x), int), 0
    for n, least in steps:
        matches = matches + (x[live, done:n] == y[live, done:n]).sum(1)
        keep = matches >= least
        live, matches, done = live[keep], matches[keep], n
    return live


def _dealt(pairs: DataFrame, most: int = 10_000) -> DataFrame:
    """Pairs (a, b) with a share s of b, a hub: of shares with about `most` pairs each."""
    hubs = written(pairs.groupBy("b").agg(F.count(F.lit(1)).alias("n")))
    dealt = joined(pairs, hubs, ["b"], "n").withColumn("shares", F.ceil(F.col("n") / most).cast("int"))
    return dealt.select("a", "b", "shares", F.pmod(F.xxhash64("a"), F.col("shares")).cast("int").alias("s"))


def _with_both(dealt: DataFrame, values: DataFrame, name: str) -> DataFrame:
    """a, b, x, y: the values of both sides of dealt pairs; those of a hub go to each of its shares."""
    own = values.select(F.col("doc_id").alias("a"), F.col(name).alias("x"))
    shares = dealt.select("b", "shares").distinct().select("b", F.explode(F.sequence(F.lit(0), F.col("shares") - 1)).alias("s"))
    hubs = shares.join(values.select(F.col("doc_id").alias("b"), F.col(name).alias("y")), "b")
    return dealt.join(own, "a").join(hubs, ["b", "s"]).select("a", "b", "x", "y")


def _likely(dealt: DataFrame, sketches: DataFrame, n_hashes: int, threshold: float, miss: float) -> DataFrame:
    """Pairs (a, b) that the sequential test leaves."""
    steps = _steps(n_hashes, threshold, miss)

    def test(batches):
        for batch in batches:
            x, y = (np.frombuffer(b"".join(v.as_py() for v in batch.column(k)), np.uint8).reshape(-1, n_hashes) for k in (2, 3))
            live = pa.array(survivors(x, y, steps))
            yield pa.RecordBatch.from_arrays([batch.column(k).take(live) for k in (0, 1)], names=["a", "b"])

    return _with_both(dealt, sketches, "sketch").mapInArrow(test, "a long, b long")


def _linked(dealt: DataFrame, texts: DataFrame, words: int, parts: tuple[int, int]) -> DataFrame:
    """Pairs whose full shingle sets reach the threshold parts[0] / parts[1]."""

    def verify(batches):
        for batch in batches:
            keep = np.zeros(batch.num_rows, bool)
            data_a, off_a = X.buffer_of(batch.column(2))
            data_b, off_b = X.buffer_of(batch.column(3))
            for s, e in X.slices(off_a + off_b):
                x, rx = shingles(data_a[off_a[s] : off_a[e]], off_a[s : e + 1] - off_a[s], words)
                y, ry = shingles(data_b[off_b[s] : off_b[e]], off_b[s : e + 1] - off_b[s], words)
                h, r = np.concatenate([x, y]), np.concatenate([rx, ry])
                order = np.lexsort((h, r))
                h, r = h[order], r[order]
                common = np.bincount(r[1:][(h[1:] == h[:-1]) & (r[1:] == r[:-1])], minlength=e - s)
                union = np.bincount(rx, minlength=e - s) + np.bincount(ry, minlength=e - s) - common
                keep[s:e] = (parts[1] * common >= parts[0] * union) & (union > 0)
            at = pa.array(np.flatnonzero(keep))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at)], names=["a", "b"])

    return _with_both(dealt, texts, "body").mapInArrow(verify, "a long, b long")


def _pair(x: str, y: str) -> list:
    return [F.greatest(x, y).alias("a"), F.least(x, y).alias("b")]


def _mixed(placed: DataFrame, found: DataFrame) -> DataFrame:
    """The members of buckets that hold more than one component, with their component c."""
    now = placed.join(found.withColumnRenamed("node", "doc_id"), "doc_id", "left").select("bucket", "doc_id", F.coalesce("component_id", "doc_id").alias("c"))
    mixed = now.groupBy("bucket").agg(F.min("c").alias("low"), F.max("c").alias("high")).filter("low <> high").select("bucket")
    return now.join(mixed, "bucket")


def _common_counts(open_: DataFrame, sets: DataFrame, texts: DataFrame, words: int) -> DataFrame:
    """doc_id, c, n (its shingles), hs (those that another component of the open buckets has too)."""

    def explode(batches):
        for batch in batches:
            data, offsets = X.buffer_of(batch.column(2))
            for s, e in X.slices(offsets):
                h, owner = shingles(data[offsets[s] : offsets[e]], offsets[s : e + 1] - offsets[s], words)
                at = pa.array(s + owner)
                yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at), pa.array(h.view(np.int64))], names=["doc_id", "c", "h"])

    asked = open_.select("doc_id", "c").distinct()
    rows = asked.join(texts, "doc_id").select("doc_id", "c", "body").mapInArrow(explode, "doc_id long, c long, h long")
    shared = rows.groupBy("h").agg(F.min("c").alias("low"), F.max("c").alias("high")).filter("low <> high").select("h")
    counts = rows.join(shared, "h", "left_semi").groupBy("doc_id", "c").agg(F.collect_list("h").alias("hs"))
    return counts.join(sets.select("doc_id", F.col("n_shingles").alias("n")), "doc_id")


def _across(open_: DataFrame, counts: DataFrame, signed: DataFrame, similarity: tuple[int, int], steps: list[tuple[int, int]], block_docs: int = 1024, block_shingles: int = 400_000) -> DataFrame:
    """Links (a > b) across components among the candidates of pools, without sending any pair."""
    p, q = similarity
    # a document that can't have enough in common with one of its least possible size has no partner
    able = written(counts.filter(q * F.size("hs") >= p * F.col("n")))
    # written, as the join asks for the hubs several times
    rows = written(open_.join(able.select("doc_id"), "doc_id", "left_semi"))
    hubs = written(rows.groupBy("bucket").agg(F.min("doc_id").alias("hub"), F.count(F.lit(1)).alias("members")))
    pools = components(joined(rows, hubs, ["bucket"], "members").select(F.col("doc_id").alias("a"), F.col("hub").alias("b"))).select(F.col("node").alias("doc_id"), F.col("component_id").alias("pool"))
    pooled = written(able.join(pools, "doc_id").join(signed, "doc_id"))
    size = pooled.groupBy("pool").agg(F.ceil(F.greatest(F.count(F.lit(1)) / block_docs, F.sum(F.size("hs")) / block_shingles)).cast("int").alias("blocks"), F.count(F.lit(1)).alias("members"))
    dealt = joined(pooled, size, ["pool"], "members").withColumn("block", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int"))
    dealt = dealt.select("pool", "block", "doc_id", "c", "n", "hs", "sketch", "bands", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    keyed = dealt.select("pool", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block", "doc_id", "c", "n", "hs", "sketch", "bands")

    def compare(table: pa.Table) -> pa.Table:
        block, doc, c, n = (table.column(k).to_numpy() for k in ("block", "doc_id", "c", "n"))
        found = []
        if len(doc) > 1:
            sketch = np.frombuffer(b"".join(table.column("sketch").to_pylist()), np.uint8).reshape(len(doc), -1)
            bands = table.column("bands").combine_chunks().flatten().to_numpy().reshape(len(doc), -1)
            one, two = np.flatnonzero(block == block.min()), np.flatnonzero(block == block.max())
            able_ = candidates(bands[one], bands[two], c[one], c[two])
            i, j = np.nonzero(able_)
            able_[:] = False
            for at in range(0, len(i), 200_000):
                k = at + survivors(sketch[one[i[at : at + 200_000]]], sketch[two[j[at : at + 200_000]]], steps)
                able_[i[k], j[k]] = True
            if able_.any():
                lists = table.column("hs").combine_chunks()
                owner = np.repeat(np.arange(len(doc)), np.diff(lists.offsets.to_numpy()))
                _, term = np.unique(lists.flatten().to_numpy(), return_inverse=True)
                x, y = able_.any(1), able_.any(0)
                found = verified_links(owner, term, n, c, one[x], two[y], p, q, able_[np.ix_(x, y)])
        return pa.table({"a": pa.array([int(max(doc[i], doc[j])) for i, j in found], pa.int64()), "b": pa.array([int(min(doc[i], doc[j])) for i, j in found], pa.int64())})

    return keyed.groupBy("pool", "low", "high").applyInArrow(compare, "a long, b long")


def candidates(x: np.ndarray, y: np.ndarray, c: np.ndarray, d: np.ndarray) -> np.ndarray:
    """Which rows of x and y, their bands, share one and are of different components (c and d)."""
    out = np.zeros((len(x), len(y)), bool)
    for k in range(x.shape[1]):
        out |= x[:, k][:, None] == y[:, k][None, :]
    return out & (c[:, None] != d[None, :])


def verified_links(owner: np.ndarray, term: np.ndarray, n: np.ndarray, c: np.ndarray, one: np.ndarray, two: np.ndarray, p: int, q: int, asked: np.ndarray, width: int = 4096) -> list[tuple[int, int]]:
    """The pairs asked for (i of one, j of two) that reach p / q and join components, a spanning forest of them."""
    order = np.argsort(term, kind="stable")
    owner, term = owner[order], term[order]
    place = np.full((2, len(n)), -1)
    place[0, one], place[1, two] = np.arange(len(one)), np.arange(len(two))
    common = np.zeros((len(one), len(two)), np.float32)
    for a in range(0, int(term[-1]) + 1 if len(term) else 0, width):
        s, e = np.searchsorted(term, a), np.searchsorted(term, a + width)
        sides = []
        for k, size in ((0, len(one)), (1, len(two))):
            at = place[k, owner[s:e]]
            m = np.zeros((size, width), np.float32)
            m[at[at >= 0], (term[s:e] - a)[at >= 0]] = 1
            sides.append(m)
        common += sides[0] @ sides[1].T
    union = n[one][:, None] + n[two][None, :] - common
    links = asked & (q * common >= p * union) & (c[one][:, None] != c[two][None, :])
    root: dict[int, int] = {}

    def top(x: int) -> int:
        while root.get(x, x) != x:
            root[x] = root.get(root[x], root[x])
            x = root[x]
        return x

    out = []
    for i, j in zip(*np.nonzero(links), strict=True):
        x, y = top(int(c[one[i]])), top(int(c[two[j]]))
        if x != y:
            root[x] = y
            out.append((int(one[i]), int(two[j])))
    return out


def near_duplicates(docs: DataFrame, words: int = 5, similarity: tuple[int, int] = (75, 100), n_hashes: int = 128, rows_in_band: int = 4, miss: float = 1e-6, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id (the least id reachable), kept for every row of docs."""
    threshold = similarity[0] / similarity[1]
    steps = _steps(n_hashes, threshold, miss)
    sets = written(sketched(docs, words, n_hashes, rows_in_band, id_col, text_col))
    # sets that several rows have, by their least document
    copies = written(sets.filter("n_shingles > 0").groupBy("k1", "k2").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("rows")).filter("rows > 1 and rep is not null"))
    folded = joined(sets.select("doc_id", "n_shingles", "k1", "k2"), copies, ["k1", "k2"], "rows", "left")
    folded = written(folded.withColumn("rep", F.when(F.col("n_shingles") > 0, F.coalesce("rep", "doc_id"))))
    others = folded.filter("rep <> doc_id").select("doc_id", "k1", "k2")
    leads = sets.filter("n_shingles > 0 and doc_id is not null").join(others, ["doc_id", "k1", "k2"], "left_anti")
    signed = leads.select("doc_id", "sketch", "bands")
    members = leads.select("doc_id", F.explode("bands").alias("bucket"))
    several = members.groupBy("bucket").agg(F.count(F.lit(1)).alias("members"), F.min("doc_id").alias("hub")).filter("members > 1")
    placed = written(joined(members, written(several), ["bucket"], "members").select("bucket", "doc_id", "hub"))
    # all that follows needs the texts and signatures of these documents alone
    some = written(placed.select("doc_id").distinct())
    own_id = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("body"))
    texts = written(own_id.join(some, "doc_id", "left_semi"))
    signed = written(signed.join(some, "doc_id", "left_semi"))
    pairs = written(_dealt(written(placed.filter("doc_id <> hub").select(*_pair("doc_id", "hub")).distinct())))
    likely = written(_likely(pairs, signed, n_hashes, threshold, miss).distinct())
    edges = written(_linked(_dealt(likely), texts, words, similarity).distinct())
    found = components(edges)
    open_ = written(_mixed(placed.select("bucket", "doc_id"), found))
    let_go(docs.sparkSession)
    ours = written(_common_counts(open_, sets, texts, words))
    more = written(_across(open_, ours, signed, similarity, steps).distinct())
    if not more.isEmpty():
        found = components(found.select(F.col("node").alias("a"), F.col("component_id").alias("b")).unionByName(more))
    return (
        folded.join(found.withColumnRenamed("node", "rep"), "rep", "left")
        .select("doc_id", "n_shingles", F.coalesce("component_id", "rep", "doc_id").alias("component_id"))
        .withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))
    )
