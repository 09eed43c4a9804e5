"""Windows of a fixed length that repeat across documents: what both substring operators share.

A document is a sequence of items, words or bytes, and a window is `length` items. Each window
is owned by its least gram of `gram` items, an anchor, so equal windows are owned by equal grams
at the same place in them. Consecutive windows of one owner make a run; an item sequence has
about 2 / (length - gram + 2) runs an item, which is what is counted, sent and grouped:

1. a sketch of all anchors tells which may repeat (it never misses one that does);
2. runs of such anchors are grouped by anchor and content. In a task only the first of equal
   runs is sent on, the others are repeats already. Where they meet, again all but the first
   of equal runs are repeats whole;
3. anchors with several different runs are open. A set of bits that marks the first run of
   each of their contents (and perhaps others, which costs work alone) goes back to the texts,
   and a third pass sends what these runs hold to a resolver: window hashes to sort, or bytes
   for suffix arrays. How a document is cut into runs depends on the document alone;
4. the repeats of each document are joined to its text, which crosses the network this once.

A common line that a third of all documents hold sends one run a task in steps 2 and 3, and
anchors with more than `hot` runs are dealt out by window in step 3. Rows cross the network as
packed arrays, one to a task and bucket, each number in as many bytes as the largest of the task
needs: with more input than the sketch has cells for, most runs are sent once.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webgather.llm import _text as X
from webgather.llm._shared import written
from webgather.llm.sketch import Marked, marked_keys

RUN = np.dtype([("fp", "<u8"), ("r", "<u8"), ("doc", "<i8"), ("s", "<i4"), ("n", "u1")])
FOUND = np.dtype([("doc", "<i8"), ("s", "<i4"), ("n", "u1")])
WINDOW = np.dtype([("a", "<u8"), ("b", "<u8"), ("doc", "<i8"), ("s", "<i4")])
POSITION_BITS = 20
#: A set of bits takes 128 MB at most, whatever the input: with more keys it lets more through.
MOST_BITS = 30
BLOBS = "kind int, bucket int, blob binary"


@dataclass(frozen=True)
class Spec:
    """by_start: an earlier start in the same document counts too; kind: words or bytes; finer: resolving tasks a partition."""

    kind: str
    length: int
    gram: int
    by_start: bool
    depth: int
    bits: int
    hot: int
    buckets: int
    finer: int = 1


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """The least of every w consecutive values."""
    step = 1
    while step * 2 <= w:
        x = np.minimum(x[:-step], x[step:])
        step *= 2
    return np.minimum(x[: len(x) - (w - step)], x[w - step :]) if step < w else x


class Items:
    """The items of a few documents, their offsets by document, and hashes of spans of them."""

    def __init__(self, kind: str, gram: int, data: np.ndarray, offsets: np.ndarray):
        self.kind, self.gram = kind, gram
        self.words8 = X.load8(data)
        if kind == "words":
            starts, ends, rows = X.word_spans(data, offsets)
            self.items = X.span_hash(self.words8, starts, ends, 7)
            self.offsets = X.row_bounds(rows, len(offsets) - 1)
        else:
            self.offsets = offsets
        self.n = int(self.offsets[-1])

    def grams(self, a: int, b: int) -> np.ndarray:
        """Hashes of the grams within items a to b."""
        k, n = self.gram, b - a - self.gram + 1
        if n <= 0:
            return np.empty(0, np.uint64)
        if self.kind == "words":
            return X.grams(self.items[a:b], k)
        v, acc = self.words8[a:b], np.zeros(n, np.uint64)
        for j in [*range(0, k - 7, 8), *([k - 8] if k % 8 else [])]:
            acc = (acc ^ v[j : j + n]) * X.K1
            acc ^= acc >> X.U64(32)
        return X.mix(acc)

    def hashed(self, starts: np.ndarray, ends: np.ndarray, seed: int) -> np.ndarray:
        if self.kind == "bytes":
            return X.span_hash(self.words8, starts, ends, seed)
        acc = X.mix((ends - starts).astype(np.uint64) * X.K1 + X.U64(seed))
        live = np.arange(len(starts))
        for j in range(int((ends - starts).max(initial=0))):
            live = live[ends[live] - starts[live] > j]
            acc[live] = X.mix(acc[live] * X.K1 + self.items[starts[live] + j])
        return acc


def runs(items: Items, length: int, most: int = 0) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(document, first window, windows, anchor, offsets) of the runs; documents and places are those of the whole batch."""
    offsets, most = items.offsets, most or 1 << (POSITION_BITS - 1)
    for first, last in X.slices(offsets, most):
        a, b = int(offsets[first]), int(offsets[last])
        for at in range(a, max(a + 1, b - length + 1), most):
            end = min(b, at + most + length - 1)
            found = _runs(items, offsets[first : last + 1], at, end, length)
            if found is not None:
                doc, s, count, fp = found
                yield first + doc, s, count, fp, offsets


def _runs(items: Items, offsets: np.ndarray, a: int, b: int, length: int):
    w = length - items.gram + 1
    g = items.grams(a, b)
    n = len(g) - w + 1
    if n <= 0:
        return None
    mask = X.U64((1 << POSITION_BITS) - 1)
    owner = (sliding_min((g & ~mask) | np.arange(len(g), dtype=np.uint64), w) & mask).astype(np.int64)
    cut = np.zeros(n + 1, np.int32)
    ends = offsets[1:]
    np.add.at(cut, np.clip(np.maximum(offsets[:-1], ends - length + 1) - a, 0, n), 1)
    np.add.at(cut, np.clip(ends - a, 0, n), -1)
    valid = np.cumsum(cut[:-1]) == 0
    new = valid.copy()
    new[1:] &= ~valid[:-1] | (owner[1:] != owner[:-1])
    starts = np.flatnonzero(new)
    if not len(starts):
        return None
    breaks = np.append(np.flatnonzero(new | ~valid), n)
    count = breaks[np.searchsorted(breaks, starts, side="right")] - starts
    return np.searchsorted(offsets, starts + a, side="right") - 1, starts + a, count, g[owner[starts]]


def _batches_of_items(batch: pa.RecordBatch, spec: Spec, text: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, Items]]:
    data, offsets = X.buffer_of(batch.column(text))
    for a, b in X.slices(offsets):
        own, off = data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        yield a, b, own, off, Items(spec.kind, spec.gram, own, off)


def _anchors(batch: pa.RecordBatch, spec: Spec) -> Iterator[np.ndarray]:
    for _, _, _, _, items in _batches_of_items(batch, spec, 1):
        for _, _, _, fp, _ in runs(items, spec.length):
            yield fp


def anchor_key(fp: np.ndarray) -> np.ndarray:
    """What of an anchor crosses the network: 40 bits. Anchors that agree in them count as one with several contents, which costs work alone."""
    return fp >> X.U64(24)


def narrowed(rows: np.ndarray) -> tuple[bytes, np.ndarray]:
    """(the least document and how many bytes each field takes, the rows as such bytes)."""
    base, columns, widths = rows["doc"].min(), [], []
    for name in rows.dtype.names:
        x = rows[name].astype("<u8") - (base.astype("<u8") if name == "doc" else X.U64(0))  # modulo 2**64, as in widened
        widths.append(-(-int(x.max()).bit_length() // 8))
        columns.append(x.view(np.uint8).reshape(-1, 8)[:, : widths[-1]])
    return base.tobytes() + bytes(widths), np.concatenate(columns, axis=1)


def widened(head: bytes, body: bytes, n: int, dtype: np.dtype) -> np.ndarray:
    widths = head[8:]
    raw, out, at = np.frombuffer(body, np.uint8).reshape(n, sum(widths)), np.empty(n, dtype), 0
    for name, k in zip(dtype.names, widths, strict=True):
        x = np.zeros((n, 8), np.uint8)
        x[:, :k] = raw[:, at : at + k]
        x, at = x.view("<u8").ravel(), at + k
        out[name] = (x + np.frombuffer(head, "<u8", count=1) if name == "doc" else x).astype(dtype[name])
    return out


def packed(kind: int, rows: np.ndarray, bucket: np.ndarray) -> tuple[list, list, list]:
    """A blob a bucket: number of rows in four bytes, head, body."""
    if not len(rows):
        return [], [], []
    order = np.argsort(bucket, kind="stable")
    bucket = bucket[order]
    head, raw = narrowed(rows[order])
    at = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
    return [kind] * len(at), bucket[at].tolist(), [len(x).to_bytes(4, "little") + head + x.tobytes() for x in np.split(raw, at[1:])]


def blob_batch(*groups: tuple[list, list, list]) -> pa.RecordBatch:
    kinds, buckets, blobs = ([x for g in groups for x in g[k]] for k in range(3))
    return pa.RecordBatch.from_arrays([pa.array(kinds, pa.int32()), pa.array(buckets, pa.int32()), pa.array(blobs, pa.binary())], names=["kind", "bucket", "blob"])


def doc_bucket(doc: np.ndarray, spec: Spec) -> np.ndarray:
    return (X.mix(doc.astype(np.uint64)) % X.U64(spec.buckets)).astype(np.int32)


def repeats_of(doc: np.ndarray, s: np.ndarray, n: np.ndarray | int) -> np.ndarray:
    out = np.empty(len(doc), FOUND)
    out["doc"], out["s"], out["n"] = doc, s, n
    return out


def first_of_equal(rows: np.ndarray, keys: tuple[str, str], by_start: bool) -> tuple[np.ndarray, np.ndarray]:
    """(rows that no equal one comes before, rows that are repeats), by document and start or document alone."""
    rows = rows[np.lexsort((rows["s"], rows["doc"], rows[keys[1]], rows[keys[0]]))]
    if not len(rows):
        return rows, rows
    new = np.ones(len(rows), bool)
    new[1:] = (rows[keys[0]][1:] != rows[keys[0]][:-1]) | (rows[keys[1]][1:] != rows[keys[1]][:-1])
    at = np.flatnonzero(new)
    lead = at[np.cumsum(new) - 1]
    later = rows["doc"] > rows["doc"][lead]
    if by_start:
        later |= (rows["doc"] == rows["doc"][lead]) & (rows["s"] > rows["s"][lead])
    return rows[~later], rows[later]


def run_key(rows: np.ndarray) -> np.ndarray:
    """A hash of a run's place and content."""
    return X.mix(X.mix(rows["doc"].astype(np.uint64) * X.K1 + rows["s"].astype(np.uint64)) ^ rows["r"])


def runs_of(batches, spec: Spec, asked: Marked, marked: Marked | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, Items]]:
    """(runs of the anchors asked for, and that are marked, places of their first items among those of the slice, its bytes, its items)."""
    for batch in batches:
        ids = np.asarray(batch.column(0))
        for a, _, data, _, items in _batches_of_items(batch, spec, 1):
            for doc, s, count, fp, offsets in runs(items, spec.length):
                own = asked(fp)
                if not own.any():
                    continue
                doc, s, count = doc[own], s[own], count[own]
                rows = np.empty(len(s), RUN)
                rows["fp"], rows["n"] = fp[own], count
                rows["r"] = items.hashed(s, s + count - 1 + spec.length, 23)
                rows["doc"], rows["s"] = ids[a + doc], s - offsets[doc]
                if marked is not None:
                    own = marked(run_key(rows))
                    rows, s = rows[own], s[own]
                if len(rows):
                    yield rows, s, data, items


def _candidates(batches, spec: Spec, repeated: Marked, flush: int = 1_500_000):
    held, n = [], 0

    def out():
        first, later = first_of_equal(np.concatenate(held), ("fp", "r"), spec.by_start)
        bucket = (first["fp"] % X.U64(spec.buckets)).astype(np.int32)
        first["fp"] = anchor_key(first["fp"])
        return blob_batch(
            packed(0, first, bucket),
            packed(1, repeats_of(later["doc"], later["s"], later["n"]), doc_bucket(later["doc"], spec)),
        )

    for rows, _, _, _ in runs_of(batches, spec, repeated):
        held.append(rows)
        n += len(rows)
        if n > flush:
            yield out()
            held, n = [], 0
    if held:
        yield out()


def _gathered(batches, dtype: np.dtype, kind: int) -> np.ndarray:
    """The rows in blobs of a kind; those of one head are widened together."""
    end, by_head = 12 + len(dtype.names), {}
    for b in batches:
        for k, x in zip(b.column(0).to_pylist(), b.column(2), strict=True):
            if k == kind:
                x = x.as_py()
                own = by_head.setdefault(x[4:end], [0, []])
                own[0] += int.from_bytes(x[:4], "little")
                own[1].append(x[end:])
    found = [widened(head, b"".join(bodies), n, dtype) for head, (n, bodies) in by_head.items()]
    return np.concatenate(found) if found else np.empty(0, dtype)


def _settle_runs(blobs, spec: Spec):
    """Equal runs: repeats, and as blobs the keys of the first runs of anchors that have several (kind 2) and the hot anchors (kind 4)."""
    first, later = first_of_equal(_gathered(blobs, RUN, 0), ("fp", "r"), spec.by_start)
    groups = []
    if len(first):
        new_fp = np.concatenate([[True], first["fp"][1:] != first["fp"][:-1]])
        new_run = new_fp | np.concatenate([[True], first["r"][1:] != first["r"][:-1]])
        anchor = np.cumsum(new_fp) - 1
        kinds = np.bincount(anchor, weights=new_run)
        for kind, keys in ((2, run_key(first[kinds[anchor] > 1])), (4, first["fp"][new_fp][kinds > spec.hot] if spec.hot else [])):
            if len(keys):
                groups.append(([kind], [0], [keys.tobytes()]))
    yield repeats_of(later["doc"], later["s"], later["n"]), groups


def merged_spans(s: np.ndarray, e: np.ndarray) -> np.ndarray:
    """Sorted spans without overlap, as rows (start, end)."""
    order = np.argsort(s, kind="stable")
    s, e = s[order], np.maximum.accumulate(e[order])
    new = np.concatenate([[True], s[1:] > e[:-1]])
    at = np.flatnonzero(new)
    return np.column_stack([s[at], np.concatenate([e[at[1:] - 1], e[-1:]])]).astype("<i4")


def _by_document(batches, spec: Spec):
    """doc_id, repeated spans of items."""
    done = _gathered(batches, FOUND, 1)
    done = done[np.argsort(done["doc"], kind="stable")]
    docs, at = np.unique(done["doc"], return_index=True)
    at = np.append(at, len(done))
    for a in range(0, len(docs), 20_000):
        spans = []
        for k in range(a, min(len(docs), a + 20_000)):
            x = done[at[k] : at[k + 1]]
            s = x["s"].astype(np.int64)
            spans.append(merged_spans(s, s + x["n"] - 1 + spec.length).tobytes())
        yield pa.RecordBatch.from_arrays([pa.array(docs[a : a + 20_000]), pa.array(spans, pa.binary())], names=["doc_id", "spans"])


def _dealt(rows: DataFrame, spec: Spec, f: Callable, schema: str, finer: int = 1) -> DataFrame:
    parts = finer * max(1, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return rows.repartition(parts, "bucket").mapInArrow(f, schema)


def _keys_of_kind(settled: DataFrame, kind: int) -> Marked | None:
    """The keys in blobs of a kind as a set of bits sized by their number; None if there are none."""
    blobs = settled.filter(F.col("kind") == kind).select("blob")
    n = (blobs.agg(F.sum(F.octet_length("blob"))).first()[0] or 0) // 8
    if not n:
        return None
    bits = int(np.clip(np.ceil(np.log2(8.0 * n)), 16, MOST_BITS))
    return marked_keys(blobs, lambda b: (np.frombuffer(x.as_py(), "<u8") for x in b.column(0)), 1, bits, 1)


def repeated_spans(docs: DataFrame, spec: Spec, opened: Callable, resolve: Callable) -> DataFrame:
    """doc_id and spans of the documents that have repeats.

    docs: doc_id (not null) and body. opened(runs, spec, hot anchors) turns open runs, as
    runs_of gives them, into blobs of kind 3 and repeats of kind 1; resolve(blobs of a bucket,
    spec) yields repeats, and further blobs.
    """
    share = docs.sparkSession.sparkContext.broadcast
    repeated = share(marked_keys(docs, lambda b: _anchors(b, spec), spec.depth, spec.bits))
    sent = docs.mapInArrow(lambda b: _candidates(b, spec, repeated.value), BLOBS)

    def settled_by(f):
        def run(batches):
            blobs = list(batches)
            found, groups = [_gathered(blobs, FOUND, 1)], []  # repeats that a task found by itself go on
            for repeats, others in f(blobs, spec):
                found.append(repeats)
                groups += others
            found = np.concatenate(found)
            yield blob_batch(packed(1, found, doc_bucket(found["doc"], spec)), *groups)

        return run

    settled = written(_dealt(sent, spec, settled_by(_settle_runs), BLOBS))
    done, marked = settled.filter("kind = 1"), _keys_of_kind(settled, 2)
    if marked is not None:
        marks = share((marked, _keys_of_kind(settled, 4)))
        contents = docs.mapInArrow(lambda b: opened(runs_of(b, spec, repeated.value, marks.value[0]), spec, marks.value[1]), BLOBS)
        done = done.unionByName(_dealt(contents, spec, settled_by(resolve), BLOBS, spec.finer))
    # stored, so that what was sent to find the spans is off the disk before the texts cross the network
    return written(_dealt(done, spec, lambda b: _by_document(b, spec), "doc_id long, spans binary"))


def with_spans(docs: DataFrame, found: DataFrame) -> DataFrame:
    """doc_id, body and the spans, if any, of every document; one without id has none.

    The join is the same at any size: were a small table of spans broadcast, what runs on little
    input would say nothing about what larger input sends.
    """
    return docs.join(found.hint("merge"), "doc_id", "left").select("doc_id", "body", "spans")


def spans_of(blob: bytes | None) -> list[tuple[int, int]]:
    return list(map(tuple, np.frombuffer(blob, "<i4").reshape(-1, 2).tolist())) if blob else []


def sketch_bits(docs: DataFrame, items_per_byte: float, least: int = 16, most: int = MOST_BITS) -> int:
    """Eight cells for each expected anchor, by the estimated size of the input; at most 2**most cells."""
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return int(np.clip(np.ceil(np.log2(max(1.0, 8 * 2.0 * size * items_per_byte))), least, most))
