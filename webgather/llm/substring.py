"""Removal of repeated word windows: a count-min prefilter, then exact groups.

The sketches of all partitions are merged; they never count a window's anchor too low, so the
second pass groups only windows estimated repeated and loses none. See repeats for the runs.

Defined cases: a null, empty or wordless text has no words and keeps nothing of none; texts
under a window long keep all; rows with one id are one document, and spans found under the id
apply to each of its rows; a row without an id has no place in the order and keeps all its
words; equal starts don't occur within a document; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webgather.llm import repeats as R
from webgather.llm.sketch import Marked

SCHEMA = "doc_id long, n_words long, n_removed long, kept_text string, spans array<struct<start:long,end:long>>"


def _opened(found, spec: R.Spec, hot: Marked | None, flush: int = 1_500_000):
    """Every window of the open runs, by two hashes; a task sends only the first of equal ones."""
    held, n = [], 0

    def out():
        first, later = R.first_of_equal(np.concatenate(held), ("a", "b"), True)
        return R.blob_batch(R.packed(3, first, (first["a"] % R.X.U64(spec.buckets)).astype(np.int32)), R.packed(1, R.repeats_of(later["doc"], later["s"], 1), R.doc_bucket(later["doc"], spec)))

    for runs, s, _, items in found:
        times = runs["n"].astype(np.int64)
        each = np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
        at = np.repeat(s, times) + each
        rows = np.empty(len(at), R.WINDOW)
        rows["a"], rows["b"] = (items.hashed(at, at + spec.length, seed) for seed in (31, 37))
        rows["doc"], rows["s"] = np.repeat(runs["doc"], times), np.repeat(runs["s"], times) + each
        held.append(rows)
        n += len(rows)
        if n > flush:
            yield out()
            held, n = [], 0
    if held:
        yield out()


def _grouped(blobs, spec: R.Spec):
    _, later = R.first_of_equal(R._gathered(blobs, R.WINDOW, 3), ("a", "b"), True)
    yield R.repeats_of(later["doc"], later["s"], 1), []


def remove_repeated_windows(docs: DataFrame, window: int = 20, gram: int = 5, depth: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_removed, kept_text (kept words joined by one space), spans removed (word places) for every row."""
    if not 1 <= min(gram, window) <= window <= 200:
        raise ValueError("1 <= gram and window <= 200")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("body"))
    named = rows.filter("doc_id is not null")
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    spec = R.Spec("words", window, min(gram, window), True, depth, R.sketch_bits(rows, 0.16 * 2 / (window - min(gram, window) + 2)), 0, 4 * parts)
    found = R.with_spans(named, R.repeated_spans(named, spec, _opened, _grouped))
    loose = rows.filter("doc_id is null").select("doc_id", "body", F.lit(None).cast("binary").alias("spans"))

    def cut(batches):
        for batch in batches:
            out: list[list] = [[], [], [], []]
            for body, found in zip(batch.column(1), batch.column(2), strict=True):
                words = (body.as_py() or "").encode("utf-8", "surrogatepass").split()
                spans = [(a, min(b, len(words))) for a, b in R.spans_of(found.as_py()) if a < len(words)]
                kept, at = [], 0
                for a, b in spans:
                    kept += words[at:a]
                    at = b
                kept += words[at:]
                for column, value in zip(out, (len(words), len(words) - len(kept), b" ".join(kept).decode("utf-8", "replace"), [{"start": a, "end": b} for a, b in spans]), strict=True):
                    column.append(value)
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(out, kinds, strict=True))], names=["doc_id", "n_words", "n_removed", "kept_text", "spans"])

    return found.unionByName(loose).mapInArrow(cut, SCHEMA)
