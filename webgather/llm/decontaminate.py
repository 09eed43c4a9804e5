"""Benchmark decontamination with one Aho-Corasick automaton.

Texts and items are normalised alike: A-Z become a-z, ASCII other than letters and digits
parts words, words are joined by one space. All windows of the items go into one automaton
and each text is scanned once; a hit's place among the words leads back to its place in the
original text. The automaton is built on the workers from the item texts, whose size is
checked: items of more than `most_bytes` are dealt into blocks, one automaton at a time. The
rows then go through the blocks one after the other, each adding the words it hits and the
items it finds to those of the blocks before, so the result is that of one block.

Defined cases: a null or wordless text has no words, no hits and isn't contaminated; a null
or wordless item has no window; items with equal windows are all reported; rows with one id,
or without one, stay apart; an empty table of either kind gives no hits; other columns are
ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, StringType, StructType

from webgather.llm._shared import enter, worker_cache, written

#: Lower case for A-Z, a space for what parts words, all else unchanged.
NORMAL = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
SCHEMA = "doc_id long, n_words long, n_hit long, items array<string>, spans array<struct<start:long,end:long>>"
#: Bytes of item texts in one automaton; its nodes take about fifty times as much.
MOST_BYTES = 8 << 20


def words_of(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(NORMAL).split() if text else []


def windows_of(words: list[bytes], size: int) -> Iterator[bytes]:
    """Each run of `size` words, or all words where there are fewer, framed by spaces."""
    for i in range(max(1, len(words) - size + 1) if words else 0):
        yield b" " + b" ".join(words[i : i + size]) + b" "


@worker_cache(maxsize=2)
def _automaton(items: tuple[tuple[str, str], ...], size: int):
    """None if there is no window; values: (words in the window, ids of its items)."""
    import ahocorasick

    found: dict[bytes, dict[str, None]] = {}
    for item, text in items:
        for w in windows_of(words_of(text), size):
            found.setdefault(w, {})[item] = None
    machine = ahocorasick.Automaton()
    for w, ids in found.items():
        machine.add_word(w.decode("latin-1"), (w.count(b" ") - 1, tuple(ids)))
    if not found:
        return None
    machine.make_automaton()
    return machine


def _original_spans(text: str, hit: np.ndarray) -> list[dict]:
    """Runs of hit words as places in the text, in code points."""
    raw = text.encode("utf-8", "surrogatepass")
    inside = np.frombuffer(raw.translate(NORMAL), np.uint8) != 32
    edge = np.diff(np.concatenate([[0], inside.astype(np.int8), [0]]))
    starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    point = np.cumsum(np.concatenate([[0], (np.frombuffer(raw, np.uint8) & 0xC0) != 0x80]))
    run = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
    return [{"start": int(point[starts[a]]), "end": int(point[ends[b - 1]])} for a, b in zip(np.flatnonzero(run == 1), np.flatnonzero(run == -1), strict=True)]


def scan(text: str | None, machine) -> tuple[int, np.ndarray, set[str]]:
    """(words, mask of hit words, items found) of one text."""
    words = words_of(text)
    hit, items = np.zeros(len(words), bool), set()
    if words and machine is not None:
        flat = b" " + b" ".join(words) + b" "
        gaps = None
        for end, (n, ids) in machine.iter(flat.decode("latin-1")):
            if gaps is None:
                gaps = np.flatnonzero(np.frombuffer(flat, np.uint8) == 32)
            last = int(np.searchsorted(gaps, end))
            hit[last - n : last] = True
            items.update(ids)
    return len(words), hit, items


def _blocks(items: DataFrame, item_id: str, item_text: str, most_bytes: int) -> list:
    """Broadcasts of (item, text) pairs, each of at most about most_bytes of text."""
    tests = items.select(F.col(item_id).cast("string").alias("item"), F.col(item_text).alias("body")).filter("item is not null and body is not null")
    total = tests.agg(F.sum(F.octet_length("body"))).first()[0] or 0
    n = max(1, -(-total // most_bytes))
    parts = [tests.filter(F.pmod(F.xxhash64("item"), F.lit(n)) == b) if n > 1 else tests for b in range(n)]
    return [items.sparkSession.sparkContext.broadcast(tuple(sorted((r["item"], r["body"]) for r in p.collect()))) for p in parts]


def _scanned(docs: DataFrame, text: int, blocks: list, size: int, finish: Callable, schema) -> DataFrame:
    """finish(batch of docs, (words, mask of hit words, items) of each row), after the rows have gone through all blocks."""
    n, names = len(docs.columns), list(docs.columns)
    state = StructType([*docs.schema.fields]).add("_hit" + "_".join(names), BinaryType()).add("_items" + "_".join(names), ArrayType(StringType()))
    for k, held in enumerate(blocks):
        last = k + 1 == len(blocks)

        def search(batches, held=held, k=k, last=last):
            enter(_automaton)
            machine = _automaton(held.value, size)
            for batch in batches:
                found = []
                for i, body in enumerate(batch.column(text)):
                    words, hit, items = scan(body.as_py(), machine)
                    if k:
                        hit |= np.unpackbits(np.frombuffer(batch.column(n)[i].as_py(), np.uint8), count=words).astype(bool)
                        items.update(batch.column(n + 1)[i].as_py())
                    found.append((words, hit, items))
                if last:
                    yield finish(pa.RecordBatch.from_arrays(batch.columns[:n], names=names), found)
                else:
                    masks, items = pa.array([np.packbits(h).tobytes() for _, h, _ in found], pa.binary()), pa.array([sorted(i) for _, _, i in found], pa.list_(pa.string()))
                    yield pa.RecordBatch.from_arrays([*batch.columns[:n], masks, items], names=state.names)

        docs = docs.mapInArrow(search, schema if last else state)
        if not last:
            docs = written(docs)
    return docs


def contamination(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text", size: int = 13, most_bytes: int = MOST_BYTES) -> DataFrame:
    """doc_id, n_words, n_hit, items found, spans hit (code points of the original) for every row of docs."""

    def report(batch, found):
        spans = [_original_spans(text.as_py(), hit) if ids else [] for text, (_, hit, ids) in zip(batch.column(1), found, strict=True)]
        columns = [pa.array([n for n, _, _ in found], pa.int64()), pa.array([int(hit.sum()) for _, hit, _ in found], pa.int64()), pa.array([sorted(ids) for _, _, ids in found], pa.list_(pa.string()))]
        places = pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
        return pa.RecordBatch.from_arrays([batch.column(0), *columns, places], names=["doc_id", "n_words", "n_hit", "items", "spans"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("body"))
    return _scanned(rows, 1, _blocks(items, item_id, item_text, most_bytes), size, report, SCHEMA)


def flagged(found: DataFrame, one_in: int = 20) -> DataFrame:
    """With contaminated: at least one word hit and at least one word in `one_in`."""
    return found.withColumn("contaminated", (F.col("n_hit") > 0) & (F.lit(one_in) * F.col("n_hit") >= F.col("n_words")))


def uncontaminated(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 13, one_in: int = 20, most_bytes: int = MOST_BYTES) -> DataFrame:
    """The rows of docs that aren't contaminated, all columns as they were: no row moves to another task."""

    def clean(batch, found):
        return batch.filter(pa.array([not (hit.any() and one_in * int(hit.sum()) >= n) for n, hit, _ in found], pa.bool_()))

    return _scanned(docs, docs.columns.index(text_col), _blocks(items, "item_id", "text", most_bytes), size, clean, docs.schema)
