"""Language identification by prediction by partial matching over bytes.

For each language a tree of byte contexts up to `order` bytes is counted on a bounded sample.
A byte that its context has not seen escapes to the next shorter context, with method C's
escape probability and the seen bytes excluded; below order 0 all bytes are alike. The counts
are then frozen, and the code length of every (context, byte) under every language is put into
one table, so that scoring a text is a lookup per byte, and its language the shortest code.

The sample is the `sample_docs` documents of each language with the least hash of their id, and
at most `sample_bytes` bytes of whole texts. Only text and language are learned from.

Defined cases: a null text, or one with no letter, is `und` with score 0; ties go to the
language first by name; of rows with one id those with a language and a text are learned from; with nothing to learn from every row is `und`; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from webgather.llm import _text as X
from webgather.llm._shared import enter

SCHEMA = "doc_id long, lang_pred string, score double, bits_per_byte double"
#: Bytes of text looked up at once: each takes a code length for every language.
SLICE = 1 << 17
ASCII_LETTER = np.zeros(256, bool)
ASCII_LETTER[[*range(65, 91), *range(97, 123)]] = True


def sample(docs: DataFrame, usable: Column, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample_docs: int = 250) -> DataFrame:
    """lang and body of the sampled documents, in order of the hash of their ids."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(lang_col).alias("lang"), F.col(text_col).alias("body"))
    order = Window.partitionBy("lang").orderBy("h", "doc_id")
    ids = rows.filter(usable & F.col("lang").isNotNull() & F.col("doc_id").isNotNull()).select("doc_id", "lang", F.xxhash64("doc_id").alias("h"))
    chosen = ids.withColumn("k", F.row_number().over(order)).filter(F.col("k") <= sample_docs).select("doc_id").distinct()
    return rows.filter(usable & F.col("lang").isNotNull() & F.col("body").isNotNull()).join(F.broadcast(chosen), "doc_id", "left_semi").select("lang", "body", F.xxhash64("doc_id").alias("h"), "doc_id")


class ContextTrees:
    """Frozen code lengths; `train` maps a language to its texts."""

    def __init__(self, train: dict[str, list[bytes]], order: int = 3, sample_bytes: int = 1 << 20):
        self.langs = sorted(train)
        texts = {}
        for lang in self.langs:
            own, n = [], 0
            for t in train[lang]:
                if own and n + len(t) > sample_bytes:
                    continue
                own.append(t)
                n += len(t)
            texts[lang] = own
        seen = np.unique(np.concatenate([np.frombuffer(b"".join(t), np.uint8) for t in texts.values()])) if texts else np.empty(0, np.uint8)
        self.n = n = len(seen) + 1
        self.symbol = np.zeros(256, np.int32)
        self.symbol[seen] = np.arange(1, n)
        streams = [np.concatenate([np.concatenate([np.zeros(order, np.int64), self.symbol[np.frombuffer(t, np.uint8)]]) for t in texts[g]]) for g in self.langs]
        table = np.full((1, n, len(self.langs)), 1.0 / n)
        row_of = np.zeros(1, np.int32)
        for k in range(order + 1 if self.langs else 0):
            codes = []
            for s in streams:
                c = np.zeros(len(s) - k, np.int64)
                for j in range(k + 1):
                    c = c * n + s[j : len(s) - k + j]
                codes.append(np.unique(c[c % n != 0], return_counts=True))  # what stands before a text is context only
            contexts = np.unique(np.concatenate([c // n for c, _ in codes]))
            below = row_of[contexts % max(1, n ** (k - 1))] if k else np.zeros(len(contexts), np.int64)
            rows = table[below].copy()
            for g, (c, m) in enumerate(codes):
                count = np.zeros((len(contexts), n))
                count[np.searchsorted(contexts, c // n), c % n] = m
                total, kinds = count.sum(1, keepdims=True), (count > 0).sum(1, keepdims=True)
                own, base = total[:, 0] > 0, rows[:, :, g]
                rest = np.maximum(1e-9, np.where(count > 0, 0, base).sum(1, keepdims=True))
                p = np.where(count > 0, count, kinds * base / rest) / np.maximum(1, total + kinds)
                rows[own, :, g] = p[own]
            wider = np.zeros(n**k, np.int32)
            if k:
                wider[:] = np.tile(row_of, n)
            wider[contexts] = len(table) + np.arange(len(contexts), dtype=np.int32)
            table, row_of = np.concatenate([table, rows]), wider
            del rows
        self.order, self.row_of = order, row_of
        self.bits = (-np.log2(np.maximum(table, 1e-30))).reshape(table.shape[0] * n, len(self.langs))

    def lengths(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Bits of each row's code under each language."""
        out = np.zeros((len(offsets) - 1, len(self.langs)), np.float64)
        s = self.symbol[data]
        context = np.zeros(len(s), np.int32)
        for j in range(self.order, 0, -1):
            earlier = np.zeros(len(s), np.int32)
            earlier[j:] = s[:-j] if len(s) > j else 0
            for i in range(j):
                at = offsets[:-1] + i
                earlier[at[at < offsets[1:]]] = 0
            context = context * self.n + earlier
        cell = self.row_of[context].astype(np.int64) * self.n + s
        full = offsets[1:] > offsets[:-1]
        if full.any():
            out[full] = np.add.reduceat(self.bits[cell], offsets[:-1][full], axis=0)
        return out


def _has_letter(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    count = np.concatenate([[0], np.cumsum(ASCII_LETTER[data])])
    found = count[offsets[1:]] > count[offsets[:-1]]
    for k in np.flatnonzero(~found):
        text = data[offsets[k] : offsets[k + 1]].tobytes().decode("utf-8", "replace")
        found[k] = any(map(str.isalpha, text))
    return found


def predict(trees: ContextTrees, column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Language, its share of likelihood, and bits a byte of its code, for each text of a column."""
    data, offsets = X.buffer_of(column)
    n = len(offsets) - 1
    names = np.array([*trees.langs, "und"], dtype=object)
    best, score, rate = np.full(n, len(trees.langs)), np.zeros(n), np.zeros(n)
    for a, b in X.slices(offsets, SLICE) if trees.langs else ():
        raw, off = data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        bits, some = trees.lengths(raw, off), _has_letter(raw, off)
        k = bits.argmin(1)
        least = bits[np.arange(b - a), k]
        share = 1 / np.exp2(-np.minimum(1000, bits - least[:, None])).sum(1)
        best[a:b] = np.where(some, k, len(trees.langs))
        score[a:b], rate[a:b] = np.where(some, share, 0), least / np.maximum(1, np.diff(off))
    return names[best], score, rate


def _parts(batches, text: int) -> Iterator[pa.RecordBatch]:
    """The batches in parts of about a megabyte of text, so that what is made of a part, and waits to be sent, is small."""
    for batch in batches:
        for a, b in X.slices(X.buffer_of(batch.column(text))[1]):
            yield batch.slice(a, b - a)


def identify(docs: DataFrame, trees: ContextTrees, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, lang_pred, score (the language's share of likelihood), bits_per_byte of its code, for every row."""
    held = docs.sparkSession.sparkContext.broadcast(trees)

    def label(batches):
        enter()
        for batch in _parts(batches, 1):
            names, score, rate = predict(held.value, batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(score), pa.array(rate)], names=["doc_id", "lang_pred", "score", "bits_per_byte"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("body")).mapInArrow(label, SCHEMA)


def recognised(docs: DataFrame, trees: ContextTrees, text_col: str = "text") -> DataFrame:
    """The rows whose language can be told, all columns as they were: no row moves to another task."""
    held = docs.sparkSession.sparkContext.broadcast(trees)
    at = docs.columns.index(text_col)

    def keep(batches):
        enter()
        for batch in _parts(batches, at):
            yield batch.filter(pa.array(predict(held.value, batch.column(at))[0] != "und", pa.bool_()))

    return docs.mapInArrow(keep, docs.schema)


def learn(docs: DataFrame, usable: Column, order: int = 3, sample_docs: int = 250, sample_bytes: int = 1 << 20) -> ContextTrees:
    """Trees from the sampled documents among those that `usable` (over doc_id) lets in."""
    train: dict[str, list[bytes]] = {}
    for r in sorted(sample(docs, usable, sample_docs=sample_docs).collect(), key=lambda r: (r["h"], r["doc_id"])):
        train.setdefault(r["lang"], []).append(r["body"].encode("utf-8", "surrogatepass"))
    return ContextTrees({k: v for k, v in train.items() if any(v)}, order, sample_bytes)
