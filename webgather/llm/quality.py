"""A quality classifier: regularised quadratic discriminant analysis of document statistics.

Each text gives a vector of statistics, logarithms of counts and arcsines of square roots of
shares. Each class has a mean and a covariance that is shrunk, first towards the pooled one
(`pool`) and then towards its own mean variance times the identity (`ridge`); both amounts
are chosen by folds on the sample. The score is the logistic of the difference of the two
classes' log densities and priors, from Mahalanobis distances with Cholesky factors kept.

Labels of at most `sample_rows` rows, those with the least hash of their id, are learned from.

Defined cases: a null text is empty and has the statistics of an empty one; with one class
alone, or too few rows, the score is the share of class 1 (0.5 without labels); rows with one
id are scored each; a doc_id labelled twice counts twice; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from webgather.llm import _text as X

NAMES = ("bytes", "words", "word_mean", "word_sd", "long_words", "short_words", "distinct_words", "top_word", "lines", "distinct_lines", "line_mean", "upper", "digits", "marks", "symbols", "beyond_ascii", "capital_words", "stops", "doubled")


def _class_of_bytes() -> np.ndarray:
    """0 lower, 1 upper, 2 digit, 3 sentence marks, 4 other symbols, 5 beyond ASCII, 6 white space and controls."""
    kind = np.full(256, 4)
    kind[:33], kind[127], kind[128:] = 6, 6, 5
    kind[97:123], kind[65:91], kind[48:58] = 0, 1, 2
    kind[list(b".,;:!?'\"()-")] = 3
    return kind


KIND = _class_of_bytes()


def _sums(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(values, dtype=np.float64)])
    return total[bounds[1:]] - total[bounds[:-1]]


def _distinct_and_top(hashes: np.ndarray, rows: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Per row: how many different hashes, and how often the commonest occurs."""
    order = np.lexsort((hashes, rows))
    h, r = hashes[order], rows[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (r[1:] != r[:-1])
    at = np.flatnonzero(new)
    times, owner = np.diff(np.append(at, len(h))), r[at]
    top = np.zeros(n)
    np.maximum.at(top, owner, times)
    return np.bincount(owner, minlength=n).astype(float), top


def statistics(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """A row of transformed statistics, in the order of NAMES, for each text."""
    n = len(offsets) - 1
    size = np.diff(offsets).astype(float)
    starts, ends, rows = X.word_spans(data, offsets)
    words8 = X.load8(data)
    bounds = X.row_bounds(rows, n)
    count = np.diff(bounds).astype(float)
    length = (ends - starts).astype(float)
    mean = _sums(length, bounds) / np.maximum(1, count)
    sd = np.sqrt(np.maximum(0, _sums(length**2, bounds) / np.maximum(1, count) - mean**2))
    h = X.span_hash(words8, starts, ends, 3)
    distinct, top = _distinct_and_top(h, rows, n)
    twice = np.zeros(len(h))
    twice[1:] = (h[1:] == h[:-1]) & (rows[1:] == rows[:-1])
    ls, le, lr = X.word_spans(data, offsets, data != 10)
    lines = np.bincount(lr, minlength=n).astype(float)
    line_kinds, _ = _distinct_and_top(X.span_hash(words8, ls, le, 5), lr, n)
    kind = KIND[data]
    share = [_sums(kind == k, offsets) / np.maximum(1, size) for k in range(6)]
    per_word = lambda v: _sums(v, bounds) / np.maximum(1, count)
    arc = lambda p: np.arcsin(np.sqrt(np.clip(p, 0, 1)))
    return np.column_stack([
        np.log1p(size), np.log1p(count), np.log1p(mean), np.log1p(sd), arc(per_word(length > 12)), arc(per_word(length < 4)), arc(distinct / np.maximum(1, count)), arc(top / np.maximum(1, count)),
        np.log1p(lines), arc(line_kinds / np.maximum(1, lines)), np.log1p(size / np.maximum(1, lines)), arc(share[1]), arc(share[2]), arc(share[3]), arc(share[4]), arc(share[5]),
        arc(per_word(KIND[data[starts]] == 1)), arc(per_word(KIND[data[ends - 1]] == 3)), arc(per_word(twice)),
    ])


@dataclass
class Discriminant:
    """Two Gaussian classes, by mean and inverse Cholesky factor, over standardised statistics."""

    center: np.ndarray
    scale: np.ndarray
    means: list
    inverses: list
    constants: list
    flat: float | None = None

    def score(self, stats: np.ndarray) -> np.ndarray:
        if self.flat is not None:
            return np.full(len(stats), self.flat)
        z = np.clip((stats - self.center) / self.scale, -8, 8)
        log = [c - 0.5 * (((z - m) @ inv.T) ** 2).sum(1) for m, inv, c in zip(self.means, self.inverses, self.constants, strict=True)]
        return 1 / (1 + np.exp(np.clip(log[0] - log[1], -700, 700)))


def _fit(z: np.ndarray, y: np.ndarray, pool: float, ridge: float) -> tuple[list, list, list]:
    own = [z[y == k] for k in (0, 1)]
    means = [x.mean(0) for x in own]
    covs = [np.cov(x.T, bias=True) for x in own]
    pooled = sum(len(x) * c for x, c in zip(own, covs, strict=True)) / len(z)
    inverses, constants = [], []
    for x, c in zip(own, covs, strict=True):
        c = (1 - pool) * c + pool * pooled
        c = (1 - ridge) * c + ridge * (np.trace(c) / len(c) + 1e-6) * np.eye(len(c))
        factor = np.linalg.cholesky(c)
        inverses.append(np.linalg.inv(factor))
        constants.append(np.log(len(x) / len(z)) - np.log(np.diag(factor)).sum())
    return means, inverses, constants


def fit(stats: np.ndarray, labels: np.ndarray, folds: int = 4) -> Discriminant:
    """The shrinkage of least log loss over folds, then the fit on all rows."""
    d = stats.shape[1]
    if min((labels == 0).sum(), (labels == 1).sum()) < folds:
        return Discriminant(np.zeros(d), np.ones(d), [], [], [], float(labels.mean()) if len(labels) else 0.5)
    center, scale = stats.mean(0), stats.std(0) + 1e-6
    z = np.clip((stats - center) / scale, -8, 8)
    part = np.zeros(len(z), int)
    for k in (0, 1):
        part[labels == k] = np.arange((labels == k).sum()) % folds
    best = None
    for pool in (0.0, 0.2, 0.5, 0.8):
        for ridge in (0.01, 0.05, 0.2, 0.5):
            loss = 0.0
            for f in range(folds):
                model = Discriminant(np.zeros(d), np.ones(d), *_fit(z[part != f], labels[part != f], pool, ridge))
                p = np.clip(model.score(z[part == f]), 1e-6, 1 - 1e-6)
                loss -= np.log(np.where(labels[part == f] == 1, p, 1 - p)).sum()
            if best is None or loss < best[0]:
                best = (loss, pool, ridge)
    return Discriminant(center, scale, *_fit(z, labels, best[1], best[2]))


def _map_stats(batches, model: Discriminant | None):
    """One batch of (key, body) to (key, statistics or score)."""
    for batch in batches:
        data, offsets = X.buffer_of(batch.column(1))
        rows = [np.zeros((0, len(NAMES)))]
        for a, b in X.slices(offsets, X.SLICE // 2):
            rows.append(statistics(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]))
        s = np.concatenate(rows)
        value = pa.FixedSizeListArray.from_arrays(pa.array(s.ravel()), len(NAMES)).cast(pa.list_(pa.float64())) if model is None else pa.array(model.score(s))
        yield pa.RecordBatch.from_arrays([batch.column(0), value], names=["key", "value"])


def learn(docs: DataFrame, labels: DataFrame, usable: Column, label_col: str = "quality", sample_rows: int = 20_000) -> Discriminant:
    """A fit to the sampled labels among those that `usable` (over doc_id) lets in."""
    chosen = (
        labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("label"))
        .filter(usable & F.col("doc_id").isNotNull() & F.col("label").isin(0, 1))
        .orderBy(F.xxhash64("doc_id"), "doc_id", "label")
        .limit(sample_rows)
    )
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("body")).join(F.broadcast(chosen), "doc_id")
    key = F.struct("doc_id", "label").alias("key")
    found = rows.select(key, "body").mapInArrow(lambda b: _map_stats(b, None), "key struct<doc_id:long,label:int>, value array<double>").collect()
    found.sort(key=lambda r: (r["key"]["doc_id"], r["key"]["label"], r["value"]))
    return fit(np.array([r["value"] for r in found]).reshape(-1, len(NAMES)), np.array([r["key"]["label"] for r in found], int))


def score(docs: DataFrame, model: Discriminant, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and score (0 to 1, higher: class 1 likelier) for every row of docs."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.col(id_col).cast("long").alias("key"), F.col(text_col).alias("body"))
    return rows.mapInArrow(lambda b: _map_stats(b, held.value), "key long, value double").select(F.col("key").alias("doc_id"), F.col("value").alias("score"))
