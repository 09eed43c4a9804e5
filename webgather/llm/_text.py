"""Vectorised text primitives shared by the operators of this subpackage.

Everything works on the UTF-8 buffer of an Arrow string column, so a batch of
documents is one numpy byte array plus row offsets and no Python string is made.
Texts are handled in slices of about a megabyte to keep workers small.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U64 = np.uint64
K1, K2, K3 = U64(0x9E3779B97F4A7C15), U64(0xBF58476D1CE4E5B9), U64(0x94D049BB133111EB)

#: The bytes that separate words, space and tab to carriage return.
SPACES = b" \t\n\x0b\x0c\r"
IS_SPACE = np.zeros(256, dtype=bool)
IS_SPACE[list(SPACES)] = True
LOWER_ASCII = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))

#: Bytes of text handled at once.
SLICE = 1 << 20


def mix(z: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    z = (z ^ (z >> U64(30))) * K2
    z = (z ^ (z >> U64(27))) * K3
    return z ^ (z >> U64(31))


def buffer_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, row offsets) of a string column; a null row is an empty one."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    n = len(column)
    if n == 0:
        return np.empty(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64)[column.offset : column.offset + n + 1]
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.empty(0, np.uint8)
    return raw, off - off[0]


def slices(offsets: np.ndarray, most: int = SLICE) -> Iterator[tuple[int, int]]:
    """Row ranges [a, b) of at most `most` bytes each, or one longer row."""
    a, n = 0, len(offsets) - 1
    while a < n:
        b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + most, side="right")) - 1)
        yield a, min(b, n)
        a = min(b, n)


def load8(data: np.ndarray) -> np.ndarray:
    """The eight bytes from every offset as one little-endian number; past the end are zeros.

    A view with a stride of one byte: it takes no more memory than the text.
    """
    n = len(data)
    return np.ndarray(n + 8, "<u8", np.concatenate([data, np.zeros(24, np.uint8)]), 0, (1,))


def span_hash(words8: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int) -> np.ndarray:
    """A 64-bit hash of each byte span, from the output of load8."""
    length = ends - starts
    acc = mix(length.astype(U64) * K1 + U64(seed))
    live, at, left = np.arange(len(starts)), starts.astype(np.int64), length.astype(np.int64)
    keep = left > 0
    while True:
        if not keep.all():
            live, at, left = live[keep], at[keep], left[keep]
        if not len(live):
            return acc
        x = words8[at]
        short = left < 8
        if short.any():
            x = np.where(short, x & ((U64(1) << (U64(8) * np.minimum(left, 7).astype(U64))) - U64(1)), x)
        acc[live] = mix(acc[live] * K1 + x)
        at, left = at + 8, left - 8
        keep = left > 0


def word_spans(data: np.ndarray, offsets: np.ndarray, inside: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, row) of every word; inside: which bytes belong to words, else all but spaces."""
    word = np.concatenate([[False], ~IS_SPACE[data] if inside is None else inside, [False]])
    cut = np.zeros(len(data) + 1, bool)
    cut[offsets] = True
    before, after = word[:-1], word[1:]
    starts = np.flatnonzero(after & (~before | cut))
    ends = np.flatnonzero(before & (~after | cut))
    return starts, ends, np.searchsorted(offsets, starts, side="right") - 1


def grams(items: np.ndarray, k: int) -> np.ndarray:
    """A hash of every k consecutive items (64-bit numbers)."""
    n = max(0, len(items) - k + 1)
    acc = np.zeros(n, U64)
    for j in range(k):
        acc = acc * K1 + items[j : j + n]
        acc ^= acc >> U64(32)
    return mix(acc)


def row_bounds(rows: np.ndarray, n_rows: int) -> np.ndarray:
    """Offsets into sorted row numbers, one more than rows."""
    return np.searchsorted(rows, np.arange(n_rows + 1))
