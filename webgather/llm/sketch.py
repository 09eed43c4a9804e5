"""A count-min sketch over 64-bit keys, made by partition and merged by slice.

A task's part is sparse: the sorted cells of its keys, each at most twice, coded by slice as
low 16 bits and a count for each value of the bits above. Slices merge in two steps, and of
the sum only whether it reaches one and two is kept, a bit a cell each. An estimate is the least
over the rows, so a key that occurs twice always passes. `depth` rows of 2**bits cells take
depth * 2**bits / 8 bytes at any size of input: that is what is broadcast.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from webgather.llm._shared import shuffles_removed
from webgather.llm._text import U64

SLICE_BITS = 24
#: Odd multipliers, one to a row.
ROWS = tuple(U64(x) for x in (0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3))


def cells(keys: np.ndarray, row: int, bits: int) -> np.ndarray:
    return ((keys * ROWS[row]) >> U64(64 - bits)).astype(np.uint32)


def parts(keys: np.ndarray, depth: int, bits: int) -> Iterator[tuple[int, bytes]]:
    """(slice, its sparse part): slices are numbered over all rows."""
    low = min(SLICE_BITS, bits)
    for row in range(depth):
        c = np.sort(cells(keys, row, bits))
        if len(c) > 2:
            third = np.zeros(len(c), bool)
            third[2:] = c[2:] == c[:-2]
            c = c[~third]
        own = c >> np.uint32(low)
        for k in np.unique(own).tolist():
            x = c[np.searchsorted(own, k) : np.searchsorted(own, k, side="right")] & np.uint32((1 << low) - 1)
            above = np.bincount(x >> 16, minlength=1 << max(0, low - 16)).astype("<u4")
            yield row * (1 << (bits - low)) + k, above.tobytes() + (x & 0xFFFF).astype("<u2").tobytes()


def _cells_of(part: bytes, low: int) -> np.ndarray:
    n = 1 << max(0, low - 16)
    above = np.frombuffer(part, "<u4", count=n)
    return (np.repeat(np.arange(n, dtype=np.uint32), above) << np.uint32(16)) | np.frombuffer(part, "<u2", offset=4 * n)


class Marked:
    """A set of keys that may hold more than it was given, and never less: which cells are marked, a bit each."""

    def __init__(self, rows: list[np.ndarray], bits: int):
        self.rows, self.bits = rows, bits

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        out = np.ones(len(keys), bool)
        for row, packed in enumerate(self.rows):
            c = cells(keys, row, self.bits)
            out &= (packed[c >> np.uint32(3)] >> (c & np.uint32(7)).astype(np.uint8)) & 1 == 1
        return out


def _bitmaps(cells_: np.ndarray, low: int) -> tuple[np.ndarray, np.ndarray]:
    """Cells met, and cells met twice (side by side in cells_)."""
    twice = np.zeros(len(cells_), bool)
    twice[1:] = cells_[1:] == cells_[:-1]
    once, both = np.zeros(1 << low, bool), np.zeros(1 << low, bool)
    once[cells_], both[cells_[twice]] = True, True
    return np.packbits(once, bitorder="little"), np.packbits(both, bitorder="little")


class _Sums:
    """Bitmaps by slice, added up."""

    def __init__(self):
        self.of: dict[int, list[np.ndarray]] = {}

    def add(self, k: int, once: np.ndarray, both: np.ndarray) -> None:
        if k not in self.of:
            self.of[k] = [once.copy(), both.copy()]
        else:
            total = self.of[k]
            total[1] |= both | (total[0] & once)
            total[0] |= once

    def batches(self, names: tuple[str, ...]) -> Iterator[pa.RecordBatch]:
        for k, (once, both) in self.of.items():
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([once.tobytes()], pa.binary()), pa.array([both.tobytes()], pa.binary())], names=list(names))


def marked_keys(rows: DataFrame, keys_of: Callable, depth: int, bits: int, times: int = 2, flush: int = 2_000_000, fan_in: int = 256) -> Marked:
    """The keys that keys_of(batch) yields, as arrays, at least `times` (1 or 2) times over all batches of rows.

    Parts of at most `fan_in` tasks meet in one, and what these give meets by slice, so no merging
    task takes what grows with the input beyond the number of tasks over `fan_in`.
    """
    low = min(SLICE_BITS, bits)
    n_slices = depth << (bits - low)
    names = ("slice", "once", "both")

    def sketch(batches):
        group = TaskContext.get().partitionId() // fan_in

        def out(held):
            found = parts(np.concatenate(held), depth, bits)
            for k, blob in found:
                yield pa.RecordBatch.from_arrays([pa.array([group], pa.int32()), pa.array([k], pa.int32()), pa.array([blob], pa.binary())], names=["group", "slice", "part"])

        held, n = [], 0
        for batch in batches:
            for keys in keys_of(batch):
                if len(keys):
                    held.append(keys)
                    n += len(keys)
            if n > flush:
                yield from out(held)
                held, n = [], 0
        if held:
            yield from out(held)

    def merge_parts(batches):
        sums = _Sums()
        for batch in batches:
            for k, part in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
                sums.add(k, *_bitmaps(_cells_of(part.as_py(), low), low))
        yield from sums.batches(names)

    def merge(batches):
        sums = _Sums()
        for batch in batches:
            for k, once, both in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2), strict=True):
                sums.add(k, np.frombuffer(once.as_py(), np.uint8), np.frombuffer(both.as_py(), np.uint8))
        yield from sums.batches(names)

    tasks = max(n_slices, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    made = rows.mapInArrow(sketch, "group int, slice int, part binary").repartition(tasks, "slice", "group")
    merged = made.mapInArrow(merge_parts, "slice int, once binary, both binary").repartition(n_slices, "slice").mapInArrow(merge, "slice int, once binary, both binary")
    size = 1 << max(0, low - 3)
    flat = np.zeros((n_slices, size), np.uint8)
    with shuffles_removed(rows.sparkSession):  # else they stay while the texts are shuffled, until the driver collects its garbage
        for r in merged.select("slice", names[times]).collect():
            flat[r[0]] = np.frombuffer(r[1], np.uint8)
    return Marked(list(flat.reshape(depth, -1)), bits)
