"""Packing of tokenised documents into sequences, by best fit and then local search by swaps.

Tokenising is one pass over the texts. What the packing needs of the corpus is how many pieces
have each length, a histogram of at most `size` entries at any scale, so it is solved on the
driver over classes of equal bins: best fit decreasing, then swaps between underfull bins (one
for one, two for one, one for two, or a move) that raise the sum of squared fills until bins
empty or the least possible number is reached. The solution, as ranges of ranks per length, is
broadcast; its size depends on `size` alone. A piece's rank among those of its length is its
rank within its task plus what earlier tasks have, so no length is gathered in one task.

Defined cases: a null text is empty and yields the end id alone; only documents longer than a
sequence are cut; rows with one id are packed each; an empty table gives an empty result;
other columns are ignored.
"""

from __future__ import annotations

import os
import re
import string
import zlib
from bisect import bisect_left, insort
from collections import Counter
from functools import lru_cache
from unicodedata import is_normalized

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from webgather.llm._shared import enter, worker_cache, written

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, task int, rank long"
#: White space that Python splits at and the tokenizer may not, or rarer kinds, or special tokens: such texts are encoded whole.
UNUSUAL = re.compile("[\\x1c-\\x1f\\x85\\xa0\\u03a3\\u1680\\u180e\\u2000-\\u200f\\u2028-\\u202f\\u205f-\\u206f\\u3000\\ufeff]|<\\|")
#: Those of them that Latin-1 has, where a search for each is quicker.
UNUSUAL_LATIN = ("<|", "\x85", "\xa0", "\x1c", "\x1d", "\x1e", "\x1f")
MOST_CACHED = 300_000


def _is_latin(text: str) -> bool:
    """Whether all characters are of Latin-1, which is in composed form before and after folding."""
    try:
        text.encode("latin-1")
    except UnicodeEncodeError:
        return False
    return True


class Encoder:
    """Token ids as little-endian 32-bit numbers; what stands between white space is encoded once and kept.

    The tokenizer drops white space, folds case and encodes runs of letters and of marks by
    themselves, so a text is the sum of its parts, and a word with marks behind it the sum
    of two. Of known parts the two latest generations of `most` each are kept.
    """

    def __init__(self, path: str, most: int = MOST_CACHED):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.tokenizer, self.most = Tokenizer.from_file(path), most
        # for folded runs of Latin-1 between single spaces, where nothing is left to normalise or to split
        self.lean = Tokenizer.from_file(path)
        self.lean.normalizer = normalizers.Sequence([])
        self.lean.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        self.known: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        vocabulary = self.tokenizer.get_vocab()
        self.ends_word = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends_word[[v for k, v in vocabulary.items() if k.endswith("</w>")]] = True

    def whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _learn(self, new: list[str], runs: bool, latin: bool) -> None:
        """runs: each of the new parts is one run of letters or of marks."""
        if runs:
            tokenizer = self.lean if latin else self.tokenizer
            ids = np.array(tokenizer.encode_batch_fast([" ".join(new)], add_special_tokens=False)[0].ids, "<u4")
            cuts = np.flatnonzero(self.ends_word[ids]) + 1
        else:
            code = self.tokenizer.encode(" ".join(new), add_special_tokens=False)
            ids = np.array(code.ids, "<u4")
            cuts = np.searchsorted([s for s, _ in code.offsets], np.cumsum([len(w) + 1 for w in new]))
        raw, a = ids.tobytes(), 0
        for w, b in zip(new, (4 * cuts).tolist(), strict=True):
            self.known[w] = raw[a:b]
            a = b

    def __call__(self, text: str) -> bytes:
        lower, latin = text.lower(), _is_latin(text)
        if latin:
            unusual = any(mark in text for mark in UNUSUAL_LATIN)
        else:  # folding can leave a text that isn't composed
            unusual = UNUSUAL.search(text) or not is_normalized("NFC", text) or not is_normalized("NFC", lower)
        if unusual:
            return self.whole(text)
        words = lower.split()
        known, older = self.known, self.older
        out = list(map(known.get, words))
        missing = {w for w, ids in zip(words, out, strict=True) if ids is None}
        if not missing:
            return b"".join(out)
        runs: list[str] = []
        others: list[str] = []
        sums: list[tuple[str, str, str]] = []
        asked = set()
        for w in missing:
            if (had := older.get(w)) is not None:
                known[w] = had
            elif w.isalpha():
                runs.append(w)
            elif (stem := w.rstrip(string.punctuation)) != w and stem.isalpha():
                sums.append((w, stem, marks := w[len(stem) :]))
                asked.update((stem, marks))
            else:
                others.append(w)
        if asked:
            runs += [w for w in asked.difference(known).difference(runs) if w not in older]
        if runs:
            self._learn(runs, True, latin)
        if others:
            self._learn(others, False, latin)
        for w, *parts in sums:
            known[w] = b"".join([known.get(part) or older[part] for part in parts])
        out = b"".join([known[w] if ids is None else ids for w, ids in zip(words, out, strict=True)])
        if len(known) > self.most:
            self.older, self.known = known, {}
        return out


@worker_cache(maxsize=2)
def _encoder(path: str) -> Encoder:
    """One to a worker: what a task has learned serves the next."""
    return Encoder(path)


def pieces(docs: DataFrame, tokenizer: str, size: int = 2048, id_col: str = "doc_id", text_col: str = "text", end_id: int = 0) -> DataFrame:
    """A row for each piece, in order of its document; rank counts the earlier pieces of that length in the task."""

    def cut(batches):
        enter(_encoder)
        encode, seen, task = _encoder(tokenizer), Counter(), TaskContext.get().partitionId()
        end = np.array([end_id], "<u4").tobytes()
        for batch in batches:
            out: list[list] = [[] for _ in range(6)]
            for doc, text in zip(batch.column(0), batch.column(1), strict=True):
                ids, doc = encode(text.as_py() or "") + end, doc.as_py()
                for k, a in enumerate(range(0, len(ids), 4 * size)):
                    part = ids[a : a + 4 * size]
                    n = len(part) // 4
                    for column, value in zip(out, (doc, k, a // 4, n, zlib.crc32(part), seen[n]), strict=True):
                        column.append(value)
                    seen[n] += 1
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            columns = [pa.array(c, k) for c, k in zip(out, kinds, strict=False)]
            yield pa.RecordBatch.from_arrays([*columns, pa.array([task] * len(out[0]), pa.int32()), pa.array(out[5], pa.int64())], names=["doc_id", "piece", "start", "length", "ids_crc32", "task", "rank"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("body")).mapInArrow(cut, PIECES)


def best_fit(histogram: dict[int, int], size: int) -> Counter:
    """Bins as {lengths in a bin, longest first: number of such bins}, by best fit decreasing over whole classes."""
    full: Counter = Counter()
    by_room: dict[int, Counter] = {}
    rooms: list[int] = []

    def put(bin_: tuple, n: int) -> None:
        room = size - sum(bin_)
        if room == 0:
            full[bin_] += n
            return
        if room not in by_room:
            by_room[room] = Counter()
            insort(rooms, room)
        by_room[room][bin_] += n

    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left > 0:
            k = bisect_left(rooms, length)
            if k == len(rooms):
                many = size // length
                if left >= many:
                    put((length,) * many, left // many)
                if left % many:
                    put((length,) * (left % many), 1)
                break
            room = rooms[k]
            bin_, n = next(iter(by_room[room].items()))
            take = min(n, left)
            by_room[room][bin_] -= take
            if not by_room[room][bin_]:
                del by_room[room][bin_]
            if not by_room[room]:
                del by_room[room]
                rooms.pop(k)
            put((*bin_, length), take)
            left -= take
    for found in by_room.values():
        full.update(found)
    return full


@lru_cache(maxsize=100_000)
def _amounts(bin_: tuple) -> tuple[dict[int, tuple], dict[int, tuple]]:
    """What one piece of a bin, and what two, can amount to, each with pieces that do."""
    ones = {x: (x,) for x in bin_}
    times = Counter(bin_)
    kinds = sorted(times)
    twos = {x + y: (y, x) for i, x in enumerate(kinds) for y in kinds[: i + 1] if x != y or times[x] > 1}
    return ones, twos


class _Takers:
    """What underfull bins can give back, as columns: (room, amount, bin, pieces given back)."""

    def __init__(self, bins: list[tuple], size: int):
        rows = []
        for k, b in enumerate(bins):
            ones, twos = _amounts(b)
            rows += [(size - sum(b), 0, k, 0, ())] + [(size - sum(b), y, k, 1, p) for y, p in ones.items()] + [(size - sum(b), y, k, 2, p) for y, p in twos.items()]
        self.bins, self.given = bins, [r[4] for r in rows]
        self.room, self.amount, self.owner, self.count = np.array([r[:4] for r in rows], np.int64).reshape(-1, 4).T

    def best(self, giver: int, fills: np.ndarray, there: np.ndarray, alone: bool) -> tuple[int, tuple, tuple, int] | None:
        """(gain, what the taker gets, what it gives back, taker) of the largest gain that fits; one for two, two for one, one for one or a move."""
        allowed = (fills >= fills[giver])[self.owner] & there[self.owner]
        if alone:  # a bin can't swap with itself
            allowed &= self.owner != giver
        best = None
        for pieces, most in zip(_amounts(self.bins[giver]), (2, 1), strict=True):
            for amount, got in pieces.items():
                gain = amount - self.amount
                # two pieces go for one in return
                fits = allowed & (gain > 0) & (gain <= self.room) & (self.count <= most) & ((most == 2) | (self.count == 1))
                if fits.any():
                    k = int(np.argmax(np.where(fits, gain * (1 << 20) + fills[self.owner], -1)))
                    if best is None or (gain[k], fills[self.owner[k]]) > (best[0], fills[best[3]]):
                        best = (int(gain[k]), got, self.given[k], int(self.owner[k]))
        return best


def _changed(bin_: tuple, out: tuple, into: tuple) -> tuple:
    rest = list(bin_)
    for x in out:
        rest.remove(x)
    return tuple(sorted([*rest, *into], reverse=True))


def swap_search(bins: Counter, size: int, steps: int | None = None) -> Counter:
    """Swaps that raise the sum of squared fills, emptying the least filled bins first.

    It ends at the least number of bins that could do, or when no swap of two underfull classes
    helps; `steps`, if set, ends it after so many swaps of classes. Each swap raises a sum that
    is bounded, so it ends.
    """
    bins = Counter(bins)
    least = -(-sum(sum(b) * n for b, n in bins.items()) // size)
    total, done, now = sum(bins.values()), 0, -1
    while total > least and now != done:
        now = done
        under = sorted((b for b in bins if sum(b) < size), key=lambda b: (sum(b), b))
        fills, there, takers = np.array([sum(b) for b in under], np.int64), np.ones(len(under), bool), _Takers(under, size)
        for k, giver in enumerate(under):
            if total <= least or steps is not None and done >= steps:
                break
            found = takers.best(k, fills, there, bins[giver] < 2) if there[k] else None
            if found:
                _, got, given, at = found
                taker = under[at]
                n = bins[giver] // 2 if at == k else min(bins[giver], bins[taker])
                for old, place in ((giver, k), (taker, at)):
                    bins[old] -= n
                    there[place] = bins[old] > 0
                    if not bins[old]:
                        del bins[old]
                for new in (_changed(giver, got, given), _changed(taker, given, got)):
                    if new:
                        bins[new] += n
                    else:
                        total -= n
                done += 1
    return bins


def _places(bins: Counter) -> dict[int, np.ndarray]:
    """For each length, rows (first rank, first sequence, offset), by first rank."""
    rows: dict[int, list] = {}
    used: Counter = Counter()
    sequence = 0
    for bin_, n in sorted(bins.items(), reverse=True):
        offset = 0
        for length in bin_:
            rows.setdefault(length, []).append((used[length], sequence, offset))
            used[length] += n
            offset += length
        sequence += n
    return {k: np.array(v, np.int64) for k, v in rows.items()}


def pack(docs: DataFrame, tokenizer: str, size: int = 2048, id_col: str = "doc_id", text_col: str = "text", end_id: int = 0) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset for each piece."""
    cut = written(pieces(docs, tokenizer, size, id_col, text_col, end_id))
    counts = cut.groupBy("length", "task").agg(F.count(F.lit(1)).alias("n"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    held = docs.sparkSession.sparkContext.broadcast(_places(swap_search(best_fit(histogram, size), size)))
    before = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("length", "task", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))

    def place(batches):
        for batch in batches:
            length, rank = (np.asarray(batch.column(k)) for k in (3, 5))
            sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            order = np.argsort(length, kind="stable")
            kinds, at = np.unique(length[order], return_index=True)
            for kind, own in zip(kinds.tolist(), np.split(order, at[1:]), strict=False):
                rows = held.value[kind]
                k = np.searchsorted(rows[:, 0], rank[own], side="right") - 1
                sequence[own], offset[own] = rows[k, 1] + rank[own] - rows[k, 0], rows[k, 2]
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(sequence), pa.array(offset)], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    ranked = cut.join(base, ["length", "task"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("rank") + F.col("base")).alias("rank"))
    return ranked.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
