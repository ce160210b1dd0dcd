"""Benchmark decontamination by CGK embedding, bit-sampling LSH, and exact edit verification.

Texts and items are sequences of words (runs of letters and digits, lower-cased). A document holds an item if some stretch of
its words is within floor(0.2 n) word edits of the item's n words. Windows of an item's size are candidates.
1. A sound filter: d edits leave at least n - 1 - 2d of an item's word pairs whole, so a stretch of n + d words must hold as
   many pairs that occur in some item. One running sum over a text's pairs tests all its windows for one item size.
2. Windows that remain are embedded by random walks: a walk repeats or advances a word by a random bit of word and step,
   so few edits become few differing places. Each walk's embedding is sampled at random places into hash keys; windows
   that share a key with an item of their size are its candidates. Walks and keys are the same for every size, so recall falls
   with length: with the most edits allowed it is at least RECALL up to WALKED words. Longer items are cut into one segment
   more than they may have edits; some segment is whole in any stretch that holds the item, so looking up segments misses none.
3. A candidate is verified exactly: the smallest edit distance of the item to any stretch around the window.

Items are broadcast in blocks of bounded size, one pass over the documents for each block. Long texts are handled whole.

Items under MIN_WORDS words may have no edits, so they need none of this: the words at every place are looked up whole. find()
reports them; clean() leaves them out, as a phrase of one to four words occurs by itself and is no leak.

Nulls: a null text holds nothing; null items and items without a word match nothing. Repeated items and repeated rows are reported each. Extra columns are ignored; empty tables give no rows.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import give_back

WORD = re.compile(r"[^\W_]+")
MIN_WORDS = 5
EDITS = 0.2  # of an item's words
WALKS, KEYS, SAMPLED = 8, 8, 4
RECALL = 0.99  # of items with the most edits allowed
WALKED = 40  # words of the longest items whose walks reach it, as measured; longer ones go by segments
OTHER = 1 << 40  # stands in windows for words that no item has
BLOCK_WORDS = 2_000_000  # words of a block of items: about 100 MB at most where it is used
SCHEMA = "doc_id long, item_id long, first_word long, n_words long, edits long, similarity double"


def words_of(text: str | None) -> list[str]:
    return WORD.findall((text or "").lower())


def allowed(n: int) -> int:
    return int(EDITS * n)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def embed(windows: np.ndarray) -> np.ndarray:
    """windows [B, n] of word ids -> [WALKS, B, 3n]: each walk's word at each step; 0 once the window is used up."""
    B, n = windows.shape
    padded = np.concatenate([windows, np.zeros((B, 1), windows.dtype)], axis=1).ravel()
    base = np.tile(np.arange(B) * (n + 1), WALKS)
    walk = np.repeat(np.arange(WALKS, dtype=np.uint64), B) * np.uint64(0xD1342543DE82EF95)
    at = np.zeros(WALKS * B, np.int64)
    out = np.empty((3 * n, WALKS * B), windows.dtype)
    for step in range(3 * n):
        here = padded[base + at]
        out[step] = here
        bit = _mix(here.astype(np.uint64) + walk + np.uint64(step * 0x9E3779B97F4A7C15 & (1 << 64) - 1)) & np.uint64(1)
        at = np.minimum(at + bit.astype(np.int64), n)
    return out.T.reshape(WALKS, B, 3 * n)


def keys(windows: np.ndarray) -> np.ndarray:
    """[B, n] -> [B, WALKS * KEYS] hashes of each embedding's words at a few random places."""
    embedded = embed(windows)
    out = np.empty((len(windows), WALKS * KEYS), np.uint64)
    for walk in range(WALKS):
        rng = np.random.default_rng([walk, windows.shape[1]])
        for k in range(KEYS):
            h = np.full(len(windows), np.uint64(walk * KEYS + k + 1))
            for place in rng.integers(0, 3 * windows.shape[1] // 2, SAMPLED):  # later places are mostly past a window's end
                h = _mix(h * np.uint64(0x9E3779B97F4A7C15) + embedded[walk, :, place].astype(np.uint64))
            out[:, walk * KEYS + k] = h
    return out


def segments(n: int) -> np.ndarray:
    """Starts of an item's segments, and its end: one segment more than edits allowed."""
    k = allowed(n) + 1
    return np.arange(k + 1) * n // k


def runs(x: np.ndarray, at: np.ndarray, length: int) -> np.ndarray:
    """Hashes of the `length` words from each place."""
    h = np.full(len(at), np.uint64(length))
    for k in range(length):
        h = _mix(h * np.uint64(0x9E3779B97F4A7C15) + x[at + k].astype(np.uint64))
    return h


def best_stretch(item: np.ndarray, text: np.ndarray) -> tuple[int, int, int]:
    """Fewest word edits from the item to any stretch of the text, and the stretch (the earliest, shortest of equals)."""
    n, m = len(item), len(text)
    cost, begin = np.zeros(m + 1, np.int64), np.arange(m + 1)
    ramp = np.arange(m + 1)
    for i in range(1, n + 1):
        step = np.empty(m + 1, np.int64)
        src = np.empty(m + 1, np.int64)
        step[0], src[0] = i, 0
        swap = cost[:-1] + (text != item[i - 1])
        drop = cost[1:] + 1
        step[1:] = np.minimum(swap, drop)
        src[1:] = np.where(swap <= drop, begin[:-1], begin[1:])
        low = np.minimum.accumulate(step - ramp)  # insertions run along the row
        where = np.maximum.accumulate(np.where(step - ramp == low, ramp, 0))
        cost, begin = low + ramp, src[where]
    end = int(cost.argmin())
    return int(cost[end]), int(begin[end]), end


class Items:
    """A block of items, with what the filter and the tables need."""

    def __init__(self, rows: list[tuple[int, list[str]]], shortest: int = 1):
        self.vocab: dict[str, int] = {}
        self.ids, self.items = [], []
        for item_id, ws in rows:
            if len(ws) >= shortest:
                self.ids.append(item_id)
                self.items.append(np.array([self.vocab.setdefault(w, len(self.vocab) + 1) for w in ws], np.int64))
        self.sizes: dict[int, list[int]] = defaultdict(list)
        whole: dict[int, list[int]] = defaultdict(list)  # by size: items that only match whole
        for i, x in enumerate(self.items):
            (self.sizes if len(x) >= MIN_WORDS else whole)[len(x)].append(i)
        self.whole: dict[int, tuple[np.ndarray, np.ndarray]] = {}  # sorted hashes and their items
        for n, some in whole.items():
            got = runs(np.concatenate([self.items[i] for i in some]), np.arange(len(some)) * n, n)
            order = np.argsort(got, kind="stable")
            self.whole[n] = got[order], np.array(some)[order]
        self.slot = {n: k % 63 for k, n in enumerate(sorted(self.sizes))}  # sizes that share a slot only weaken the filter
        bits = max(20, int(np.ceil(np.log2(64 * max(1, sum(map(len, self.items)))))))
        self.shift = np.uint64(64 - bits)
        self.pairs = np.zeros(1 << bits, np.uint64)  # which sizes of items have a pair with this hash
        for n, some in self.sizes.items():
            for i in some:
                self.pairs[self._pair(self.items[i])] |= np.uint64(1 << self.slot[n])
        self.tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}  # sorted keys and their items
        self.parts: dict[int, dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]] = {}  # by size and length: sorted segments, their items and offsets
        for n, some in self.sizes.items():
            if n > WALKED:
                self.parts[n] = self._segments(n, some)
                continue
            got = keys(np.stack([self.items[i] for i in some]))
            order = np.argsort(got.ravel(), kind="stable")
            self.tables[n] = got.ravel()[order], np.repeat(np.array(some), got.shape[1])[order]

    def _segments(self, n: int, some: list[int]) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
        cuts, x, out = segments(n), np.stack([self.items[i] for i in some]), {}
        for length in np.unique(np.diff(cuts)).tolist():
            begins = cuts[:-1][np.diff(cuts) == length]
            at = (np.arange(len(some))[:, None] * n + begins).ravel()
            got = runs(x.ravel(), at, length)
            order = np.argsort(got, kind="stable")
            out[length] = got[order], np.repeat(np.array(some), len(begins))[order], np.tile(begins, len(some))[order]
        return out

    def _pair(self, x: np.ndarray) -> np.ndarray:
        return _mix((x[:-1].astype(np.uint64) << np.uint64(32)) + x[1:].astype(np.uint64)) >> self.shift

    def _starts(self, at: np.ndarray, n: int) -> np.ndarray:
        """Starts of stretches of n + d words that hold enough of the pairs at these places."""
        d = allowed(n)
        need, reach = n - 1 - 2 * d, n + d - 2  # the last pair of a stretch starts `reach` words after its first
        if len(at) < need:
            return at[:0]
        a, b = at[: len(at) - need + 1], at[need - 1 :]
        near = b - a <= reach
        lo, hi = np.maximum(b[near] - reach, 0), a[near]
        if not len(lo):
            return lo
        lo = np.maximum(lo, np.concatenate([[0], np.maximum.accumulate(hi)[:-1] + 1]))  # both are sorted: count each start once
        some = hi >= lo
        lo, size = lo[some], (hi - lo + 1)[some]
        return np.repeat(lo - np.cumsum(size) + size, size) + np.arange(size.sum())

    def candidates(self, x: np.ndarray) -> set[tuple[int, int]]:
        """(item, window start) pairs that share a key. x: word ids of one or more texts, 0 for other words and between texts."""
        if not self.sizes:
            return set()
        mask = self.pairs[self._pair(x)]
        mask[(x[:-1] == 0) | (x[1:] == 0)] = 0
        at = np.flatnonzero(mask)
        mask = mask[at]
        found: set[tuple[int, int]] = set()
        padded = np.concatenate([np.where(x, x, OTHER), np.full(max(self.sizes), OTHER)])
        for n in self.sizes:
            starts = self._starts(at[(mask >> np.uint64(self.slot[n])) & np.uint64(1) > 0], n)
            if n in self.parts:
                found |= self._by_segments(n, at[(mask >> np.uint64(self.slot[n])) & np.uint64(1) > 0], starts, padded)
                continue
            known, owner = self.tables[n]
            for lo in range(0, len(starts), 4096):
                part = starts[lo : lo + 4096]
                got = keys(padded[part[:, None] + np.arange(n)])
                left, right = np.searchsorted(known, got, "left"), np.searchsorted(known, got, "right")
                for r, c in zip(*np.nonzero(right > left), strict=True):
                    start = int(part[r])
                    found.update((i, start) for i in owner[left[r, c] : right[r, c]].tolist())
        return found

    def _by_segments(self, n: int, at: np.ndarray, starts: np.ndarray, padded: np.ndarray) -> set[tuple[int, int]]:
        """(item, start it would have without edits) of segments found near a start that the filter leaves."""
        d, found = allowed(n), set()
        if not len(starts):
            return found
        near = np.searchsorted(starts, at + d, "right") > np.searchsorted(starts, at - n - d, "left")
        at = at[near]
        for length, (known, owner, offset) in self.parts[n].items():
            got = runs(padded, at, length)
            left = np.searchsorted(known, got, "left")
            size = np.searchsorted(known, got, "right") - left
            which = np.repeat(left - np.cumsum(size) + size, size) + np.arange(size.sum())
            items, begin = owner[which], np.repeat(at, size) - offset[which]
            near = np.searchsorted(starts, begin + d, "right") > np.searchsorted(starts, begin - d, "left")
            found.update(zip(items[near].tolist(), begin[near].tolist(), strict=True))
        return found

    def _exact(self, x: np.ndarray, ends: np.ndarray) -> Iterator[tuple[int, int, int]]:
        """(text, item, start) of the first place in each text where an item that only matches whole does so."""
        for n, (known, owner) in self.whole.items():
            at = np.flatnonzero(x[: len(x) - n + 1])
            for k in range(1, n):
                at = at[x[at + k] > 0]
            got = runs(x, at, n)
            left = np.searchsorted(known, got, "left")
            size = np.searchsorted(known, got, "right") - left
            start = np.repeat(at, size)
            items, texts = owner[np.repeat(left - np.cumsum(size) + size, size) + np.arange(size.sum())], np.searchsorted(ends, start, "right")
            for k in np.unique(texts * len(self.items) + items, return_index=True)[1].tolist():
                if np.array_equal(x[start[k] : start[k] + n], self.items[items[k]]):
                    yield int(texts[k]), int(items[k]), int(start[k])

    def matches(self, texts: list[list[str]]) -> list[tuple[int, int, int, int, int, float]]:
        """(text, item_id, first word, words, edits, similarity) of each item that a text holds: its best stretch, the first of equals."""
        if not self.items or not texts:
            return []
        ends = np.cumsum([len(ws) + 1 for ws in texts])
        x = np.zeros(int(ends[-1]) + 1, np.int64)
        get = self.vocab.get
        for ws, end in zip(texts, ends.tolist(), strict=True):
            x[end - 1 - len(ws) : end - 1] = np.fromiter(map(get, ws, repeat(0)), np.int64, len(ws))
        found: dict[tuple[int, int], list[int]] = defaultdict(list)
        pairs = sorted(self.candidates(x))
        start = np.array([s for _, s in pairs], np.int64)
        reach = np.array([len(self.items[i]) + allowed(len(self.items[i])) for i, _ in pairs], np.int64)
        first, last = np.searchsorted(ends, start, side="right"), np.searchsorted(ends, np.minimum(start + reach, len(x) - 2), side="right")
        for (i, s), a, b in zip(pairs, first.tolist(), np.minimum(last, len(texts) - 1).tolist(), strict=True):
            for text in range(a, b + 1):
                found[text, i].append(s)
        out = [(text, self.ids[i], s - int(ends[text]) + 1 + len(texts[text]), len(self.items[i]), 0, 1.0) for text, i, s in self._exact(x, ends)]
        for (text, i), starts in sorted(found.items()):
            item, n, d, best, covered = self.items[i], len(self.items[i]), allowed(len(self.items[i])), None, -1
            begin, end = int(ends[text]) - 1 - len(texts[text]), int(ends[text]) - 1
            same = [s for s in sorted(starts) if s >= begin and np.array_equal(x[s : s + n], item)]  # of segments' starts, some lie before the text
            if same:
                best = (0, same[0], n)
            for start in [] if same else sorted(starts):
                if start <= covered:
                    continue  # the stretch already looked at holds this window's
                lo, hi = max(begin, start - d), min(end, start + 2 * n + 2 * d)
                covered = start + n - d
                # the sound filter again, for this item alone
                if hi - lo < 2 or np.isin(self._pair(x[lo:hi]), self._pair(item)).sum() < n - 1 - 2 * d:
                    continue
                cost, a, b = best_stretch(item, x[lo:hi])
                if cost <= d and (best is None or cost < best[0]):
                    best = (cost, lo + a, b - a)
            if best:
                out.append((text, self.ids[i], best[1] - begin, best[2], best[0], 1 - best[0] / n))
        return out

    def in_groups(self, texts: list[str | None], most: int = 4 << 20) -> Iterator[tuple]:
        """matches() over texts in groups of bounded size."""
        first, group, size = 0, [], 0
        for t in texts:
            group.append(words_of(t))
            size += len(t or "")
            if size >= most:
                yield from ((first + m[0], *m[1:]) for m in self.matches(group))
                first, group, size = first + len(group), [], 0
        yield from ((first + m[0], *m[1:]) for m in self.matches(group))


def blocks(benchmark: DataFrame, most: int = BLOCK_WORDS, shortest: int = 1) -> Iterator[Items]:
    """Items of `shortest` words or more in blocks of at most `most` words (a longer item is a block of its own), streamed to the driver one by one."""
    held, size = [], 0
    for r in benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).orderBy("item_id", "text").toLocalIterator():
        ws = words_of(r["text"])
        if held and size + len(ws) > most:
            yield Items(held, shortest)
            held, size = [], 0
        held.append((r["item_id"], ws))
        size += len(ws)
    if held:
        yield Items(held, shortest)


def find(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, first_word, n_words, edits, similarity: a row for each document and item it holds."""
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    found = None
    for items in blocks(benchmark):
        here = rows.mapInArrow(_finder(spark.sparkContext.broadcast(items)), SCHEMA)
        found = here if found is None else found.unionByName(here)
    return found if found is not None else spark.createDataFrame([], SCHEMA)


def _finder(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column("doc_id").to_pylist()
            out = [(ids[m[0]], *m[1:]) for m in shared.value.in_groups(b.column("text").to_pylist())]
            cols = list(zip(*out, strict=True)) if out else [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.float64() if i == 5 else pa.int64()) for i, c in enumerate(cols)], names=["doc_id", "item_id", "first_word", "n_words", "edits", "similarity"])

    return run


def clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents that hold no item of MIN_WORDS words or more, with all their columns."""
    out = docs
    for items in blocks(benchmark, shortest=MIN_WORDS):
        shared = docs.sparkSession.sparkContext.broadcast(items)
        at = docs.columns.index("text")

        def run(batches: Iterator[pa.RecordBatch], shared=shared, at=at) -> Iterator[pa.RecordBatch]:
            for b in batches:
                keep = np.ones(b.num_rows, bool)
                keep[[m[0] for m in shared.value.in_groups(b.column(at).to_pylist())]] = False
                yield b.filter(pa.array(keep))
            give_back()

        out = out.mapInArrow(run, docs.schema)
    return out
