"""Covers of many order-only sequences at once, in arrays; `baselines.cover` tells of one sequence what these tell of all."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

CHUNK = 1 << 18  # events of the sequences held as one piece, but a longer sequence is one
FLAGS = 1 << 22  # keys that direct addressing may take


class Piece:
    """Whole sequences one after another: types, and by place the sequence and its end."""

    def __init__(self, e: np.ndarray, sizes: np.ndarray):
        self.e = e
        self.line = np.repeat(np.arange(len(sizes)), sizes)
        self.n_lines, self.ends = len(sizes), np.cumsum(sizes)
        order = np.argsort(e, kind="stable")
        kinds, first = np.unique(e[order], return_index=True)
        self.at = dict(zip(kinds.tolist(), np.split(order, first[1:]), strict=False))  # no events: no kinds, one part

    def free(self) -> np.ndarray:
        return np.ones(len(self.e), bool)

    def take(self, free: np.ndarray, pattern: tuple[int, ...], window: int, only: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """First and last places of a pattern's uses where places are free, as `baselines.cover` takes them; what they take is free
        no more. only: the sequences looked at. Types of a pattern differ.

        Uses of a sequence don't cross: each next one's events come after those of the one before, type by type. So the next free
        event of a type is the first after both, and all sequences take their r-th start at the same time.
        """
        none = np.zeros(0, np.int64)
        if any(c not in self.at for c in pattern):
            return none, none
        here = [p[free[p]] for p in (self.at[c] for c in pattern)]
        start = here[0]
        if only is not None:
            start = start[only[self.line[start]]]
        if len(pattern) == 1:
            free[start] = False
            return start, start
        stop = np.minimum(start + window, self.ends[self.line[start]])
        last = start
        for some in here[1:]:  # without other uses; those that fail so fail in any case
            got = np.searchsorted(some, last, side="right")
            ok = got < len(some)
            ok[ok] = some[got[ok]] < stop[ok]
            start, stop, last = start[ok], stop[ok], some[got[ok]]
        if not len(start):
            return none, none
        line = self.line[start]
        first = np.flatnonzero(np.diff(line, prepend=-1))
        nth = np.arange(len(line)) - np.repeat(first, np.diff(np.append(first, len(line))))
        order = np.argsort(nth, kind="stable")
        edges = np.cumsum(np.bincount(nth))
        passed = np.full((len(pattern), self.n_lines), -1, np.int64)  # place of each type's event in the last use
        lo, firsts, lasts = 0, [], []
        for hi in edges.tolist():
            now = order[lo:hi]
            lo = hi
            a, b, who = start[now], stop[now], line[now]
            places = [a]
            for k, some in enumerate(here[1:], 1):
                got = np.searchsorted(some, np.maximum(places[-1], passed[k, who]), side="right")
                j = some[np.minimum(got, len(some) - 1)]
                ok = (got < len(some)) & (j < b)
                if not ok.all():
                    b, who, j, places = b[ok], who[ok], j[ok], [x[ok] for x in places]
                places.append(j)
            for k, x in enumerate(places):
                passed[k, who] = x
                free[x] = False
            firsts.append(places[0])
            lasts.append(places[-1])
        first, last = np.concatenate(firsts), np.concatenate(lasts)
        order = np.argsort(first)
        return first[order], last[order]


def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[Piece]:
    for b in batches:
        col = b.column("line")
        off = col.offsets.to_numpy().astype(np.int64)
        e = col.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
        off = off - off[0]
        i = 0
        while i < len(off) - 1:
            j = max(i + 1, int(np.searchsorted(off, off[i] + CHUNK, side="right")) - 1)
            yield Piece(e[off[i] : off[j]], np.diff(off[i : j + 1]))
            i = j


def statistics(piece: Piece, patterns: list[tuple[int, ...]], window: int, with_pairs: bool) -> tuple[list[tuple], list[tuple]]:
    """Uses and skips by pattern (-1 - type: single events), and numbers of neighbouring uses: (number, uses, skips), (a, b, n)."""
    free, out = piece.free(), []
    number = np.full(len(piece.e), np.iinfo(np.int64).min)
    for k, pattern in enumerate(patterns):
        first, last = piece.take(free, pattern, window)
        if len(first):
            out.append((k, len(first), int((last - first + 1 - len(pattern)).sum())))
            number[first] = k
    number[free] = -1 - piece.e[free]
    kinds, n = np.unique(piece.e[free], return_counts=True)
    out += [(-1 - e, c, 0) for e, c in zip(kinds.tolist(), n.tolist(), strict=True)]
    if not with_pairs:
        return out, []
    at = np.flatnonzero(number != np.iinfo(np.int64).min)
    same = piece.line[at[1:]] == piece.line[at[:-1]]
    a, b = number[at[:-1]][same], number[at[1:]][same]
    if not len(a):
        return out, []
    low = int(number[at].min())
    width = int(number[at].max()) - low + 1
    key, n = np.unique((a - low) * width + b - low, return_counts=True)
    return out, [(x // width + low, x % width + low, c) for x, c in zip(key.tolist(), n.tolist(), strict=True)]


def changes(piece: Piece, chosen: list[tuple[int, ...]], cands: list[tuple[int, ...]], spots: list[int | None], window: int) -> tuple[list[tuple[int, int]], list[list[tuple[int, int, int]]]]:
    """Uses and skips of the chosen patterns, and for each candidate what it changes when it stands at its spot among them:
    (place in the new order, uses more, skips more). Sequences where it has no use, and patterns whose types' events are left as
    they were, don't change."""
    free, states, base, uses = piece.free(), [], [], []
    for pattern in chosen:
        states.append(free.copy())
        first, last = piece.take(free, pattern, window)
        skips = last - first + 1 - len(pattern)
        base.append((len(first), int(skips.sum())))
        uses.append((piece.line[first], skips))
    states.append(free)
    taken: dict[int, np.ndarray] = {}
    out = []
    for c, spot in zip(cands, spots, strict=True):
        more: list[tuple[int, int, int]] = []
        out.append(more)
        if spot is None or any(e not in piece.at for e in c):
            continue
        left = states[spot].copy()  # held for touched types only
        first, last = piece.take(left, c, window)
        if not len(first):
            continue
        more.append((spot, len(first), int((last - first + 1 - len(c)).sum())))
        hit = np.zeros(piece.n_lines, bool)
        hit[piece.line[first]] = True
        touched = set(c)
        for k in range(spot, len(chosen)):
            pattern = chosen[k]
            if touched.isdisjoint(pattern) or any(e not in piece.at for e in pattern):
                continue
            for e in set(pattern) - touched:
                left[piece.at[e]] = states[k][piece.at[e]]
            if k not in taken:
                taken[k] = np.flatnonzero(states[k] & ~states[k + 1])
            left[taken[k][~hit[piece.line[taken[k]]]]] = False
            first, last = piece.take(left, pattern, window, hit)
            before = hit[uses[k][0]]
            more.append((k + 1, len(first) - int(before.sum()), int((last - first + 1 - len(pattern)).sum()) - int(uses[k][1][before].sum())))
            touched.update(pattern)
    return base, out


def _distinct(key: np.ndarray, space: int) -> np.ndarray:
    if space > FLAGS:
        return np.unique(key)
    there = np.zeros(space, bool)
    there[key] = True
    return np.flatnonzero(there)


def sides(piece: Piece, pattern: tuple[int, ...], window: int) -> list[tuple[int, int, int]]:
    """Types that a sequence has more uses of the pattern before than after, or fewer: (type, such sequences, those with more before)."""
    first, last = piece.take(piece.free(), pattern, window)
    if not len(first):
        return []
    line = piece.line[first]
    begin, end = np.append(0, piece.ends)[line], piece.ends[line]
    m = int(piece.e.max()) + 1
    keys, signs = [], []
    for sign, lo, hi in ((1, last + 1, np.minimum(first + window, end)), (-1, np.maximum(begin, last + 1 - window), first)):
        some = []
        for d in range(window):
            ok = np.flatnonzero(lo + d < hi)
            some.append(ok * m + piece.e[lo[ok] + d])
        use = _distinct(np.concatenate(some), len(first) * m)  # a use has a type beside it or not
        keys.append(line[use // m] * m + use % m)
        signs.append(np.full(len(use), sign))
    key, sign = np.concatenate(keys), np.concatenate(signs)
    if piece.n_lines * m <= FLAGS:
        more = np.bincount(key, sign, piece.n_lines * m)
        key = np.flatnonzero(more)
        etype, more = key % m, more[key]
    else:
        key, where = np.unique(key, return_inverse=True)
        more = np.bincount(where, sign, len(key))
        etype, more = key[more != 0] % m, more[more != 0]
    n, wins = np.bincount(etype, minlength=m), np.bincount(etype, more > 0, m).astype(np.int64)
    return [(e, int(n[e]), int(wins[e])) for e in np.flatnonzero(n).tolist() if e not in pattern]
