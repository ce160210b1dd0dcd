"""Selection over one sequence of bounded size, in arrays. The DataFrame operators give the same results at any size."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np

from ..model import floor_met, score
from ..params import Params


@dataclass
class Candidate:
    types: tuple[int, ...]
    gaps: tuple[int, ...]
    starts: np.ndarray
    events: np.ndarray = field(default=None, repr=False)

    @property
    def size(self) -> int:
        return len(self.types)

    @property
    def value(self) -> int:
        return score(len(self.types), len(self.starts))


@dataclass
class Pick:
    round: int
    rank: int
    score: int
    episode: Candidate


DENSE = 1 << 22  # counters that direct addressing may take
PART_ROWS = 1 << 20  # followers held at once


class Events:
    """Distinct events in order of time, then type."""

    def __init__(self, t: np.ndarray, e: np.ndarray):
        order = np.lexsort((e, t))
        t, e = np.asarray(t, np.int64)[order], np.asarray(e, np.int64)[order]
        keep = np.ones(len(t), bool)
        keep[1:] = (t[1:] != t[:-1]) | (e[1:] != e[:-1])
        self.t, self.e = t[keep], e[keep]
        self.m = int(self.e.max()) + 1 if len(self.e) else 1

    def __len__(self) -> int:
        return len(self.t)

    def find(self, t: np.ndarray, e: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.t * self.m + self.e, t * self.m + e)

    def drop(self, gone: np.ndarray) -> Events:
        out = Events.__new__(Events)
        out.t, out.e, out.m = self.t[~gone], self.e[~gone], self.m
        return out


def followers(ev: Events, end: np.ndarray, tg: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each end time all events up to tg later: row, event index, gap."""
    lo, hi = np.searchsorted(ev.t, end, side="right"), np.searchsorted(ev.t, end + tg, side="right")
    n = hi - lo
    row = np.repeat(np.arange(len(end)), n)
    at = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + lo[row]
    return row, at, ev.t[at] - end[row]


def followers_in_parts(ev: Events, end: np.ndarray, tg: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The same in parts of about PART_ROWS rows: a dense line has hundreds of followers for each event."""
    lo = np.searchsorted(ev.t, end, side="right")
    n = np.searchsorted(ev.t, end + tg, side="right") - lo
    upto, a = np.cumsum(n), 0
    while a < len(end):
        base = int(upto[a] - n[a])
        b = max(a + 1, int(np.searchsorted(upto, base + PART_ROWS, side="right")))
        row = np.repeat(np.arange(a, b), n[a:b])
        at = np.arange(base, base + len(row)) - np.repeat(upto[a:b] - n[a:b] - lo[a:b], n[a:b])
        yield row, at, ev.t[at] - end[row]
        a = b


def _grouped(path: np.ndarray, etype: np.ndarray, gap: np.ndarray, m: int, tg: int, n_paths: int) -> tuple[np.ndarray, ...]:
    """Counts of (path, type, gap), and which count each row belongs to; by direct addressing where the kinds are few."""
    key = (path * m + etype) * (tg + 1) + gap
    space = n_paths * m * (tg + 1)
    if space <= max(DENSE, 2 * len(key)):
        n = np.bincount(key, minlength=space)
        kinds = np.flatnonzero(n)
        place = np.zeros(space, np.int64)
        place[kinds] = np.arange(len(kinds))
        inverse, n = place[key], n[kinds]
    else:
        kinds, inverse, n = np.unique(key, return_inverse=True, return_counts=True)
    return kinds // ((tg + 1) * m), kinds // (tg + 1) % m, kinds % (tg + 1), n, inverse


class Counts:
    """Counts by key, by direct addressing where the keys are few."""

    def __init__(self, space: int):
        self.dense = np.zeros(space, np.int64) if space <= DENSE else None
        self.held, self.size = [(np.zeros(0, np.int64), np.zeros(0, np.int64))], 0

    def add(self, key: np.ndarray) -> None:
        if self.dense is not None:
            self.dense += np.bincount(key, minlength=len(self.dense))
            return
        self.held.append(np.unique(key, return_counts=True))
        self.size += len(self.held[-1][0])
        if self.size > max(DENSE, len(self.held[0][0])):
            self._merge()

    def _merge(self) -> None:
        key, n = (np.concatenate(x) for x in zip(*self.held, strict=True))
        key, where = np.unique(key, return_inverse=True)
        self.held, self.size = [(key, np.bincount(where, n, len(key)).astype(np.int64))], 0

    def all(self) -> tuple[np.ndarray, np.ndarray]:
        if self.dense is not None:
            some = np.flatnonzero(self.dense)
            return some, self.dense[some]
        self._merge()
        return self.held[0]


def _unused(who: np.ndarray, etype: np.ndarray, members: list[tuple[int, tuple[int, ...]]], m: int, n_paths: int) -> np.ndarray:
    """Which rows bring a type that their path doesn't have."""
    return _unused_by(members, m, n_paths)(who, etype)


def _unused_by(members: list[tuple[int, tuple[int, ...]]], m: int, n_paths: int):
    if n_paths * m <= 16 * DENSE:
        used = np.zeros((n_paths, m), bool)
        for k, types in members:
            used[k, list(types)] = True
        return lambda who, etype: ~used[who, etype]
    table = np.full((n_paths, max((len(t) for _, t in members), default=1)), -1, np.int64)
    for k, types in members:
        table[k, : len(types)] = types

    def unused(who: np.ndarray, etype: np.ndarray) -> np.ndarray:
        ok = np.ones(len(who), bool)
        for c in range(table.shape[1]):
            ok &= table[who, c] != etype
        return ok

    return unused


def _extensions(ev: Events, path: np.ndarray, end: np.ndarray, paths: dict[int, tuple], tg: int) -> tuple[np.ndarray, ...]:
    """Path, type, gap and count of all one-event extensions by a type that the path doesn't have, with bounded memory: from
    followers in parts, or on a dense line from products of 0-1 blocks of paths by ticks."""
    m = ev.m
    followed = int((np.searchsorted(ev.t, end + tg, side="right") - np.searchsorted(ev.t, end, side="right")).sum())
    if 2.0 * len(paths) * m * tg * (int(end.max()) - int(end.min()) + 1) / 2e10 < followed * 6e-8:
        return _extensions_by_product(ev, path, end, paths, tg)
    counts, unused = Counts(m * m * (tg + 1)), _unused_by([(k, x[0]) for k, x in paths.items()], m, m)
    for row, at, gap in followers_in_parts(ev, end, tg):
        who, etype = path[row], ev.e[at]
        ok = unused(who, etype)
        counts.add((who[ok] * m + etype[ok]) * (tg + 1) + gap[ok])
    key, n = counts.all()
    return key // ((tg + 1) * m), key // (tg + 1) % m, key % (tg + 1), n


def _extensions_by_product(ev: Events, path: np.ndarray, end: np.ndarray, paths: dict[int, tuple], tg: int, block: int = 1 << 15) -> tuple[np.ndarray, ...]:
    names = np.array(sorted(paths), np.int64)
    number = np.zeros(ev.m, np.int64)
    number[names] = np.arange(len(names))
    order = np.argsort(end, kind="stable")
    who, at = number[path[order]], end[order]
    total = np.zeros((len(names), ev.m, tg + 1), np.int64)
    for a in range(int(at[0]), int(at[-1]) + 1, block):
        i, j = np.searchsorted(at, (a, a + block))
        u, v = np.searchsorted(ev.t, (a, a + block + tg))
        if i == j or u == v:
            continue
        x, y = np.zeros((len(names), block), np.float32), np.zeros((ev.m, block + tg), np.float32)
        x[who[i:j], at[i:j] - a] = 1  # a path's occurrences end at different times
        y[ev.e[u:v], ev.t[u:v] - a] = 1
        for g in range(1, tg + 1):
            total[:, :, g] += (x @ y[:, g : g + block].T).astype(np.int64)  # sums of a block stay exact in single precision
    for k, x in paths.items():
        total[number[k], list(x[0])] = 0
    k, e, g = np.nonzero(total)
    return names[k], e, g, total[k, e, g]


def best_paths(ev: Events, p: Params) -> list[Candidate]:
    """One episode for each starting type, grown by its most frequent extension while the rule allows; all grow in lockstep."""
    types_at, counts = np.unique(ev.e, return_counts=True)
    paths = {int(e): ((int(e),), (), int(n)) for e, n in zip(types_at, counts, strict=True)}
    path, start, end = ev.e.copy(), ev.t.copy(), ev.t.copy()
    out, size, key = [], 1, ev.t * ev.m + ev.e
    while len(path):
        g_path, g_type, g_gap, n = _extensions(ev, path, end, paths, p.tg)
        order = np.lexsort((g_type, g_gap, -n, g_path))
        first = order[np.flatnonzero(np.diff(g_path[order], prepend=-1))]
        grown, more = {}, np.zeros((2, ev.m), np.int64)
        for i in first.tolist():
            k, f = int(g_path[i]), int(n[i])
            types, gaps, old = paths[k]
            if not floor_met(size, f, int(g_gap[i]), p.tg) or (p.max_size and size >= p.max_size):
                continue
            if p.stop_rule == "score_improves" and score(size + 1, f) <= score(size, old):
                continue
            grown[k] = (*types, int(g_type[i])), (*gaps, int(g_gap[i])), f
            more[:, k] = g_type[i], g_gap[i]
        for k, (types, gaps, f) in paths.items():
            if k not in grown and size > 1 and score(size, f) > 0:
                out.append(Candidate(types, gaps, start[path == k]))
        if not len(n):
            break
        etype, gap = more[0][path], more[1][path]
        want = (end + gap) * ev.m + etype
        on = (gap > 0) & (key[np.minimum(np.searchsorted(key, want), len(key) - 1)] == want)
        path, start, end = path[on], start[on], (end + gap)[on]
        paths, size = grown, size + 1
    return out


def frequent(ev: Events, p: Params, total: int) -> list[Candidate]:
    """All injective episodes of two or more types with frequency at or above fth times `total`, level by level."""
    if p.fth is None:
        raise ValueError("the two-phase selector needs fth")
    least = p.fth * total
    types_at, counts = np.unique(ev.e, return_counts=True)
    often = np.zeros(ev.m, bool)
    often[types_at[counts >= least]] = True
    ev = ev.drop(~often[ev.e])
    eps = [((int(e),), ()) for e in np.flatnonzero(often)]
    number = np.cumsum(often) - 1
    path, start, end, out, size = number[ev.e], ev.t.copy(), ev.t.copy(), [], 1
    while len(path) and not (p.max_size and size >= p.max_size):
        row, at, gap = followers(ev, end, p.tg)
        who, etype = path[row], ev.e[at]
        ok = _unused(who, etype, [(k, x[0]) for k, x in enumerate(eps)], ev.m, len(eps))
        row, at, gap, who, etype = row[ok], at[ok], gap[ok], who[ok], etype[ok]
        g_path, g_type, g_gap, n, inverse = _grouped(who, etype, gap, ev.m, p.tg, len(eps))
        good = n >= least
        eps = [((*eps[a][0], int(b)), (*eps[a][1], int(g))) for a, b, g in zip(g_path[good].tolist(), g_type[good].tolist(), g_gap[good].tolist(), strict=True)]
        renumber = np.cumsum(good) - 1
        on = good[inverse]
        path, start, end = renumber[inverse[on]], start[row[on]], ev.t[at[on]]
        order = np.argsort(path, kind="stable")
        for (types, gaps), s in zip(eps, np.split(start[order], np.cumsum(np.bincount(path, minlength=len(eps)))[:-1]), strict=True) if eps else ():
            out.append(Candidate(types, gaps, s))
        size += 1
    return out


def covered(ev: Events, c: Candidate) -> np.ndarray:
    off = np.concatenate([[0], np.cumsum(c.gaps)]).astype(np.int64)
    return ev.find((c.starts[:, None] + off).ravel(), np.tile(np.array(c.types, np.int64), len(c.starts)))


def overlaps(ev: Events, cands: list[Candidate]) -> dict[int, dict[int, int]]:
    """Events that two candidates share, both ways; pairs that share none are left out."""
    n, total = len(cands), sum(c.size * len(c.starts) for c in cands)
    if total > 4 * DENSE and 2.0 * n * n * len(ev) / 4e10 < total * 1e-7 and n * len(ev) <= 1 << 32:
        return _by_rows(ev, cands)
    for c in cands:
        c.events = covered(ev, c)
    return shared(np.concatenate([c.events for c in cands]), np.repeat(np.arange(len(cands)), [len(c.events) for c in cands]), len(cands), len(ev))


def shared(at: np.ndarray, who: np.ndarray, n: int, n_events: int) -> dict[int, dict[int, int]]:
    """The same from a row for each event (at) of each of n candidates (who)."""
    order = np.lexsort((who, at))
    at, who = at[order], who[order]
    first = np.flatnonzero(np.diff(at, prepend=-1))
    size = np.diff(np.append(first, len(at)))
    if n <= 4000 and 2.0 * n * n * n_events / 4e10 < float((size.astype(np.float64) ** 2).sum()) * 1e-8:
        return _by_product(at, who, n, n_events)  # events are in so many candidates that a matrix product is quicker
    dense = np.zeros(n * n, np.int64) if n * n <= 16 * DENSE else None
    total: dict[int, int] = {}
    for d in range(1, int(size.max(initial=1))):  # the d-th next candidate of the same event
        same = np.flatnonzero(at[d:] == at[:-d])
        key = who[same] * n + who[same + d]
        if dense is not None:
            if len(key) * 8 > n * n:
                dense += np.bincount(key, minlength=n * n)
            else:
                np.add.at(dense, key, 1)
        else:
            for k, x in zip(*map(np.ndarray.tolist, np.unique(key, return_counts=True)), strict=True):
                total[k] = total.get(k, 0) + x
    if dense is not None:
        some = np.flatnonzero(dense)
        total = dict(zip(some.tolist(), dense[some].tolist(), strict=True))
    out: dict[int, dict[int, int]] = {}
    for k, x in total.items():
        a, b = divmod(k, n)
        out.setdefault(a, {})[b] = x
        out.setdefault(b, {})[a] = x
    return out


def _by_rows(ev: Events, cands: list[Candidate], block: int = 1 << 15) -> dict[int, dict[int, int]]:
    """The same where candidates cover an event many times over: a bit for each candidate and event, one candidate's events at a time."""
    bits, out = np.zeros((len(cands), -(-len(ev) // 8)), np.uint8), np.zeros((len(cands), len(cands)), np.int64)
    for i, c in enumerate(cands):
        here = np.zeros(len(ev), bool)
        here[covered(ev, c)] = True
        bits[i] = np.packbits(here)
    for a in range(0, bits.shape[1], block // 8):
        x = np.unpackbits(bits[:, a : a + block // 8], axis=1).astype(np.float32)
        out += (x @ x.T).astype(np.int64)
    np.fill_diagonal(out, 0)
    return {a: {int(b): int(out[a, b]) for b in np.flatnonzero(out[a])} for a in range(len(cands)) if out[a].any()}


def _by_product(at: np.ndarray, who: np.ndarray, n: int, n_events: int, block: int = 1 << 15) -> dict[int, dict[int, int]]:
    """The same from products of 0-1 blocks of candidates by events; sums stay exact in single precision."""
    shared = np.zeros((n, n), np.int64)
    edges = np.searchsorted(at, np.arange(0, n_events + block, block))
    for k in range(len(edges) - 1):
        x = np.zeros((n, block), np.float32)
        x[who[edges[k] : edges[k + 1]], at[edges[k] : edges[k + 1]] - k * block] = 1
        shared += (x @ x.T).astype(np.int64)
    np.fill_diagonal(shared, 0)
    return {a: {int(b): int(shared[a, b]) for b in np.flatnonzero(shared[a])} for a in range(n) if shared[a].any()}


def tie_order(c) -> tuple:
    """Among equal scores: the larger, then the shorter in time, then smaller types, then smaller gaps."""
    return -len(c.types), sum(c.gaps), tuple(c.types), tuple(c.gaps)


def greedy(cands: list, om, left: int | None, values: list[int] | None = None, bound: int = 0) -> list[tuple[int, int]]:
    """(candidate, overlap score) in order of choice: always the largest positive score, less what it shares with those chosen.

    om: overlaps by candidate, or a function that tells a pick's: it gets the pick and another function for the candidates in
    order of their scores at that time, so that it may find those of the next picks too. bound: the first pick at or under it is
    the last one told.
    """
    order = sorted(range(len(cands)), key=lambda i: tie_order(cands[i]))
    now = np.array([(values[i] if values else cands[i].value) for i in order], np.int64)
    place = {i: r for r, i in enumerate(order)}
    out = []
    while len(now) and (left is None or len(out) < left):
        best = int(now.argmax())  # the first of equals
        if now[best] <= 0:
            break
        i = order[best]
        out.append((i, int(now[best])))
        if out[-1][1] <= bound or len(out) == left:
            break
        now[best] = np.iinfo(np.int64).min // 2
        ranking = lambda: [order[r] for r in np.argsort(-now, kind="stable") if now[r] > 0]
        for j, shared in (om(i, ranking) if callable(om) else om.get(i, {})).items():
            now[place[j]] -= shared
    return out


def select(t: np.ndarray, e: np.ndarray, p: Params, selector: str = "path_greedy", done: tuple[int, int] | None = None) -> tuple[list[Pick], Events, list[tuple]]:
    """Chosen episodes, the events left over, and a trace: round, candidates, picks, events left. done: rounds before, and the
    events that there were at first."""
    ev = Events(t, e)
    rnd, total = done or (0, len(ev))
    picks, trace = [], []
    while (p.k is None or len(picks) < p.k) and (p.max_rounds is None or rnd < p.max_rounds) and len(ev):
        rnd += 1
        found = best_paths(ev, p) if selector == "path_greedy" else frequent(ev, p, total if p.min_freq_base == "original" else len(ev))
        cands = [c for c in found if c.value > 0]
        if p.max_candidates is not None:
            cands = sorted(cands, key=lambda c: (-c.value, tie_order(c)))[: p.max_candidates]
        if not cands:
            trace.append((rnd, len(found), 0, 0, len(ev)))
            break
        om = overlaps(ev, cands) if p.overlap_mode == "penalise" else {}
        got = greedy(cands, om, None if p.k is None else p.k - len(picks))
        gone = np.zeros(len(ev), bool)
        for i, s in got:
            picks.append(Pick(rnd, len(picks) + 1, s, cands[i]))
            gone[cands[i].events if cands[i].events is not None else covered(ev, cands[i])] = True
        ev = ev.drop(gone)
        trace.append((rnd, len(found), len(cands), len(got), len(ev)))
        if not got or sum(s for _, s in got) <= p.min_gain:
            break
    return picks, ev, trace
