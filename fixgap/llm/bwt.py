"""Burrows-Wheeler transforms of string collections, merged by iterative interleave refinement.

The symbols are blocks of `step` bytes, and the transform is over suffixes at every byte: the symbol before a suffix at
byte i is the block that ends at i, so the suffixes of one string form `step` chains, each with an end of its own. A shard
sorts its own suffixes once. Merging never sorts suffixes of different shards: an interleave (which shard gives the next
suffix) starts as one shard after another and is refined; a round deals the shards' transform symbols, in the present
order, stably into their buckets, which orders all suffixes by one more symbol. A boundary appears between neighbours in the
first round that tells them apart and stays there, so that round gives the length of their common prefix (one less, in blocks).
The repeated intervals are the stretches whose common prefixes are long enough.
"""

from __future__ import annotations

import numpy as np

_MULT = 0x9E3779B97F4A7C15
_TABLE = np.random.default_rng(20240229).integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)


class Powers:
    """Powers of an odd multiplier modulo 2^64 and of its inverse, for hashes of any byte range from one running sum."""

    def __init__(self, n: int):
        self.up, self.down = np.full(n, _MULT, np.uint64), np.full(n, pow(_MULT, -1, 1 << 64), np.uint64)
        self.up[0] = self.down[0] = 1
        np.multiply.accumulate(self.up, out=self.up)
        np.multiply.accumulate(self.down, out=self.down)


_powers = Powers(1)


def powers(n: int) -> Powers:
    global _powers
    if len(_powers.up) < n:
        _powers = Powers(1 << (n - 1).bit_length())
    return _powers


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(29))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(32))


def running(x: np.ndarray) -> np.ndarray:
    """Running sums from which `ranges` gets hashes."""
    out = np.zeros(len(x) + 1, np.uint64)
    np.cumsum(_TABLE[x] * powers(len(x)).up[: len(x)], out=out[1:])
    return out


def ranges(sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hashes of the byte ranges [start, end): equal for equal bytes wherever they are."""
    return mix((sums[end] - sums[start]) * powers(len(sums)).down[start])


class Shard:
    """Suffixes of a few strings in order, and their transform.

    place: byte offset (in the strings put together, each followed by one position for its end) of each suffix by rank.
    before: the symbol before each suffix, 0 where the string starts (the mark that no refinement moves).
    """

    def __init__(self, strings: list[bytes], step: int):
        lens = np.array([len(s) for s in strings], np.int64)
        starts = np.cumsum(lens + 1) - (lens + 1)
        total = int((lens + 1).sum())
        x = np.frombuffer(b"\0".join(strings) + b"\0", np.uint8)
        owner = np.repeat(np.arange(len(strings)), lens + 1)
        at = np.arange(total)
        left = starts[owner] + lens[owner] - at  # bytes from here to the string's end
        full = left >= step
        sums = running(x)
        block = np.zeros(total, np.uint64)  # 0: too few bytes left, an end
        some = at[full]
        block[full] = np.maximum(ranges(sums, some, some + step), np.uint64(1))
        back = at - starts[owner] >= step
        before = np.zeros(total, np.uint64)
        before[back] = block[at[back] - step]

        # ranks by doubling: ends come first, each on its own, in order of place
        n_ends = int((~full).sum())
        rank = np.empty(total, np.int64)
        rank[~full] = np.arange(n_ends)
        rank[full] = n_ends + np.unique(block[full], return_inverse=True)[1]
        span = step
        while True:
            after = np.zeros(total, np.int64)
            more = left - span >= 0
            after[more] = rank[np.minimum(at[more] + span, total - 1)]
            key = rank * (total + 1) + np.where(full, after, 0)
            order = np.argsort(key)
            k = key[order]
            new = np.concatenate([[0], np.cumsum(k[1:] != k[:-1])])
            rank[order] = new
            if new[-1] == total - 1:
                break
            span *= 2
            if span > 2 * max(lens.max(initial=1), step):
                raise AssertionError("suffixes with ends of their own can't stay equal")
        self.place, self.n_ends, self.before = order, n_ends, before[order]


def merge(shards: list[Shard], depth: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Merged order by the first `depth` symbols: shard and place of each suffix, and the common prefix (in blocks, `depth` at most) with the one before it."""
    if len(shards) > 1 << 16:
        raise ValueError("too many shards for one merge")
    source = np.repeat(np.arange(len(shards)), [len(s.place) for s in shards]).astype(np.uint16)
    ends = np.repeat(np.arange(len(shards)), [s.n_ends for s in shards]).astype(np.uint16)
    # symbols as small integers, the same in all shards; 0 is the mark
    kinds, flat = np.unique(np.concatenate([s.before for s in shards] + [np.zeros(1, np.uint64)]), return_inverse=True)
    flat = flat[:-1].astype(np.int64)
    n, total = len(ends), len(source)
    common = np.full(total, -1, np.int32)  # -1: no boundary yet
    group = np.zeros(total, np.int64)
    for known in range(depth):
        # the transform symbols in the present order: each shard's own, one after another
        turn = np.argsort(source, kind="stable") if len(shards) > 1 else np.arange(total)
        symbol = np.empty(total, np.int64)
        symbol[turn] = flat
        moving = np.flatnonzero(symbol)
        to = moving[np.argsort(symbol[moving] * total + np.arange(len(moving)))]  # stable
        s, g = symbol[to], group[to]
        edge = np.ones(total, bool)
        edge[n + 1 :] = (s[1:] != s[:-1]) | (g[1:] != g[:-1])
        common[edge & (common < 0)] = known
        source = np.concatenate([ends, source[to]])
        group = np.cumsum(edge) - 1
    common[common < 0] = depth
    turn = np.argsort(source, kind="stable")
    place = np.empty(total, np.int64)
    place[turn] = np.concatenate([s.place for s in shards])
    return source, place, common


def repeated_intervals(common: np.ndarray, depth: int) -> np.ndarray:
    """Which suffixes of the merged order share a prefix of `depth` blocks with a neighbour."""
    joined = common >= depth
    if len(joined):
        joined[0] = False
    return joined | np.concatenate([joined[1:], [False]]) if len(joined) else joined


def repeated_windows(strings: list[bytes], length: int, step: int, shard_bytes: int = 1 << 20) -> list[np.ndarray]:
    """For each string, which starts of `length`-byte windows have the same window elsewhere among the strings. step divides length."""
    if length % step:
        raise ValueError("step must divide length")
    groups: list[list[int]] = [[]]
    size = 0
    for i, s in enumerate(strings):
        if size and size + len(s) > shard_bytes:
            groups.append([])
            size = 0
        groups[-1].append(i)
        size += len(s)
    shards = [Shard([strings[i] for i in g], step) for g in groups if g]
    out = [np.zeros(max(0, len(s) - length + 1), bool) for s in strings]
    if not shards:
        return out
    source, place, common = merge(shards, length // step)
    many = repeated_intervals(common, length // step)
    for k, g in enumerate(x for x in groups if x):
        here = place[many & (source == k)]
        lens = np.array([len(strings[i]) + 1 for i in g])
        starts = np.cumsum(lens) - lens
        owner = np.searchsorted(starts, here, side="right") - 1
        order = np.argsort(owner, kind="stable")
        here, owner = here[order], owner[order]
        cut = np.searchsorted(owner, np.arange(len(g) + 1))
        for j, i in enumerate(g):
            out[i][here[cut[j] : cut[j + 1]] - starts[j]] = True
    return out
