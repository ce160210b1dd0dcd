"""Selection rounds over packed blocks of time, for lines of any length.

A row is a block: its times and types, and those of its neighbours within the reach of an episode on both sides, so a task
solves its blocks alone. Candidates are nodes of a tree (an episode is its parent with one event more). A pass counts what
follows every node of the tree. Which nodes are worth counting is guessed on one block; a guess decides only what is counted in
the same pass: growth takes the counts of the whole line, and a node that was not guessed is counted by the next pass. So results
don't depend on guesses, and a round takes a few passes, not one for each level.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Episode, floor_met, score
from ..params import Params
from ..sources.shared import Scratch
from . import kernel

PACK_EVENTS = 1 << 21  # events that a task packs at once
POOL = 2000  # candidates that a choice starts with
FEW = 150  # candidates whose overlaps are all counted at once
AHEAD = 4  # candidates whose overlaps with all others a pass counts


class Tree:
    """Episodes as nodes. Roots are single types."""

    def __init__(self, m: int, tg: int):
        self.m, self.tg = m, tg
        self.parent: list[int] = []
        self.etype: list[int] = []
        self.gap: list[int] = []
        self.size: list[int] = []
        self.at: dict[tuple[int, int, int], int] = {}

    def add(self, parent: int, etype: int, gap: int) -> int:
        key = parent, etype, gap
        if key not in self.at:
            self.at[key] = len(self.parent)
            self.parent.append(parent)
            self.etype.append(etype)
            self.gap.append(gap)
            self.size.append(1 if parent < 0 else self.size[parent] + 1)
        return self.at[key]

    def put(self, types: tuple[int, ...], gaps: tuple[int, ...]) -> int:
        k = -1
        for e, g in zip(types, (0, *gaps), strict=True):
            k = self.add(k, e, g)
        return k

    def episode(self, k: int) -> Episode:
        types, gaps = [], []
        while k >= 0:
            types.append(self.etype[k])
            gaps.append(self.gap[k])
            k = self.parent[k]
        return Episode(tuple(types[::-1]), tuple(gaps[::-1][1:]))

    def walk(self, nodes) -> Walk:
        """What a task needs to find the occurrences of these nodes."""
        on = set()
        for k in nodes:
            while k >= 0 and k not in on:
                on.add(k)
                k = self.parent[k]
        return Walk(self, sorted(on), set(nodes))


class Walk:
    def __init__(self, tree: Tree, on: list[int], wanted: set[int]):
        self.m, self.tg = tree.m, tree.tg
        self.parent, self.etype = np.array(tree.parent, np.int64), np.array(tree.etype, np.int64)
        self.root = np.full(tree.m, -1, np.int64)
        self.wanted = np.zeros(len(self.parent), bool)
        self.wanted[list(wanted)] = True
        children = []
        for k in on:
            if tree.parent[k] < 0:
                self.root[tree.etype[k]] = k
            else:
                children.append(((tree.parent[k] * self.m + tree.etype[k]) * (self.tg + 1) + tree.gap[k], k))
        children.sort()
        self.keys, self.child = np.array([a for a, _ in children], np.int64), np.array([b for _, b in children], np.int64)
        self.inner = np.zeros(len(self.parent), bool)
        self.inner[self.parent[self.child]] = True
        self.used = self.ways = None  # made where a task needs them
        # children of a node lie together, in order of their parents' numbers
        self.n_children = np.bincount(self.parent[self.child], minlength=len(self.parent)) if len(self.child) else np.zeros(len(self.parent), np.int64)
        self.first_child = np.cumsum(self.n_children) - self.n_children
        self.gap = np.array(tree.gap, np.int64)

    def key(self, node: np.ndarray, etype: np.ndarray, gap: np.ndarray) -> np.ndarray:
        return (node * self.m + etype) * (self.tg + 1) + gap

    def next(self, key: np.ndarray) -> np.ndarray:
        """The node that each extension leads to, -1 where none is on the way."""
        if not len(self.keys):
            return np.full(len(key), -1, np.int64)
        if self.ways is None and (space := len(self.parent) * self.m * (self.tg + 1)) <= kernel.DENSE:
            self.ways = np.full(space, -1, np.int32)
            self.ways[self.keys] = self.child
        if self.ways is not None:
            return self.ways[key]
        place = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[place] == key, self.child[place], -1)

    def unused(self, node: np.ndarray, etype: np.ndarray) -> np.ndarray:
        if self.used is None and len(self.parent) * self.m <= 16 * kernel.DENSE:
            self.used = np.zeros((len(self.parent), self.m), bool)
            for k in range(len(self.parent)):
                if self.parent[k] >= 0:
                    self.used[k] = self.used[self.parent[k]]
                self.used[k, self.etype[k]] = True
        if self.used is not None:
            return ~self.used[node, etype]
        ok = np.ones(len(node), bool)
        while len(node) and node.max() >= 0:
            ok &= (self.etype[node] != etype) | (node < 0)
            node = np.where(node < 0, -1, self.parent[node])
        return ok

    def grow(self, parent: list[int], etype: list[int], ways: dict[int, int]) -> None:
        """Nodes one event longer, which alone are on the way from here."""
        self.parent, self.etype = np.append(self.parent, parent), np.append(self.etype, etype)
        self.keys = np.array(sorted(ways), np.int64)
        self.child = np.array([ways[x] for x in sorted(ways)], np.int64)
        self.used = self.ways = None

    def steps(self, ev: kernel.Events, find: Callable[[np.ndarray], np.ndarray], node: np.ndarray, end: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
        """Row, event index and child of the occurrences of the nodes' children, looked up by their times and types."""
        n = self.n_children[node]
        upto, a = np.cumsum(n), 0
        while a < len(node):
            base = int(upto[a] - n[a])
            b = max(a + 1, int(np.searchsorted(upto, base + kernel.PART_ROWS, side="right")))
            row = np.repeat(np.arange(a, b), n[a:b])
            to = self.child[np.arange(base, base + len(row)) - np.repeat(upto[a:b] - n[a:b] - self.first_child[node[a:b]], n[a:b])]
            at = find((end[row] + self.gap[to]) * ev.m + self.etype[to])
            on = at >= 0
            yield row[on], at[on], to[on]
            a = b

    def extensions(self, ev: kernel.Events, node: np.ndarray, end: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
        """Row, event index, key of all one-event extensions by a type that the episode doesn't have, in parts of bounded size."""
        for row, at, gap in kernel.followers_in_parts(ev, end, self.tg):
            ok = self.unused(node[row], ev.e[at])
            row, at, gap = row[ok], at[ok], gap[ok]
            yield row, at, self.key(node[row], ev.e[at], gap)

    def levels(self, ev: kernel.Events, lo: int, hi: int, counting=None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Node, start and end of the occurrences on the way that start in lo..hi, level by level. counting(keys) gets the
        extensions of wanted nodes."""
        first = np.flatnonzero((ev.t >= lo) & (ev.t < hi) & (self.root[ev.e] >= 0))
        node, start, end = self.root[ev.e[first]], ev.t[first], ev.t[first]
        find, whole = None if counting else _places(ev), bool(self.wanted.all())
        while len(node):
            yield node, start, end
            go = self.inner[node] | (self.wanted[node] if counting else False)
            node, start, end = node[go], start[go], end[go]
            if not counting:
                parts = [(to, start[row], ev.t[at]) for row, at, to in self.steps(ev, find, node, end)]
                if not parts:
                    return
                node, start, end = (np.concatenate(x) for x in zip(*parts, strict=True))
                continue
            parts = []
            for row, at, key in self.extensions(ev, node, end):
                counting(key if whole else key[self.wanted[node[row]]])
                to = self.next(key)
                on = to >= 0
                parts.append((to[on], start[row[on]], ev.t[at[on]]))
            if not parts:
                return
            node, start, end = (np.concatenate(x) for x in zip(*parts, strict=True))


def _places(ev: kernel.Events) -> Callable[[np.ndarray], np.ndarray]:
    """A function from keys (time by types, type) to the events' places, -1 where there is none; by direct addressing where a
    block's time is short."""
    if not len(ev):
        return lambda want: np.full(len(want), -1, np.int64)
    key = ev.t * ev.m + ev.e
    first, space = int(key[0]), int(key[-1] - key[0]) + 1
    if space <= kernel.DENSE:
        place = np.full(space + 1, -1, np.int32)  # the last stands for all keys outside
        place[key - first] = np.arange(len(ev))
        return lambda want: place[np.where((want >= first) & (want < first + space), want - first, space)]

    def find(want: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(key, want), len(key) - 1)
        return np.where(key[at] == want, at, -1)

    return find


def _pieces(t: np.ndarray, e: np.ndarray, ticks: int, reach: int) -> pa.RecordBatch:
    """Events by block, with copies for the neighbours."""
    home = t // ticks
    on = t - home * ticks
    early, late = on < reach, on >= ticks - reach
    block = np.concatenate([home, home[early] - 1, home[late] + 1])
    order = np.argsort(block, kind="stable")
    block, t, e = block[order], np.concatenate([t, t[early], t[late]])[order], np.concatenate([e, e[early], e[late]])[order]
    first = np.flatnonzero(np.diff(block, prepend=block[:1] - 1))
    edges = pa.array(np.append(first, len(block)), pa.int32())
    lists = [pa.ListArray.from_arrays(edges, pa.array(x, k)) for x, k in ((t, pa.int64()), (e, pa.int32()))]
    return pa.RecordBatch.from_arrays([pa.array(block[first], pa.int64()), *lists], names=["block", "t", "e"])


def _blocks(batches: Iterator[pa.RecordBatch], m: int) -> Iterator[tuple[int, kernel.Events]]:
    for b in batches:
        for i in range(b.num_rows):
            ev = kernel.Events(*(b.column(c)[i].values.to_numpy(zero_copy_only=False) for c in ("t", "e")))
            ev.m = m
            yield b.column("block")[i].as_py(), ev


SCHEMA = "block long, t array<long>, e array<int>"


class Line:
    """A line of events in packed blocks."""

    def __init__(self, events: DataFrame, p: Params, scratch: Scratch, nodes: int):
        self.p, self.scratch, self.spark = p, scratch, events.sparkSession
        r = events.agg(F.count(F.lit(1)), F.max("etype"), F.min("t"), F.max("t")).first()
        self.n_events, self.m, self.span = r[0], (r[1] or 0) + 1, (r[3] or 0) - (r[2] or 0) + 1
        self._lay(events.select("t", "etype"), nodes)

    def _lay(self, events: DataFrame, nodes: int) -> None:
        self.nodes, self.reach = nodes, (nodes - 1) * self.p.tg
        self.ticks = ticks = max(self.p.block_ticks, self.reach + 1)
        reach = self.reach

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held, size = [], 0
            for b in batches:
                held.append((b.column("t").to_numpy(), b.column("etype").to_numpy()))
                size += b.num_rows
                if size >= PACK_EVENTS:
                    yield _pieces(*(np.concatenate(x) for x in zip(*held, strict=True)), ticks, reach)
                    held, size = [], 0
            if size:
                yield _pieces(*(np.concatenate(x) for x in zip(*held, strict=True)), ticks, reach)

        self._gather(events.mapInArrow(run, SCHEMA))

    def _gather(self, pieces: DataFrame) -> None:
        """Pieces of a block put together. A partition has some blocks, so that all cores have work."""
        n = self.span // self.ticks + 2
        parts = int(max(1, min(n, max(4 * self.spark.sparkContext.defaultParallelism, n // 8))))
        rows = pieces.repartition(parts, "block").groupBy("block").agg(*(F.flatten(F.collect_list(c)).alias(c) for c in ("t", "e")))
        self.packed = self.scratch.write(rows)
        lo = F.col("block") * self.ticks
        home = F.size(F.filter("t", lambda x: (x >= lo) & (x < lo + self.ticks)))
        self.sizes = sorted((r[1], r[0]) for r in self.packed.select("block", home).collect())  # a row for each block
        self.n_events = sum(x for x, _ in self.sizes)

    def _run(self, solve, schema: str, rows: DataFrame | None = None) -> DataFrame:
        m, ticks = self.m, self.ticks

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            yield from solve((ev, block * ticks, (block + 1) * ticks) for block, ev in _blocks(batches, m))

        return (self.packed if rows is None else rows).mapInArrow(run, schema)

    def room_for(self, size: int) -> None:
        """Blocks are laid anew where extensions of episodes of this size would not be in reach."""
        if size >= self.nodes:
            self._lay(self.events().select("t", "etype"), max(size + 1, 2 * self.nodes))

    def events(self) -> DataFrame:
        def solve(blocks):
            for ev, lo, hi in blocks:
                here = (ev.t >= lo) & (ev.t < hi)
                yield pa.RecordBatch.from_arrays([pa.array(ev.e[here], pa.int32()), pa.array(ev.t[here])], names=["etype", "t"])

        return self._run(solve, "etype int, t long")

    def type_counts(self) -> dict[int, int]:
        return {r["etype"]: r["n"] for r in self.events().groupBy("etype").agg(F.count(F.lit(1)).alias("n")).collect()}

    def follow(self, tree: Tree, nodes: list[int]) -> DataFrame:
        """node, etype, gap, n: how often each extension of these nodes occurs."""
        walk = tree.walk(nodes)

        def solve(blocks):
            counts = kernel.Counts(len(walk.parent) * walk.m * (walk.tg + 1))
            for ev, lo, hi in blocks:
                for _ in walk.levels(ev, lo, hi, counts.add):
                    pass
            key, n = counts.all()
            cols = key // ((walk.tg + 1) * walk.m), key // (walk.tg + 1) % walk.m, key % (walk.tg + 1)
            yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int32()) for c in cols), pa.array(n)], names=["node", "etype", "gap", "n"])

        rows = self._run(solve, "node int, etype int, gap int, n long").repartition("node")
        return rows.groupBy("node", "etype", "gap").agg(F.sum("n").alias("n"))

    def guess(self, tree: Tree, nodes: list[int], grow) -> list[int]:
        """Nodes that probably follow these, added to the tree: grown on one block of middling size. grow(size, old, counts, scale)
        tells which of a node's extensions, with their counts here, go on."""
        rows = [x for x in self.sizes if x[0]]
        if not rows:
            return []
        here, block = rows[len(rows) // 2]
        walk, scale, sizes, most = tree.walk(nodes), self.n_events / here, list(tree.size), self.nodes - 1

        def solve(blocks):
            for ev, lo, hi in blocks:
                found = [[x[walk.wanted[node]] for x in (node, start, end)] for node, start, end in walk.levels(ev, lo, hi)]
                node, _, end = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64),) * 3
                new: list[tuple[int, int, int, int]] = []
                while len(node):
                    counts = kernel.Counts(len(walk.parent) * walk.m * (walk.tg + 1))
                    for _, _, key in walk.extensions(ev, node, end):
                        counts.add(key)
                    key, n = counts.all()
                    who, old = key // ((walk.tg + 1) * walk.m), np.bincount(node, minlength=len(walk.parent))
                    ways: dict[int, int] = {}
                    parent, etype = [], []
                    edges = np.flatnonzero(np.diff(who, prepend=-1, append=-1)) if len(who) else []
                    for a, b in zip(edges[:-1], edges[1:], strict=True):
                        k = int(who[a])
                        if sizes[k] >= most:
                            continue
                        e, g = key[a:b] // (walk.tg + 1) % walk.m, key[a:b] % (walk.tg + 1)
                        for i in grow(sizes[k], int(old[k]), n[a:b], g, e, scale):
                            ways[int(key[a + i])] = len(walk.parent) + len(parent)
                            parent.append(k)
                            etype.append(int(e[i]))
                            sizes.append(sizes[k] + 1)
                            new.append((len(sizes) - 1, k, int(e[i]), int(g[i])))
                    if not ways:
                        break
                    walk.grow(parent, etype, ways)
                    parts = []
                    for _, at, x in walk.extensions(ev, node, end):
                        to = walk.next(x)
                        parts.append((to[to >= 0], ev.t[at[to >= 0]]))
                    node, end = (np.concatenate(x) for x in zip(*parts, strict=True))
                cols = list(zip(*new, strict=True)) if new else [[]] * 4
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int32()) for c in cols], names=["id", "parent", "etype", "gap"])

        known, out = {}, []
        for r in sorted(self._run(solve, "id int, parent int, etype int, gap int", self.packed.where(F.col("block") == block)).collect()):
            known[r["id"]] = tree.add(known.get(r["parent"], r["parent"]), r["etype"], r["gap"])
            out.append(known[r["id"]])
        return out

    def occurrences(self, eps: list[Episode]) -> DataFrame:
        """ep_id, start_t."""
        solve = _finder(self, eps)

        def rows(blocks):
            for ev, lo, hi in blocks:
                for i, starts in solve(ev, lo, hi):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(starts), i, np.int32)), pa.array(starts)], names=["no", "start_t"])

        names = self.spark.createDataFrame([(i, e.key) for i, e in enumerate(eps)], "no int, ep_id string")
        return self._run(rows, "no int, start_t long").join(F.broadcast(names), "no").select("ep_id", "start_t")  # names: a row for each episode

    def overlaps(self, eps: list[Episode]) -> dict[int, dict[int, int]]:
        """Events that two episodes share, both ways. An event counts in its own block."""
        solve, reach, n = _finder(self, eps), self.reach, len(eps)

        def rows(blocks):
            total: dict[tuple[int, int], int] = {}
            product = np.zeros((n, n), np.int64)
            for ev, lo, hi in blocks:
                if n <= 150 and n * len(ev) <= 8 * kernel.DENSE:  # quicker than sorting the events of all candidates
                    x = np.zeros((n, len(ev)), np.float32)
                    for i, starts in solve(ev, lo - reach, hi):
                        x[i, kernel.covered(ev, kernel.Candidate(eps[i].types, eps[i].gaps, starts))] = 1
                    x = x[:, (ev.t >= lo) & (ev.t < hi)]
                    for a in range(0, x.shape[1], 1 << 15):
                        product += (x[:, a : a + (1 << 15)] @ x[:, a : a + (1 << 15)].T).astype(np.int64)
                    continue
                at, who = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
                for i, starts in solve(ev, lo - reach, hi):
                    x = kernel.covered(ev, kernel.Candidate(eps[i].types, eps[i].gaps, starts))
                    at.append(x[(ev.t[x] >= lo) & (ev.t[x] < hi)])
                    who.append(np.full(len(at[-1]), i))
                for a, some in kernel.shared(np.concatenate(at), np.concatenate(who), n, len(ev)).items():
                    for b, x in some.items():
                        if a < b:
                            total[a, b] = total.get((a, b), 0) + x
            total |= {(a, b): int(product[a, b]) for a, b in np.argwhere(np.triu(product, 1)).tolist()}
            cols = list(zip(*((a, b, x) for (a, b), x in total.items()), strict=True)) if total else [[]] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int32(), pa.int32(), pa.int64()), strict=True)], names=["a", "b", "n"])

        om: dict[int, dict[int, int]] = {}
        for r in self._run(rows, "a int, b int, n long").groupBy("a", "b").agg(F.sum("n").alias("n")).collect():  # a row for each pair of candidates
            om.setdefault(r["a"], {})[r["b"]] = om.setdefault(r["b"], {})[r["a"]] = r["n"]
        return om

    def overlaps_of(self, some: list[int], eps: list[Episode]) -> dict[int, dict[int, int]]:
        """The same from some of the episodes to all: a line for each of some."""
        tree, reach, n = Tree(self.m, self.p.tg), self.reach, len(eps)
        nodes = [tree.put(e.types, e.gaps) for e in eps]
        walk, mine = tree.walk(nodes), tree.walk([nodes[i] for i in some])
        column = {nodes[i]: c for c, i in enumerate(some)}
        kind = np.uint8 if max(tree.size) < 256 else np.int32

        def rows(blocks):
            by_node = np.zeros((len(tree.parent), len(some)), np.int64)
            for ev, lo, hi in blocks:
                inside = np.zeros((len(ev), len(some)), kind)  # which of some an event is in
                for i, starts in _occurrences(mine, ev, lo - reach, hi):
                    e = tree.episode(i)
                    inside[kernel.covered(ev, kernel.Candidate(e.types, e.gaps, starts)), column[i]] = 1
                inside[(ev.t < lo) | (ev.t >= hi)] = 0
                find = _places(ev)
                at = np.flatnonzero((ev.t >= lo - reach) & (ev.t < hi) & (walk.root[ev.e] >= 0))
                node, end, met = walk.root[ev.e[at]], ev.t[at], inside[at]  # met: an occurrence's events in each of some
                while len(node):
                    order = np.argsort(node, kind="stable")
                    node, end, met = node[order], end[order], met[order]
                    edges = np.flatnonzero(np.diff(node, prepend=-1))
                    by_node[node[edges]] += np.add.reduceat(met, edges, axis=0, dtype=np.int64)
                    parts = [(to, ev.t[x], met[row] + inside[x]) for row, x, to in walk.steps(ev, find, node, end)]
                    if not parts:
                        break
                    node, end, met = (np.concatenate(x) for x in zip(*parts, strict=True))
            total = by_node[nodes]
            b, a = np.nonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(np.array(some, np.int32)[a]), pa.array(b.astype(np.int32)), pa.array(total[b, a])], names=["a", "b", "n"])

        om: dict[int, dict[int, int]] = {i: {} for i in some}
        for r in self._run(rows, "a int, b int, n long").where("a <> b").groupBy("a", "b").agg(F.sum("n").alias("n")).collect():  # a row for each pair of them
            om[r["a"]][r["b"]] = r["n"]
        return om

    def delete(self, eps: list[Episode]) -> None:
        """Events in occurrences of these episodes go; blocks are laid anew from what is left of each."""
        solve, reach, ticks = _finder(self, eps), self.reach, self.ticks

        def rows(blocks):
            for ev, lo, hi in blocks:
                keep = (ev.t >= lo) & (ev.t < hi)
                for i, starts in solve(ev, lo - reach, hi):
                    keep[kernel.covered(ev, kernel.Candidate(eps[i].types, eps[i].gaps, starts))] = False
                if keep.any():
                    yield _pieces(ev.t[keep], ev.e[keep], ticks, reach)

        self._gather(self._run(rows, SCHEMA))


def _finder(line: Line, eps: list[Episode]):
    """A function for tasks: (number, starts) of each episode's occurrences that start in lo..hi."""
    tree = Tree(line.m, line.p.tg)
    number = {tree.put(e.types, e.gaps): i for i, e in enumerate(eps)}
    walk = tree.walk(list(number))

    def solve(ev: kernel.Events, lo: int, hi: int) -> Iterator[tuple[int, np.ndarray]]:
        for k, starts in _occurrences(walk, ev, lo, hi):
            yield number[k], starts

    return solve


def _occurrences(walk: Walk, ev: kernel.Events, lo: int, hi: int) -> Iterator[tuple[int, np.ndarray]]:
    """Wanted nodes and the starts of their occurrences in lo..hi."""
    for node, start, _ in walk.levels(ev, lo, hi):
        mine = walk.wanted[node]
        node, start = node[mine], start[mine]
        order = np.argsort(node, kind="stable")
        node, start = node[order], start[order]
        edges = np.flatnonzero(np.diff(node, prepend=-1, append=-1))
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            yield int(node[a]), start[a:b]


def best_paths(line: Line) -> list[tuple[Episode, int]]:
    """Path-greedy candidates with their frequencies. Types with fewer than five events can't start a path."""
    p, tree, out = line.p, Tree(line.m, line.p.tg), []

    def admits(size: int, old: int, n: int, gap: int) -> bool:
        if not floor_met(size, n, gap, p.tg) or (p.max_size and size >= p.max_size):
            return False
        return p.stop_rule != "score_improves" or score(size + 1, n) > score(size, old)

    def grow(size, old, n, gap, etype, scale):
        i = np.lexsort((etype, gap, -n))[0]
        return [i] if admits(size, int(old * scale), int(n[i] * scale), int(gap[i])) else []

    freq = {tree.add(-1, e, 0): n for e, n in sorted(line.type_counts().items()) if n >= 5}
    front = list(freq)
    while front:
        line.room_for(max(tree.size[k] for k in front))
        nodes = [*front, *line.guess(tree, front, grow)]
        best = line.follow(tree, nodes).groupBy("node").agg(F.max(F.struct("n", (-F.col("gap")).alias("gap"), (-F.col("etype")).alias("etype"))).alias("x"))
        found = {r["node"]: (r["x"]["n"], -r["x"]["gap"], -r["x"]["etype"]) for r in best.collect()}  # a row for each node
        todo, front, counted = front, [], set(nodes)
        while todo:
            k = todo.pop()
            n, gap, etype = found.get(k, (0, 1, 0))
            if n and admits(tree.size[k], freq[k], n, gap):
                child = tree.add(k, etype, gap)
                freq[child] = n
                (todo if child in counted else front).append(child)
            elif tree.size[k] > 1 and score(tree.size[k], freq[k]) > 0:
                out.append((tree.episode(k), freq[k]))
    return out


def frequent(line: Line, least: float) -> list[tuple[Episode, int]]:
    """All episodes of two or more nodes with a frequency at or above `least`."""
    p, tree, out = line.p, Tree(line.m, line.p.tg), []
    front = [tree.add(-1, e, 0) for e, n in sorted(line.type_counts().items()) if n >= least]
    often = set(tree.etype)

    def grow(size, old, n, gap, etype, scale):
        return [] if p.max_size and size + 1 >= p.max_size else np.flatnonzero(n * scale >= least).tolist()

    while front and not (p.max_size and p.max_size <= 1):
        line.room_for(max(tree.size[k] for k in front))
        nodes = list(dict.fromkeys([*front, *line.guess(tree, front, grow)]))
        found: dict[int, list] = {}
        for r in line.follow(tree, nodes).where(F.col("n") >= least).collect():  # a row for each frequent episode
            found.setdefault(r["node"], []).append(r)
        todo, front, counted = front, [], set(nodes)
        while todo:
            k = todo.pop()
            for r in found.get(k, ()):
                if r["etype"] not in often:
                    continue
                child = tree.add(k, r["etype"], r["gap"])
                out.append((tree.episode(child), r["n"]))
                if not (p.max_size and tree.size[child] >= p.max_size):
                    (todo if child in counted else front).append(child)
    return out


class _Choice:
    def __init__(self, episode: Episode, freq: int):
        self.types, self.gaps, self.value = episode.types, episode.gaps, score(episode.size, freq)
        self.episode = episode


def choose(line: Line, eps: list[tuple[Episode, int]], left: int | None, pool: int = POOL) -> list[tuple[Episode, int]]:
    """The greedy picks (episode, overlap score) from useful candidates.

    Overlaps are counted among a pool of the best by initial score. An overlap score never exceeds the initial score, so picks
    above the best initial score outside the pool are final. If more may follow, the pool is widened and the choice made again.
    """
    p = line.p
    ranked = sorted((_Choice(e, n) for e, n in eps), key=lambda c: (-c.value, kernel.tie_order(c)))[: p.max_candidates]
    while True:
        cands, bound = ranked[:pool], ranked[pool].value if len(ranked) > pool else 0
        picks = kernel.greedy(cands, _Overlaps(line, cands) if p.overlap_mode == "penalise" else {}, left, bound=bound)
        final = next((i for i, (_, s) in enumerate(picks) if s <= bound), len(picks))
        if final == len(picks) and (bound == 0 or len(picks) == left):
            return [(cands[i].episode, s) for i, s in picks]
        pool *= 2


class _Overlaps:
    """Overlaps of a pick with all candidates. Of few candidates all are counted at once; else a pass counts those of the
    candidates that come first now, which the next picks are likely to be."""

    def __init__(self, line: Line, cands: list[_Choice]):
        self.line, self.eps = line, [c.episode for c in cands]
        self.known = line.overlaps(self.eps) if len(cands) <= FEW else None
        self.rows: dict[int, dict[int, int]] = {}

    def __call__(self, i: int, ranking: Callable[[], list[int]]) -> dict[int, int]:
        if self.known is not None:
            return self.known.get(i, {})
        if i not in self.rows:
            ahead = [j for j in ranking() if j not in self.rows and j != i]
            self.rows |= self.line.overlaps_of([i, *ahead[: AHEAD - 1]], self.eps)
        return self.rows[i]
