"""What the selectors are compared with: trivial and raw coding, all frequent episodes, closed and maximal ones, a random
subset, a gap-coding pattern set and a dependency-test pattern set over order-only sequences.

The last two work on many short sequences without times. A cover is a fold of each sequence on its own, so it runs in Arrow
batches over the executors; uses, marks and neighbouring pairs are aggregates; a round's decision is the driver's. Their
published descriptions leave much open; costs here are: dictionary (gamma-coded size, fixed-width types and code length),
each use at -log2 of its pattern's share of all uses, and a mark for each step inside an occurrence (go on or skip) at the
marks' entropy by pattern.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Callable, Iterable, Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.expr import episode_key, episode_score
from ..params import Params
from . import table
from .lines import Piece, changes, pieces, sides, statistics


def frequent_all(events: DataFrame, p: Params, nodes: int = 16) -> DataFrame:
    """Every frequent multi-node episode: ep_id, size, types, gaps, freq."""
    from ..sources.shared import Scratch

    scratch = Scratch(events.sparkSession)
    events = scratch.write(events.select("etype", "t"))
    lay = table.Layout(events, p, nodes)
    rows, _ = table.frequent(lay, p.fth * events.count(), scratch)
    lay.drop()
    return rows


def _shorter(cands: DataFrame) -> DataFrame:
    """Each episode's sub-episodes with one node less: key, freq of the longer. Gaps around an inner node add up."""
    drop = F.posexplode("types").alias("i", "_e")
    rows = cands.where("size > 2").select("types", "gaps", "freq", "size", drop)
    types = F.filter("types", lambda _, j: j != F.col("i"))
    inner = F.transform(F.slice("gaps", F.lit(1), F.col("size") - 2), lambda g, j: F.when(j < F.col("i") - 1, g).when(j == F.col("i") - 1, g + F.element_at("gaps", F.col("i") + 1)).otherwise(F.element_at("gaps", j + 2)))
    gaps = F.when(F.col("i") == 0, F.slice("gaps", F.lit(2), F.col("size") - 2)).when(F.col("i") == F.col("size") - 1, F.slice("gaps", F.lit(1), F.col("size") - 2)).otherwise(inner)
    return rows.select(episode_key(types, gaps).alias("ep_id"), F.col("freq").alias("long_freq"))


def closed(cands: DataFrame) -> DataFrame:
    """Candidates (ep_id, size, types, gaps, freq) without a longer one of equal frequency."""
    return cands.join(_shorter(cands).select("ep_id", F.col("long_freq").alias("freq")), ["ep_id", "freq"], "left_anti").select(*cands.columns)


def maximal(cands: DataFrame) -> DataFrame:
    """Candidates that no longer candidate extends."""
    return cands.join(_shorter(cands).select("ep_id"), "ep_id", "left_anti")


def closed_then_greedy(events: DataFrame, p: Params) -> DataFrame:
    """One greedy pass over closed frequent episodes: rank, score, size, types, gaps, freq."""
    from ..sources.shared import Scratch

    spark = events.sparkSession
    scratch = Scratch(spark)
    events = scratch.write(events.select("etype", "t"))
    lay = table.Layout(events, p)
    rows, occs = table.frequent(lay, p.fth * events.count(), scratch)
    kept = scratch.write(closed(rows).where(episode_score(F.col("size").cast("long"), F.col("freq")) > 0))
    chosen, _ = table.choose(kept, occs, p.k, p)
    lay.drop()
    names = spark.createDataFrame([(i, s, e.key) for i, (e, s) in enumerate(chosen, 1)], "rank int, score long, ep_id string")
    return kept.join(names, "ep_id").select("rank", "score", "size", "types", "gaps", "freq")


def random_subset(cands: DataFrame, n: int, seed: int = 1) -> DataFrame:
    """n useful candidates drawn by hash: a control for the choice."""
    useful = cands.where(episode_score(F.col("size").cast("long"), F.col("freq")) > 0)
    return useful.orderBy(F.xxhash64("ep_id", F.lit(seed)), "ep_id").limit(n)



# ---- order-only pattern sets


def _parts(spark: SparkSession) -> int:
    """Many passes follow over the lines, so small tables use all cores too."""
    return max(2 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))


FEW = 64  # tasks whose sums the driver adds up


def _sums(lines: DataFrame, rows_of: Callable[[Piece], list[tuple]], n_keys: int, n_values: int) -> dict[tuple, tuple]:
    """Sums over all sequences of the rows (keys, then values, all whole numbers) that `rows_of` tells of a piece, by keys."""
    names = [f"k{i}" for i in range(n_keys)] + [f"v{i}" for i in range(n_values)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple, tuple] = {}
        for piece in pieces(batches):
            _add(total, rows_of(piece), n_keys)
        cols = list(zip(*(k + v for k, v in total.items()), strict=True)) if total else [[]] * len(names)
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=names)

    rows = lines.select("line").mapInArrow(run, ", ".join(f"{x} long" for x in names))
    if _parts(lines.sparkSession) > FEW:
        rows = rows.groupBy(*names[:n_keys]).agg(*(F.sum(x).alias(x) for x in names[n_keys:]))
    return _add({}, map(tuple, rows.collect()), n_keys)  # a row for each type, pattern of a trial, or pair, from each of few tasks


def _add(total: dict[tuple, tuple], rows: Iterable[tuple], n_keys: int) -> dict[tuple, tuple]:
    for row in rows:
        key, values = row[:n_keys], row[n_keys:]
        old = total.get(key)
        total[key] = values if old is None else tuple(a + b for a, b in zip(old, values, strict=True))
    return total


def _lines(seqs: DataFrame) -> DataFrame:
    """One row for each sequence: its types in order. Sequences are chopped or short by nature."""
    return seqs.repartition(_parts(seqs.sparkSession), "seq_id").groupBy("seq_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("t", "etype"))), lambda x: x["etype"]).alias("line"))


def cover(line: list[int], patterns: list[tuple[int, ...]], window: int) -> list[tuple[int, int, int]]:
    """Uses as (position, pattern number, skips), patterns in the order given; what none covers is left to single events (number -1 - type)."""
    free, uses = [True] * len(line), []
    at: dict[int, list[int]] = {}
    for i, e in enumerate(line):
        at.setdefault(e, []).append(i)
    for number, pat in enumerate(patterns):
        places = [at.get(e) for e in pat]
        if None in places:
            continue
        for i in places[0]:
            if not free[i]:
                continue
            got = [i]
            for some in places[1:]:
                j = next((x for x in some if x > got[-1] and free[x]), None)
                if j is None or j - i >= window:
                    break
                got.append(j)
            else:
                for x in got:
                    free[x] = False
                uses.append((i, number, got[-1] - i + 1 - len(pat)))
    uses += [(i, -1 - e, 0) for i, e in enumerate(line) if free[i]]
    return sorted(uses)


def _statistics(lines: DataFrame, trials: list[list[tuple[int, ...]]], window: int, with_pairs: bool = False) -> list[tuple[Counter, Counter, Counter]]:
    """For each trial set of patterns, over all sequences and in one pass: uses and skips by pattern, and pairs of neighbouring uses."""

    def rows_of(piece: Piece) -> list[tuple]:
        rows = []
        for i, patterns in enumerate(trials):
            uses, pairs = statistics(piece, patterns, window, with_pairs)
            rows += [(0, i, k, 0, n, s) for k, n, s in uses]
            rows += [(1, i, x, y, n, 0) for x, y, n in pairs]
        return rows

    out = [(Counter(), Counter(), Counter()) for _ in trials]
    for (what, i, a, b), (n, s) in _sums(lines, rows_of, 4, 2).items():
        uses, skips, pairs = out[i]
        if what:
            pairs[a, b] = n
        else:
            uses[a], skips[a] = n, s
    return out


def _with_each(lines: DataFrame, chosen: list[tuple[int, ...]], cands: list[tuple[int, ...]], window: int) -> list[tuple[list[tuple[int, ...]], Counter, Counter]]:
    """For each candidate, patterns with it beside the chosen ones, and their uses and skips over all sequences, in one pass.

    A line is covered by the chosen patterns once; a candidate changes what comes after its place in the order, and nothing where
    it has no use. Single events are what patterns leave of each type's count.
    """
    chosen = _ordered(chosen)
    trials = [_ordered([*chosen, c]) for c in cands]
    spots = [None if c in chosen else trial.index(c) for c, trial in zip(cands, trials, strict=True)]

    def rows_of(piece: Piece) -> list[tuple]:
        kinds, n = np.unique(piece.e, return_counts=True)
        rows = [(-1, e, c, 0) for e, c in zip(kinds.tolist(), n.tolist(), strict=True)]
        base, more = changes(piece, chosen, cands, spots, window)
        rows += [(-2, k, c, s) for k, (c, s) in enumerate(base) if c]
        return rows + [(i, *x) for i, some in enumerate(more) for x in some]

    got = _sums(lines, rows_of, 2, 2)
    types = {a: n for (i, a), (n, _) in got.items() if i == -1}
    out = []
    for i, (trial, spot) in enumerate(zip(trials, spots, strict=True)):
        uses, skips, singles = Counter(), Counter(), Counter(types)
        for k, pattern in enumerate(trial):
            n, s = got.get((i, k), (0, 0))
            if spot is None or k != spot:
                x, y = got.get((-2, k - (spot is not None and k > spot)), (0, 0))
                n, s = n + x, s + y
            if n:
                uses[k], skips[k] = n, s
                for e in pattern:
                    singles[e] -= n
        uses.update({-1 - e: n for e, n in singles.items() if n})
        out.append((trial, uses, skips))
    return out


def _first_better(lines: DataFrame, chosen: list[tuple[int, ...]], cands: Iterator[tuple[int, ...]], best: float, m: int, window: int, patience: int | None, together: int = 8):
    """The first candidate that, beside the chosen patterns, lowers the bits: (bits, patterns in use), or None.

    Candidates are tried `together` in a pass, twice as many in each next; without `patience` all of them, else so many at most.
    """
    cands = iter(cands if patience is None else islice(cands, patience))
    while some := list(islice(cands, together)):
        together = min(2 * together, 128)
        for trial, u, s in _with_each(lines, chosen, some, window):
            bits = code_bits(trial, u, s, m)
            if bits < best:
                return bits, [c for k, c in enumerate(trial) if u[k]]
    return None


def _ordered(patterns: list[tuple[int, ...]]) -> list[tuple[int, ...]]:
    return sorted(set(patterns), key=lambda c: (-len(c), c))


def code_bits(patterns: list[tuple[int, ...]], uses: Counter, skips: Counter, m: int) -> float:
    """Total bits of dictionary, uses and marks."""
    total = sum(uses.values())
    bits = 0.0
    for k, n in uses.items():
        size = len(patterns[k]) if k >= 0 else 1
        bits += n * -math.log2(n / total)
        bits += 2 * int(math.log2(size)) + 1 + size * (int(math.log2(m)) + 1) + math.ceil(-math.log2(n / total)) + 1
        go, skip = n * (size - 1), skips[k]
        for x in (go, skip):
            if x:
                bits += x * -math.log2(x / (go + skip))
    return bits


def gap_coding(seqs: DataFrame, m: int, mode: str = "grow", max_window: int = 15, max_size: int = 12, patience: int | None = None) -> tuple[list[tuple[int, ...]], float, float]:
    """Patterns, their bits, and the bits of single events alone. seqs: seq_id, etype, t (order only).

    grow: join two that follow each other in the cover, the most frequent first, as long as some join lowers the bits.
    candidates: go through joined pairs of the first cover and their overlaps, longest first, keep what lowers the bits, and drop
    earlier ones that have become useless. patience: joins (or candidates in a row) without gain that end the search; None tries all.
    """
    lines = _lines(seqs).persist()
    (uses, skips, pairs), = _statistics(lines, [[]], max_window, True)
    base = best = code_bits([], uses, skips, m)
    chosen: list[tuple[int, ...]] = []
    joins = lambda ps, some: (c for (a, b), _ in sorted(some.items(), key=lambda x: (-x[1], x[0])) if len(c := _spell(a, ps) + _spell(b, ps)) <= max_size and len(set(c)) == len(c))
    if mode == "candidates":
        todo = list(joins([], pairs))
        todo += [x + y[-1:] for x in todo for y in todo if x[1:] == y[:-1] and y[-1] not in x]
        rest = sorted(set(todo), key=lambda c: (-len(c), -pairs[-1 - c[0], -1 - c[1]], c))
        while rest and (got := _first_better(lines, chosen, iter(rest), best, m, max_window, patience)):
            best, kept = got
            new = next((c for c in kept if c not in chosen), None)
            chosen = kept
            rest = rest[rest.index(new) + 1 :] if new in rest else rest[1:]
    else:
        tried: set[tuple[int, ...]] = set()
        while True:
            fresh = [c for c in joins(chosen, pairs) if c not in tried]
            got = _first_better(lines, chosen, iter(fresh), best, m, max_window, patience)
            if got is None:
                break
            best, kept = got
            new = next((c for c in kept if c not in chosen), fresh[0])
            tried.update(fresh[: fresh.index(new) + 1])
            chosen = kept
            (_, _, pairs), = _statistics(lines, [chosen], max_window, True)
    lines.unpersist()
    return chosen, best, base


def _spell(k: int, patterns: list[tuple[int, ...]]) -> tuple[int, ...]:
    return patterns[k] if k >= 0 else (-1 - k,)


def binomial_tail(n: int, k: int) -> float:
    """P(at least k of n fair tosses)."""
    return sum(math.exp(math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) - n * math.log(2)) for i in range(k, n + 1))


def dependent_types(lines: DataFrame, patterns: list[tuple[int, ...]], window: int, alpha: float, min_pairs: int) -> list[list[tuple[int, int]]]:
    """For each pattern, types that follow it more often than they precede it, by a sign test over sequences: (type, sequences for it)."""

    rows = _sums(lines, lambda piece: [(i, *x) for i, pattern in enumerate(patterns) for x in sides(piece, pattern, window)], 2, 2)
    out: list[list[tuple[int, int]]] = [[] for _ in patterns]
    for (i, e), (n, wins) in rows.items():
        if n >= min_pairs and binomial_tail(n, wins) <= alpha:
            out[i].append((e, wins))
    return [sorted(x, key=lambda x: (-x[1], x[0])) for x in out]


def dependency_test(seqs: DataFrame, m: int, alpha: float = 0.01, min_pairs: int = 25, max_window: int = 15) -> tuple[list[tuple[int, ...]], float, float]:
    """Patterns grown from single types by dependent types while bits fall; as `gap_coding` returns. One sequence has one pair, so nothing passes."""
    lines = _lines(seqs).persist()
    (uses, skips, _), = _statistics(lines, [[]], max_window)
    base = best = code_bits([], uses, skips, m)
    chosen: list[tuple[int, ...]] = []
    seeds = [(-1 - k,) for k, _ in sorted(uses.items(), key=lambda x: (-x[1], x[0]))]
    known: dict[tuple[int, ...], list[tuple[int, int]]] = {}  # what depends on a pattern is so whatever else is chosen
    for i, seed in enumerate(seeds):
        if any(seed[0] in c for c in chosen):
            continue
        if seed not in known:
            some = seeds[i : i + 64]
            known.update(zip(some, dependent_types(lines, some, max_window, alpha, min_pairs), strict=True))
        current = seed
        while True:
            if current not in known:
                known[current] = dependent_types(lines, [current], max_window, alpha, min_pairs)[0]
            longer = [(*current, e) for e, _ in known[current]]
            rest = [c for c in chosen if c != current]
            got = _first_better(lines, rest, iter(longer), best, m, max_window, None)
            if got is None:
                break
            best, chosen = got
            grown = next((c for c in longer if c in chosen), None)
            if grown is None:
                break
            current = grown
    lines.unpersist()
    return chosen, best, base
