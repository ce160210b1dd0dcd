"""Trials of the order-only baselines."""

from __future__ import annotations

import random
from collections import Counter

import pyarrow as pa

from fixgap.operators import baselines, lines
from fixgap.plans import paper


def test_trials_told_by_what_they_change_equal_whole_covers(spark, monkeypatch):
    """A cover of every line for every trial made large lines miss their time."""
    rng = random.Random(4)
    rows = [(i, [rng.randrange(1, 7) for _ in range(rng.randrange(0, 30))]) for i in range(120)]
    lines = spark.createDataFrame(rows, "seq_id long, line array<int>")
    chosen = [(2, 3, 1), (1, 2), (4, 2)]
    cands = [(1, 2), (3, 4), (5, 1, 2, 3), (2, 1), (9, 1), (6, 5, 4)]
    want = []
    for c in cands:
        trial = baselines._ordered([*chosen, c])
        uses, skips = {}, {}
        for _, line in rows:
            for _, k, s in baselines.cover(line, trial, 8):
                uses[k], skips[k] = uses.get(k, 0) + 1, skips.get(k, 0) + s
        want.append((trial, uses, {k: n for k, n in skips.items() if n}))
    monkeypatch.setattr(baselines, "cover", None)
    got = baselines._with_each(lines, chosen, cands, 8)
    assert [(t, dict(u), {k: n for k, n in s.items() if n}) for t, u, s in got] == want
    assert sum(bool(u.get(0)) for _, u, _ in got) > 2


def test_conveyor_tables_try_every_join(spark, small, monkeypatch):
    """Their search ended after 16 joins in a row without gain, which lost patterns (48 of 51 at sf0.001, three routes)."""
    asked = []
    monkeypatch.setattr(baselines, "gap_coding", lambda rows, m, patience=None, **_: asked.append(patience) or ([], 1.0, 1.0))
    monkeypatch.setattr(baselines, "dependency_test", lambda rows, m: ([], 1.0, 1.0))
    queries = paper.Q
    for name in ("tab_conv_two", "tab_conv_three", "tab_conv_time"):
        queries[name](spark, small).collect()
    assert asked == [None] * 5


def test_covers_in_arrays_equal_covers_of_each_sequence(monkeypatch):
    """Covers in plain Python, a sequence at a time, made every pass over a large line take seconds."""
    rng = random.Random(9)
    rows = [[rng.randrange(1, 6) for _ in range(rng.randrange(0, 60))] for _ in range(300)]
    patterns, window = [(3, 1, 2, 5), (2, 4, 1), (1, 2), (4, 3), (7, 1)], 9
    batch = pa.RecordBatch.from_arrays([pa.array([[0]] + rows, pa.list_(pa.int32()))], names=["line"]).slice(1)
    for chunk, flags in ((1, 1 << 22), (500, 0), (1 << 18, 0), (1 << 18, 1 << 22)):
        uses, skips, pairs, n, wins = Counter(), Counter(), Counter(), Counter(), Counter()
        monkeypatch.setattr(lines, "CHUNK", chunk)
        monkeypatch.setattr(lines, "FLAGS", flags)
        for piece in lines.pieces(iter([batch])):
            for k, c, s in (got := lines.statistics(piece, patterns, window, True))[0]:
                uses[k] += c
                skips[k] += s
            for a, b, c in got[1]:
                pairs[a, b] += c
            for e, c, w in lines.sides(piece, (1, 2), window):
                n[e] += c
                wins[e] += w
        covers = [baselines.cover(line, patterns, window) for line in rows]
        assert uses == Counter(k for x in covers for _, k, _ in x)
        assert +skips == +sum((Counter({k: s}) for x in covers for _, k, s in x), Counter())
        assert pairs == Counter((a[1], b[1]) for x in covers for a, b in zip(x, x[1:], strict=False))
        want = Counter(), Counter()
        for line in rows:
            beside = Counter()
            for i, k, s in baselines.cover(line, [(1, 2)], window):
                if k == 0:
                    beside.update(set(line[i + 2 + s : i + window]))
                    beside.subtract(set(line[max(0, i + 2 + s - window) : i]))
            for e, x in beside.items():
                if x and e not in (1, 2):
                    want[0][e] += 1
                    want[1][e] += x > 0
        assert n == want[0] and +wins == +want[1]
