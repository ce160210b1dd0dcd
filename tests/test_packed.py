"""Rounds over packed blocks."""

from __future__ import annotations

import random

import numpy as np
import pytest

from fixgap.operators import kernel, packed, table
from fixgap.params import Params
from fixgap.sources.shared import Scratch


def _planted(seed: int, size: int = 8, uses: int = 300) -> set[tuple[int, int]]:
    rng = random.Random(seed)
    line = {(e, 40 * k + 2 * e) for k in range(1, uses) for e in range(1, size + 1) if rng.random() < 0.97}
    return line | {(rng.randrange(1, size + 4), rng.randrange(1, 40 * uses)) for _ in range(3 * uses)}


@pytest.mark.parametrize("selector,settings", [("path_greedy", {}), ("path_greedy", {"max_candidates": 2}), ("path_greedy", {"stop_rule": "frequency_floor", "max_rounds": 3}), ("two_phase", {"max_size": 4})])
@pytest.mark.parametrize("guessing", [True, False])
def test_rounds_equal_the_kernel_whatever_is_guessed(spark, monkeypatch, selector, settings, guessing):
    """Each count comes from the whole line."""
    pairs = sorted(_planted(3))
    if not guessing:
        monkeypatch.setattr(packed.Line, "guess", lambda *x: [])
    p = Params(fth=0.03, block_ticks=900, **settings)
    want, left, steps = kernel.select(np.array([t for _, t in pairs]), np.array([e for e, _ in pairs]), p, selector)
    got, kept, rest, trace = table.select(spark.createDataFrame(pairs, "etype int, t long"), p, selector)
    assert [(x.round, x.rank, x.score, x.episode.types, x.episode.gaps) for x in want] == [(r, n, s, e.types, e.gaps) for r, n, s, e in got]
    assert trace == steps and rest.count() == len(left) and max(x.episode.size for x in want) > 3
    starts = {r["ep_id"]: r["n"] for r in kept.groupBy("ep_id").count().withColumnRenamed("count", "n").collect()}
    assert starts == {e.key: len(x.episode.starts) for x, (_, _, _, e) in zip(want, got, strict=True)}


def test_a_round_takes_fewer_passes_than_levels(spark, monkeypatch):
    """Guessed nodes are counted in the same pass; a pass for each level made large lines miss their time."""
    line = packed.Line(spark.createDataFrame(sorted({(e, 40 * k + 2 * e) for k in range(1, 300) for e in range(1, 13)}), "etype int, t long"), Params(block_ticks=900), Scratch(spark), 32)
    passes = []
    follow = packed.Line.follow
    monkeypatch.setattr(packed.Line, "follow", lambda self, tree, nodes: passes.append(len(nodes)) or follow(self, tree, nodes))
    assert max(e.size for e, _ in packed.best_paths(line)) == 12 and len(passes) == 1


def test_overlaps_count_an_event_once_over_block_borders(spark):
    pairs = sorted({(e, 7 * k + 2 * e) for k in range(1, 400) for e in (1, 2, 3)})
    p = Params(block_ticks=200)
    ev = kernel.Events(np.array([t for _, t in pairs]), np.array([e for e, _ in pairs]))
    cands = [c for c in kernel.frequent(ev, p.but(fth=0.05), len(ev)) if c.value > 0]
    line = packed.Line(spark.createDataFrame(pairs, "etype int, t long"), p, Scratch(spark), 8)
    assert line.overlaps([packed.Episode(c.types, c.gaps) for c in cands]) == kernel.overlaps(ev, cands) and len(cands) > 3


@pytest.mark.parametrize("ahead", [1, 3])
def test_a_choice_counts_overlaps_of_its_picks_only(spark, monkeypatch, ahead):
    """All pairs of many candidates made large lines miss their time; rows of the picks make the same choice."""
    pairs = sorted(_planted(5))
    p = Params(fth=0.03, block_ticks=900, max_size=4)
    ev = kernel.Events(np.array([t for _, t in pairs]), np.array([e for e, _ in pairs]))
    cands = [c for c in kernel.frequent(ev, p, len(ev)) if c.value > 0]
    om = kernel.overlaps(ev, cands)
    want = [(packed.Episode(cands[i].types, cands[i].gaps), s) for i, s in kernel.greedy(cands, om, None)]
    line = packed.Line(spark.createDataFrame(pairs, "etype int, t long"), p, Scratch(spark), 8)
    eps = [packed.Episode(c.types, c.gaps) for c in cands]
    assert line.overlaps_of([0, 5, 2], eps) == {i: om.get(i, {}) for i in (0, 5, 2)}
    monkeypatch.setattr(packed, "FEW", 1)
    monkeypatch.setattr(packed, "AHEAD", ahead)
    monkeypatch.setattr(packed.Line, "overlaps", None)
    for pool in (5, packed.POOL):
        got = packed.choose(line, [(e, len(c.starts)) for e, c in zip(eps, cands, strict=True)], None, pool)
        assert got == want and len(cands) > 50 > len(want) > 1


def test_coded_conveyor_is_the_encoded_line(spark):
    """Packages dealt out by time give the events and types of the whole line, equal events once, also without a time or route."""
    from datetime import datetime, timedelta

    from fixgap.sources import sequence as seq

    day = lambda i: None if i % 97 == 0 else datetime(1994, 12, 20) + timedelta(days=i * 37 % 2000)
    rows = [(i, i * 11 % 300, day(i), None if i % 89 == 0 else f"{(1, 3, 4)[i % 3]}-X") for i in range(1, 900)]
    orders = spark.createDataFrame([*rows, *rows[:50]], "o_orderkey long, o_custkey long, o_orderdate timestamp, o_orderpriority string")
    want, alphabet = seq.encode_alphabet(seq.conveyor_from_orders(orders, "three", day_ticks=1000))
    got, names = seq.coded_conveyor(orders, "three", day_ticks=1000)
    assert sorted(map(str, got.collect())) == sorted(map(str, want.select(*got.columns).collect()))
    assert sorted(map(tuple, names.collect())) == sorted(map(tuple, alphabet.select("etype", "symbol").collect()))


def test_frequent_episodes_of_a_middling_line_are_not_left_to_one_task(spark, monkeypatch):
    """The second round of a large line went to one task with thousands of candidates."""
    from fixgap.operators import selection

    pairs = sorted(_planted(7, size=5, uses=60))
    ev = spark.createDataFrame(pairs, "etype int, t long")
    p = Params(fth=0.03, block_ticks=900, kernel_events=2 * len(pairs), max_rounds=1)
    called = []
    rounds = table.rounds
    monkeypatch.setattr(table, "rounds", lambda *x, **y: called.append(y["until"]) or rounds(*x, **y))
    rows = [sorted(map(str, selection.select(ev, q, "two_phase").collect())) for q in (p, p.but(engine="kernel"))]
    assert rows[0] == rows[1] and called == [p.kernel_events // 32]
