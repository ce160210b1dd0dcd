"""Worked examples, planted cases, brute force, engine equivalence and published behaviour of the sequence methods."""

import random
import sys
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).parent))
import brute

from fixgap import api
from fixgap.functions.expr import elias_bits, episode_key, min_useful_freq, offsets, type_bits
from fixgap.model import Episode, floor_met, score
from fixgap.operators import baselines, classify, encoding, features, kernel, metrics, occ, selection, table
from fixgap.params import Params
from fixgap.sources import sequence

# The worked examples.
D1 = [("A", 1), ("A", 2), ("B", 3), ("E", 4), ("A", 5), ("B", 6), ("C", 6), ("B", 7), ("D", 8), ("C", 10), ("E", 11)]
D2 = [("D", 1), ("A", 2), ("C", 3), ("E", 3), ("A", 4), ("B", 4), ("C", 5), ("D", 5), ("B", 6), ("C", 7), ("E", 7), ("C", 8), ("C", 9)]
A, B, C, D, E = range(1, 6)


def events(spark, pairs):
    rows = [(0, "ABCDE".index(s) + 1 if isinstance(s, str) else s, t) for s, t in pairs]
    return spark.createDataFrame(rows, "seq_id long, etype int, t long")


def frame(spark, rows):
    return spark.createDataFrame(rows, "row_no int, ep_id string, size int, types array<int>, gaps array<int>")


def test_occurrences_of_worked_example(spark):
    ev = events(spark, D1)
    assert {(1, 3, 6), (2, 3, 6), (5, 6, 10)} <= {(r.t1, r.t2, r.t3) for r in occ.serial_all(ev, [A, B, C]).collect()}
    got = occ.fixed(ev, occ.episodes_frame(spark, [Episode((A, B, C), (2, 3))]))
    assert sorted(r.start_t for r in got.collect()) == [1, 5]


def test_lengths_of_worked_example(spark):
    ev = events(spark, D2)
    eps = [Episode((A, B, C), (2, 1)), Episode((D, E, C), (2, 2))]
    f = occ.episodes_frame(spark, eps)
    occs = occ.fixed(ev, f)
    multi = encoding.encode(f.withColumn("row_no", F.when(F.col("ep_id") == eps[0].key, 1).otherwise(2)), occs)
    rest = ev.select("etype", "t").join(occ.covered(occs, f).select("etype", "t"), ["etype", "t"], "left_anti")
    enc = multi.unionByName(encoding.trivial(rest).withColumn("row_no", F.lit(3)))
    rows = {r.row_no: r for r in enc.collect()}
    assert [rows[i].starts for i in (1, 2, 3)] == [[2, 4], [1, 5], [3, 8]]
    assert encoding.units(enc).first().total_units == 23 and encoding.trivial_units(ev).first().trivial_units == 28
    assert encoding.bits(enc, 5).first().total_bits == 71 + 5 and encoding.bits(encoding.trivial(ev), 5).first().total_bits == 96 + 5
    assert encoding.bits(enc, 5, "delta").first().total_bits < 76
    assert encoding.lost_or_added(ev, enc).count() == 0
    back = encoding.from_stream(encoding.to_stream(enc))
    assert sorted(map(str, back.collect())) == sorted(map(str, enc.select(*back.columns).collect()))
    assert table.overlap_matrix(occs, f).first().shared == 1
    assert encoding.decode(enc).count() == 13 and encoding.per_event_time_units(enc).first()[0] == (6 + 1 + 6) * 2 + (2 + 1 + 2)


def test_bits_and_thresholds(spark):
    row = spark.range(1).select(*[elias_bits(F.lit(n)) for n in (1, 2, 3, 4, 7, 8)], *[type_bits(F.lit(n)) for n in (1, 5, 16, 64)], *[min_useful_freq(F.lit(n)) for n in (2, 3, 4, 5, 6)]).first()
    assert list(row) == [1, 3, 3, 5, 5, 7, 1, 3, 5, 7, 6, 4, 4, 3, 3]
    assert not floor_met(1, 5, 5, 5) and floor_met(1, 5, 4, 5) and floor_met(1, 6, 5, 5) and not floor_met(3, 3, 5, 5)


@pytest.mark.parametrize("bad", [((1, 1), (1,)), ((1, 2), (0,)), ((1, 2), ())])
def test_episodes_are_checked(bad):
    with pytest.raises(ValueError):
        Episode(*bad)


def _total(picks, left):
    return sum(2 * p.episode.size + len(p.episode.starts) + 1 for p in picks) + len(left) + 3 * len(set(left.e.tolist()))


def _arrays(pairs):
    return np.array([t for _, t in pairs]), np.array([e for e, _ in pairs])


def test_planted_cases():
    pl1 = [(e, 10 * k + o) for k in range(1, 7) for e, o in ((A, 0), (B, 2), (C, 3))]
    picks, left, _ = kernel.select(*_arrays(pl1), Params())
    assert [(p.episode.types, p.episode.gaps, p.score) for p in picks] == [((A, B, C), (2, 1), 5)] and _total(picks, left) == 13
    picks, left, trace = kernel.select(*_arrays(pl1), Params(fth=0.2), "two_phase")
    assert _total(picks, left) == 13 and trace[0][1] == 4
    pl2 = [(e, 10 * k + o) for k in range(1, 11) for e, o in ((A, 0), (B, 1), (C, 2)) if e != C or k <= 4]
    sizes = {}
    for rule in ("score_improves", "frequency_floor"):
        picks, left, _ = kernel.select(*_arrays(pl2), Params(stop_rule=rule))
        assert _total(picks, left) == 22
        sizes[rule] = [p.episode.size for p in picks]
    assert sizes == {"score_improves": [2], "frequency_floor": [3, 2]}
    d2 = [("ABCDE".index(s), t) for s, t in D2]
    assert _total(*kernel.select(*_arrays(d2), Params())[:2]) == 28


def _random(rng, n=40, m=4, span=30):
    return sorted({(rng.randrange(1, m + 1), rng.randrange(1, span)) for _ in range(n)}, key=lambda x: (x[1], x[0]))


def test_mining_against_brute_force():
    rng = random.Random(1)
    for _ in range(15):
        ev = _random(rng)
        k = kernel.Events(*_arrays(ev))
        got = {(c.types, c.gaps): sorted(c.starts.tolist()) for c in kernel.frequent(k, Params(tg=3, fth=3 / len(ev), max_size=4), len(ev))}
        assert got == {k: v for k, v in brute.frequent(ev, 3, 3).items()}


def test_overlap_and_greedy_against_brute_force():
    rng = random.Random(2)
    for _ in range(25):
        ev = _random(rng, 60, 4, 30)
        k = kernel.Events(*_arrays(ev))
        cands = [c for c in kernel.frequent(k, Params(tg=3, fth=3 / len(ev), max_size=3), len(ev)) if c.value > 0]
        if not cands:
            continue
        om = kernel.overlaps(k, cands)
        keys = [(c.types, c.gaps) for c in cands]
        auto = brute.overlap_by_automata(ev, keys)
        for i, a in enumerate(keys):
            for j, b in enumerate(keys):
                if a < b:
                    shared = len(brute.covered(*a, cands[i].starts.tolist()) & brute.covered(*b, cands[j].starts.tolist()))
                    assert om.get(i, {}).get(j, 0) == shared == auto.get((a, b), 0)
        chosen, before = {}, brute.total(ev, {})
        for i, s in kernel.greedy(cands, om, None):
            chosen[keys[i]] = cands[i].starts.tolist()
            now = brute.total(ev, chosen)
            assert before - now >= s > 0  # a positive overlap score shortens the encoding by that much at least
            before = now
        if len(cands) <= 8:
            assert brute.best_subset(ev, {k: c.starts.tolist() for k, c in zip(keys, cands, strict=True)}) <= before


def test_properties_of_selection():
    rng = random.Random(3)
    for selector in ("path_greedy", "two_phase"):
        for _ in range(10):
            ev = _random(rng, 120, 5, 60)
            p = Params(tg=3, fth=0.03, max_size=5)
            picks, left, trace = kernel.select(*_arrays(ev), p, selector)
            assert _total(picks, left) <= len(ev) + 3 * len({e for e, _ in ev})
            seen: set = set(zip(left.e.tolist(), left.t.tolist(), strict=True))
            by_round: dict = {}
            for x in picks:
                assert len(set(x.episode.types)) == x.episode.size and all(1 <= g <= 3 for g in x.episode.gaps)
                cov = brute.covered(x.episode.types, x.episode.gaps, x.episode.starts.tolist())
                assert len(cov) == x.episode.size * len(x.episode.starts)
                by_round.setdefault(x.round, set()).update(cov)
            rounds = list(by_round.values())
            assert all(not a & b for i, a in enumerate(rounds) for b in rounds[:i])
            assert seen | set().union(*rounds) == set(ev) if rounds else seen == set(ev)
            assert len({(x.episode.types, x.episode.gaps) for x in picks}) == len(picks)
            limited = kernel.select(*_arrays(ev), p.but(k=2), selector)[0]
            assert [(x.episode.types, x.episode.gaps) for x in limited] == [(x.episode.types, x.episode.gaps) for x in picks][: len(limited)] and len(limited) <= 2


@pytest.mark.parametrize("selector,block", [("path_greedy", 1 << 16), ("path_greedy", 200), ("two_phase", 300)])
def test_table_engine_equals_kernel(spark, selector, block):
    rng = random.Random(4)
    pairs = {(e, 20 * k + o + rng.randrange(2)) for k in range(1, 40) for e, o in ((A, 0), (B, 3), (C, 5), (D, 9))} | set(_random(rng, 60, 5, 800))
    ev = events(spark, sorted(pairs))
    p = Params(tg=4, fth=0.05, block_ticks=block, max_size=4)
    a = selection.select(ev, p.but(engine="kernel"), selector).orderBy("row_no").collect()
    b = selection.select(ev, p.but(engine="table"), selector).orderBy("row_no").collect()
    assert a == b and any(r.rank for r in a)


# events, trivial units, then total units and episodes by the prose rule and by the frequency floor
def test_long_episodes_in_the_table_engine(spark):
    """Episodes of more nodes than a layout was laid for: blocks are laid anew, and both engines give them all."""
    pairs = [(e, 60 * k + e) for k in range(7) for e in range(1, 13)]
    ev = spark.createDataFrame([(e, t) for e, t in pairs], "etype int, t long")
    p = Params(tg=1, fth=0.02, block_ticks=16)
    picks, left, _ = kernel.select(*_arrays(pairs), p)
    got, _, rest, _ = table.select(ev, p, nodes=3)
    assert [(x.rank, x.score, x.episode.types, x.episode.gaps) for x in picks] == [(r, s, e.types, e.gaps) for _, r, s, e in got] and got[0][3].size == 12
    assert rest.count() == len(left)
    rows = baselines.frequent_all(ev, p, nodes=4).collect()
    k = kernel.Events(*_arrays(pairs))
    assert {(tuple(r.types), tuple(r.gaps), r.freq) for r in rows} == {(c.types, c.gaps, len(c.starts)) for c in kernel.frequent(k, p, len(k))}
    assert [r.size for r in baselines.maximal(spark.createDataFrame(rows)).collect()] == [12]


@pytest.mark.parametrize("pool", [1, 3, 1000])
def test_lazy_choice_equals_the_whole_one(spark, pool):
    rng = random.Random(9)
    pairs = {(e, 20 * k + o + rng.randrange(2)) for k in range(1, 40) for e, o in ((A, 0), (B, 3), (C, 5), (D, 9))} | set(_random(rng, 60, 5, 800))
    k = kernel.Events(*_arrays(sorted(pairs)))
    cands = [c for c in kernel.frequent(k, Params(tg=4, fth=0.05, max_size=4), len(k)) if c.value > 0]
    want = [(Episode(cands[i].types, cands[i].gaps).key, s) for i, s in kernel.greedy(cands, kernel.overlaps(k, cands), None)]
    rows = [(*Episode(c.types, c.gaps).row()[:4], len(c.starts)) for c in cands]
    useful = spark.createDataFrame(rows, "ep_id string, size int, types array<int>, gaps array<int>, freq long")
    occs = spark.createDataFrame([(r[0], int(x)) for r, c in zip(rows, cands, strict=True) for x in c.starts], "ep_id string, start_t long")
    got, _ = table.choose(useful, occs, None, Params(tg=4), pool)
    assert [(e.key, s) for e, s in got] == want and len(want) > 2


def test_large_classes_go_through_the_table_engine(spark):
    rows = [(c, e, 20 * k + o) for c in ("x", "y") for k in range(1, 12 if c == "x" else 30) for e, o in ((A, 0), (B, 2), (C, 5))]
    ev = spark.createDataFrame(rows, "label string, etype int, t long")
    a = selection.select_groups(ev, Params(), by="label").orderBy("cls", "row_no").collect()
    b = selection.select_groups(ev, Params(kernel_events=50), by="label").select(*a[0].asDict()).orderBy("cls", "row_no").collect()
    assert a == b and {r.cls for r in a if r["size"] == 3} == {"x", "y"}
    one = ev.where("label = 'y'").select("etype", "t")
    assert selection.trace(one, Params(kernel_events=50)).collect() == selection.trace(one).collect()


def test_ranks_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(sequence, "RANK_BLOCK", 7)
    rng = random.Random(3)
    rows = sorted({(s, rng.randrange(1, 5), rng.randrange(1, 90)) for s in (0, 4) for _ in range(60)}, key=lambda r: (r[0], r[2], r[1]))
    ev = spark.createDataFrame(rows, "seq_id long, etype int, t long").repartition(3)
    want = {s: [r for r in rows if r[0] == s] for s in (0, 4)}
    assert {(r.seq_id, r.etype, r.t) for r in sequence.order_only(ev).collect()} == {(s, r[1], i) for s in want for i, r in enumerate(want[s], 1)}
    assert {(r.seq_id, r.etype, r.t) for r in sequence.chop(ev, 10).collect()} == {(s * 2**31 + i // 10, r[1], r[2]) for s in want for i, r in enumerate(want[s])}
    mixed = sequence.shuffled(ev).collect()
    assert {(r.seq_id, r.t) for r in mixed} == {(r[0], r[2]) for r in rows} and len(mixed) <= len(rows)


def test_stems_and_stop_words(spark):
    df = spark.createDataFrame([(1, "The parties linked their nodes, linking classes quickly")], "doc_id long, text string")
    got = sequence.from_text(df, stop_words=sequence.STOP_WORDS, stemmer=sequence.stem).orderBy("t").collect()
    assert [(r.sym, r.t) for r in got] == [("party", 2), ("link", 3), ("node", 5), ("link", 6), ("classe", 7), ("quick", 8)]


EXPECTED = {"two": (7021, 7081, 731, 4, 2140, 47), "three": (13035, 13137, 1712, 8, 4572, 107), "five": (27147, 27345, 2859, 13, 10611, 246)}


@pytest.mark.parametrize("topology", EXPECTED)
def test_conveyors_reach_the_expected_lengths(spark, small, topology):
    orders = sequence.table(spark, small, "orders")
    ev, alphabet = sequence.encode_alphabet(sequence.conveyor_from_orders(orders, topology))
    ev = ev.persist()
    n, trivial, prose, n_prose, listing, n_listing = EXPECTED[topology]
    t = encoding.trivial_units(ev).first()
    assert (t.n_events, t.trivial_units) == (n, trivial)
    enc = selection.select(ev).persist()
    u = encoding.units(enc).first()
    assert (u.total_units, u.n_patterns) == (prose, n_prose)
    u = encoding.units(selection.select(ev, Params(stop_rule="frequency_floor"))).first()
    assert (u.total_units, u.n_patterns) == (listing, n_listing)
    m = metrics.route_match(enc, alphabet, topology).first()
    assert m.subpath_precision == 1 and m.route_recall == 1
    assert encoding.lost_or_added(ev, enc).count() == 0


def test_path_greedy_beats_the_order_only_baselines(spark, small):
    ev, _ = sequence.encode_alphabet(sequence.conveyor_from_orders(sequence.table(spark, small, "orders"), "two"))
    rows = {r.method: r for r in api.compare(ev, ["path_greedy"]).collect()}
    chopped = sequence.order_only(sequence.chop(ev.withColumn("seq_id", F.lit(0).cast("long")), 50))
    m = ev.select("etype").distinct().count()
    for got in (baselines.gap_coding(chopped, m, patience=16), baselines.gap_coding(chopped, m, mode="candidates", patience=16), baselines.dependency_test(chopped, m)):
        assert got[0] and got[1] < got[2] and rows["path_greedy"].ratio_bits > 2 * got[2] / got[1]
    one = sequence.order_only(ev.withColumn("seq_id", F.lit(0).cast("long")))
    patterns, bits, base = baselines.dependency_test(one, m)
    assert patterns == [] and bits == base  # a single sequence has a single pair, so no test passes


def test_closed_and_maximal(spark):
    rows = [("1+1>2", 2, [1, 2], [1], 5), ("2+1>3", 2, [2, 3], [1], 5), ("1+2>3", 2, [1, 3], [2], 4), ("1+1>2+1>3", 3, [1, 2, 3], [1, 1], 4)]
    c = spark.createDataFrame(rows, "ep_id string, size int, types array<int>, gaps array<int>, freq long")
    assert {r.ep_id for r in baselines.closed(c).collect()} == {"1+1>2", "2+1>3", "1+1>2+1>3"}
    assert {r.ep_id for r in baselines.maximal(c).collect()} == {"1+1>2+1>3"}


def test_order_only_loses_order_that_gaps_keep(spark):
    ev = events(spark, [("A", 1), ("B", 2), ("C", 3), ("D", 4)])
    enc = frame(spark, [(1, "x", 2, [A, C], [2]), (2, "y", 2, [B, D], [2])]).withColumn("n_occ", F.lit(1).cast("long")).withColumn("starts", F.array(F.col("row_no").cast("long")))
    assert [r.etype for r in encoding.decode(enc).orderBy("t").collect()] == [A, B, C, D]
    ranks = sequence.order_only(ev).orderBy("t").collect()
    assert [r.t for r in ranks] == [1, 2, 3, 4]


def test_order_only_counts_against_queues(spark):
    rng = random.Random(5)
    lines = {s: sorted({(rng.randrange(1, 15), rng.randrange(1, 5)) for _ in range(rng.randrange(1, 18))}) for s in range(60)}
    ev = spark.createDataFrame([(s, e, t) for s, line in lines.items() for t, e in line], "seq_id long, etype int, t long")
    pats = [(1, 2), (1, 2, 3), (3, 1, 2, 4)]
    eps = spark.createDataFrame([(str(p), len(p), list(p)) for p in pats], "ep_id string, size int, types array<int>")
    got = {(r.ep_id, r.seq_id): r.n for r in occ.serial_distinct(ev, eps).collect() if r.n}
    assert got == {(str(p), s): n for p in pats for s, line in lines.items() if (n := brute.fifo(line, list(p)))}
    one = {(r.ep_id, r.seq_id): r.n for r in occ.serial_non_overlapped(ev, eps).collect()}
    assert all(n <= got[k] for k, n in one.items())


def test_frozen_model_on_new_events(spark, small):
    ev, _ = sequence.encode_alphabet(sequence.conveyor_from_orders(sequence.table(spark, small, "orders"), "two"))
    model = api.select(ev.where("t < 20000"))
    new = ev.where("t >= 20000").persist()
    enc = model.encode(new)
    assert encoding.lost_or_added(new, enc).count() == 0
    assert encoding.units(enc).first().total_units < encoding.trivial_units(new).first().trivial_units
    assert model.lengths().first().ratio > 4 and model.ratio("bits") > 3


def test_adapters(spark):
    df = spark.createDataFrame([(1, "a", 5), (1, "b", 9), (2, "a", 3), (7, "c", 4)], "seq_id long, sym string, t long")
    line = sorted((r.t, r.sym) for r in sequence.concat(df, 5, bucket=2).collect())
    assert line == [(1, "a"), (5, "b"), (11, "a"), (17, "c")]
    iv = sequence.split_intervals(spark.createDataFrame([(1, "x", 2, 7)], "seq_id long, sym string, t1 long, t2 long")).collect()
    assert {(r.sym, r.t) for r in iv} == {("x/start", 2), ("x/end", 7)}
    ev, alphabet = sequence.encode_alphabet(df)
    assert [(r.etype, r.symbol, r.n) for r in alphabet.orderBy("etype").collect()] == [(1, "a", 2), (2, "b", 1), (3, "c", 1)]
    with pytest.raises(Exception, match="start at 1"):
        sequence.normalise(spark.createDataFrame([(1, 1, 0)], "seq_id long, etype int, t long")).collect()
    assert sequence.normalise(spark.createDataFrame([(1, 1, 2), (1, 1, 2), (1, None, 3)], "seq_id long, etype int, t long")).count() == 1


@pytest.mark.parametrize("pairs", [[], [(1, 5)], [(1, t) for t in range(1, 9)], [(e, 4) for e in range(1, 6)]])
def test_degenerate_sequences(spark, pairs):
    ev = spark.createDataFrame([(0, e, t) for e, t in pairs], "seq_id long, etype int, t long")
    for engine in ("kernel", "table"):
        enc = selection.select(ev, Params(engine=engine))
        assert encoding.decode(enc).count() == len(pairs) and enc.where("size > 1").count() == 0


def test_class_features_and_svm(spark):
    rng = random.Random(6)
    rows, labels = [], []
    for s in range(60):
        label = "p" if s % 2 else "q"
        labels.append((s, label))
        for k in range(5):
            t = 20 * k + rng.randrange(1, 5)
            rows += [(s, A, t), (s, B, t + (2 if label == "p" else 3))]
    ev, lab = spark.createDataFrame(rows, "seq_id long, etype int, t long"), spark.createDataFrame(labels, "seq_id long, label string")
    eps = features.select_per_class(ev, lab, Params()).persist()
    assert {r.ep_id for r in eps.collect()} == {"1+2>2", "1+3>2"}
    vec = features.assemble(features.fixed_gap(ev, eps).unionByName(features.singletons(ev)), lab)
    assert classify.accuracy(classify.linear_svm(vec, vec)).first()[0] == 100
    assert features.order_only(ev, eps).agg(F.min("n")).first()[0] == 5
    got = classify.repeated_cv(lambda train: vec, lab, folds=2, reps=1)
    assert got[0][1] == 100


def test_expressions(spark):
    r = spark.createDataFrame([([1, 2, 3], [4, 5]), ([7], [])], "types array<int>, gaps array<int>").select(episode_key(F.col("types"), F.col("gaps")), offsets(F.col("gaps"))).collect()
    assert [tuple(x) for x in r] == [("1+4>2+5>3", [0, 4, 9]), ("7", [0])]
    assert score(2, 6) == 1 and score(2, 5) == 0


def test_later_rounds_of_a_large_line_go_to_the_kernel(spark, small):
    """Above kernel_events the first round is the table engine's; what it leaves is solved in one task, with equal results."""
    ev = sequence.encode_alphabet(sequence.conveyor_from_orders(sequence.table(spark, small, "orders"), "two"))[0].select("etype", "t").localCheckpoint()
    p = Params(kernel_events=5000)
    assert table.rounds(ev, p, "path_greedy", until=5000)[4] == (1, ev.count())
    got, want = (sorted(map(str, selection.select(ev, x).collect())) for x in (p, p.but(engine="kernel")))
    assert got == want
