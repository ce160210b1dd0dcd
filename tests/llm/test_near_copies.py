"""The pipeline's near-copy stage against brute-force shingle similarity."""

import random
from collections import Counter, defaultdict
from itertools import combinations

import corpus_pipeline
import pytest

from fixgap.llm import near_copies, simhash
from fixgap.llm.base import table

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def _sets(texts):
    out = {}
    for d, t in texts:
        w = (t or "").encode().lower().split()
        out[d] = frozenset(zip(*(w[i:] for i in range(5)), strict=False)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])
    return out


def _pairs(sets):
    """Pairs at 0.8 or more; those without a word are copies of one another."""
    where, both = defaultdict(list), Counter()
    for d, s in sets.items():
        for g in s or [()]:
            where[g].append(d)
    for some in where.values():
        both.update(combinations(some, 2))
    return [(a, b) for (a, b), k in both.items() if 5 * k >= 4 * (max(len(sets[a]), 1) + max(len(sets[b]), 1) - k)]


def _components(sets):
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in _pairs(sets):
        parent[max(find(a), find(b))] = min(find(a), find(b))
    return {d: find(d) for d in sets}


def test_stage_drops_every_near_copy(spark, small):
    docs = table(spark, small, "documents")
    want = _components(_sets((r.doc_id, r.text) for r in docs.collect()))
    kept = [r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, small).select("doc_id").collect()]
    assert sorted(kept) == sorted(set(want.values()))


@pytest.mark.parametrize("few,leaders", [(2, 1), (16, 4)])
def test_groups_against_brute_force(spark, few, leaders):
    """Groups whose copies differ from their base, and from one another, on both sides of the bound."""
    rng = random.Random(6)
    texts = []
    for _ in range(4):
        base = [f"w{rng.randrange(3000)}" for _ in range(rng.randrange(60, 300))]
        for _ in range(30):
            w = list(base)
            for _ in range(rng.randrange(1 + len(w) // 25)):
                w[rng.randrange(len(w))] = f"w{rng.randrange(3000)}"
            texts.append(" ".join(w))
    texts += ["a b", "a B", "", None, "a b c"]
    got = near_copies.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4), few, leaders)
    want = _components(_sets(enumerate(texts)))
    assert {r.doc_id: r.component_id for r in got.collect()} == want and len(set(want.values())) > 4


def test_recall_of_candidates_at_the_bound():
    rng = random.Random(7)
    found = total = 0
    while total < 400:
        w = [f"w{rng.randrange(5000)}" for _ in range(rng.randrange(60, 400))]
        v = list(w)
        for _ in range(max(1, len(w) // 46)):
            v[rng.randrange(len(v))] = "changed"
        a, b = (near_copies.shingles(" ".join(x).encode()) for x in (w, v))
        both = len(set(a.tolist()) & set(b.tolist()))
        if 0.8 <= both / (len(a) + len(b) - both) < 0.84:
            found, total = found + bool(set(near_copies.bands(a).tolist()) & set(near_copies.bands(b).tolist())), total + 1
    assert found / total >= 0.99


def test_odd_rows(spark, odd_docs, empty_docs, clashing):
    assert near_copies.keep_one(empty_docs).collect() == []
    for docs in (odd_docs, clashing):
        out = near_copies.keep_one(docs)
        assert out.columns == docs.columns and Counter(r.text for r in out.collect())["same text twice"] == 1
    nulls = spark.createDataFrame([(None, f"{'a b c d e f g h i j k l m n o p ' * 3}{x}", "en", "s", 9) for x in ("q r", "q r")] + [(None, "other", "en", "s", 5)], DOCS)
    assert near_copies.keep_one(nulls).count() == 2


def test_fingerprints_link_what_shingles_do_not(spark):
    """Fingerprints at three bits or fewer make near copies, whatever the five-word shingles say."""
    rng = random.Random(11)
    while True:  # changed words apart from one another cost five-word shingles most
        w = [f"w{rng.randrange(5000)}" for _ in range(400)]
        v = list(w)
        for i in range(0, 400, 21):
            v[i] = "changed"
        a, b = " ".join(w), " ".join(v)
        if (simhash.fingerprint(a.encode()) ^ simhash.fingerprint(b.encode())).bit_count() <= 3:
            break
    sets = _sets([(5, a), (9, b)])
    assert not _pairs(sets)
    rows = [(d, t, "en", "s", len(t)) for d, t in ((9, b), (5, a), (7, "another text of more than five words"))]
    kept = corpus_pipeline.drop_near_copies(spark, spark.createDataFrame(rows, DOCS), "")
    assert sorted(r.doc_id for r in kept.collect()) == [5, 7]


def test_large_groups_make_no_rows_of_pairs(spark, monkeypatch):
    """Copies that are mostly too far from one another: the work is in cells, and rows stay in proportion to the sets."""
    rng = random.Random(12)
    base = [f"w{rng.randrange(3000)}" for _ in range(140)]
    texts = []
    for _ in range(300):
        w = list(base)
        for _ in range(rng.randrange(2, 6)):
            w[rng.randrange(len(w))] = f"w{rng.randrange(3000)}"
        texts.append(" ".join(w))
    counted, similar = [], near_copies._similar

    def spy(pairs, sets):
        counted.append(pairs.count())
        return similar(pairs, sets)

    monkeypatch.setattr(near_copies, "_similar", spy)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    want = _components(_sets(enumerate(texts)))
    assert {r.doc_id: r.component_id for r in near_copies.near_duplicates(docs).collect()} == want and 2 < len(set(want.values())) < 290
    assert sum(counted) <= 20 * len(texts), counted


def test_cells_of_few_sets(spark):
    """Cells that hold parts of a group find what one cell finds."""
    rng = random.Random(13)
    base = [f"w{rng.randrange(3000)}" for _ in range(200)]
    texts = []
    for _ in range(40):
        w = list(base)
        for _ in range(rng.randrange(3, 9)):
            w[rng.randrange(len(w))] = f"w{rng.randrange(3000)}"
        texts.append(" ".join(w))
    got = near_copies.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), 2, 1, side=9)
    want = _components(_sets(enumerate(texts)))
    assert {r.doc_id: r.component_id for r in got.collect()} == want and 2 < len(set(want.values())) < 40
