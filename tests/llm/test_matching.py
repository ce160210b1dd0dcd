"""Near duplicates, decontamination, repeated strings and personal data against brute force."""

import hashlib
import random
import re
from collections import Counter
from itertools import combinations

import numpy as np
import xxhash

from fixgap.llm import bwt, components, decontaminate, pii, repeats, simhash
from fixgap.llm.base import table


def test_masks_cover_every_small_difference():
    for positions, radius in ((list(range(20)), 3), (list(range(64)), 2), ([1, 5, 9, 60], 3)):
        masks = simhash.covering_masks(positions, radius)
        for some in combinations(positions, min(radius, len(positions))):
            diff = sum(1 << p for p in some)
            assert any(not m & diff for m in masks)


def test_fingerprint_by_definition():
    def brute(text):
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text))
        if not w:
            return 0
        hs = [xxhash.xxh64_intdigest(" ".join(w[i : i + 3]).encode(), 42) for i in range(len(w) - 2)] or [xxhash.xxh64_intdigest(" ".join(w).encode(), 42)]
        return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hs) * 2 > len(hs))

    for text in ("", "A b", "One two\tThree\x0bFOUR five", "É é x y z É é x y z", "a b c " * 50):
        assert simhash.fingerprint(text.encode()) == brute(text)


def _roots(fps, radius):
    parent = {f: f for f in fps}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in combinations(fps, 2):
        if (a ^ b).bit_count() <= radius:
            parent[find(a)] = find(b)
    return {f: find(f) for f in fps}


def test_links_connect_what_brute_force_connects(spark):
    rng = random.Random(2)
    fps = set()
    for _ in range(6):
        base = rng.getrandbits(64)
        for _ in range(40):
            base ^= sum(1 << b for b in rng.sample(range(64), rng.randrange(1, 5)))
            fps.add(base)
    want = _roots(sorted(fps), 3)
    signed = {f: f - (1 << 64) if f >> 63 else f for f in fps}
    df = spark.createDataFrame([(v,) for v in signed.values()], "fp long")
    for bucket in (24, 1024):
        roots = {r.node: r.root for r in components.connected(simhash.links(df, bucket=bucket)).collect()}
        for a, b in combinations(sorted(fps), 2):
            same = a == b or (signed[a] in roots and roots.get(signed[a]) == roots.get(signed[b]))
            assert same == (want[a] == want[b])


def test_components_of_a_long_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(200)] + [(500, 500), (900, 901)], "a long, b long")
    got = {r.node: r.root for r in components.connected(edges).collect()}
    assert all(got[i] == 0 for i in range(201)) and got[901] == 900 and 500 not in got


def _repeats_brute(texts, n):
    count = Counter(t[i : i + n] for t in texts for i in range(len(t) - n + 1))
    out = []
    for t in texts:
        gone = np.zeros(len(t), bool)
        for i in range(len(t) - n + 1):
            if count[t[i : i + n]] > 1:
                gone[i : i + n] = True
        kept = bytes(np.frombuffer(t, np.uint8)[~gone])
        out.append((len(t), int(gone.sum()), int((gone & ~np.concatenate([[False], gone[:-1]])).sum()) if len(t) else 0, hashlib.sha256(kept).hexdigest()))
    return out


def test_bwt_windows_against_counting():
    rng = random.Random(1)
    for _ in range(120):
        strings = [bytes(rng.choice(b"ab") for _ in range(rng.randrange(60))) for _ in range(rng.randrange(1, 12))]
        n, step = rng.choice([(12, 3), (12, 12), (8, 2), (20, 5), (6, 1)])
        count = Counter(s[i : i + n] for s in strings for i in range(len(s) - n + 1))
        for s, hit in zip(strings, bwt.repeated_windows(strings, n, step, rng.choice([30, 100, 10**6])), strict=True):
            assert hit.tolist() == [count[s[i : i + n]] > 1 for i in range(len(s) - n + 1)]


def test_repeats_against_counting(spark):
    rng = random.Random(3)
    para = lambda n: " ".join("".join(rng.choice("abcd") for _ in range(rng.randrange(1, 5))) for _ in range(n))
    shared = [para(12) for _ in range(6)]
    texts = [None, "", "x", "a" * 60, "é" * 40] + [para(rng.randrange(1, 40)) + (rng.choice(shared) if rng.random() < 0.5 else "") for _ in range(100)]
    texts += texts[10:40] + [t[: rng.randrange(len(t))] + "Q" + t[5:] for t in texts[10:60]]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    for n, gram, step, bucket, often in ((20, 5, 5, 1 << 20, 256), (24, 7, 12, 300, 256), (20, 4, 20, 60, 2), (20, 5, 5, 1 << 20, 4), (24, 7, 12, 300, 1)):
        got = [tuple(r)[1:] for r in repeats.remove(docs, length=n, gram=gram, step=step, bucket_bytes=bucket, sample=1.0, often=often).orderBy("doc_id").collect()]
        assert got == _repeats_brute([(t or "").encode() for t in texts], n)


def test_a_passage_of_every_text_is_dealt_out(spark):
    """One passage in all texts, alone, whole or cut: rows of its anchors don't meet in one window group, and results stay exact."""
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdef") for _ in range(6))
    passage = " ".join(word() for _ in range(12))
    texts = [word() + passage[: rng.choice([40, 84, 84])] + word() for _ in range(300)] + [passage] * 60
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    hot = repeats.frequent(docs, 24, 7, 1.0, 50)
    assert len(hot[0]) and hot[1].min() >= 50
    rows = repeats.keyed(docs).mapInArrow(repeats._scan(24, 7, hot), repeats.ROWS).toPandas()
    assert rows.groupby(["fp", "deal", "ctx"]).size().max() <= 6  # two a task
    got = [tuple(r)[1:] for r in repeats.remove(docs, length=24, gram=7, step=12, sample=1.0, often=50).orderBy("doc_id").collect()]
    assert got == _repeats_brute([t.encode() for t in texts], 24)


def test_repeats_in_pieces(spark, monkeypatch):
    monkeypatch.setattr(repeats, "PIECE", 64)
    rng = random.Random(9)
    a = "".join(rng.choice("ab") for _ in range(400))
    texts = [a, a[100:300] + "z", "b" * 30 + a[250:]]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1)
    rows = [tuple(r)[1:] for r in repeats.remove(docs, length=24, gram=6, step=12).orderBy("doc_id").collect()]
    assert rows == _repeats_brute([t.encode() for t in texts], 24)


def test_repeats_whole_table(spark, small):
    docs = table(spark, small, "documents")
    got = [tuple(r)[1:] for r in repeats.remove(docs).orderBy("doc_id").collect()]
    assert got == _repeats_brute([(r.text or "").encode() for r in docs.orderBy("doc_id").collect()], 200)


def test_best_stretch_against_levenshtein():
    def lev(a, c):
        p = list(range(len(c) + 1))
        for i, x in enumerate(a):
            q = [i + 1]
            for j, y in enumerate(c):
                q.append(min(p[j] + (x != y), p[j + 1] + 1, q[j] + 1))
            p = q
        return p[-1]

    rng = random.Random(4)
    for _ in range(150):
        a = np.array([rng.randrange(3) for _ in range(rng.randrange(1, 6))])
        c = np.array([rng.randrange(3) for _ in range(rng.randrange(9))], np.int64)
        cost, s, e = decontaminate.best_stretch(a, c)
        assert cost == min(lev(a, c[i:j]) for i in range(len(c) + 1) for j in range(i, len(c) + 1)) == lev(a, c[s:e])


def test_leaks_with_edits_are_found(spark, small):
    rng = random.Random(1)
    bench = [(r.item_id, r.text) for r in table(spark, small, "benchmark").collect()]
    items = decontaminate.Items([(i, decontaminate.words_of(t)) for i, t in bench])
    vocab = sorted({w for _, t in bench for w in decontaminate.words_of(t)})
    filler = [decontaminate.words_of(r.text) for r in table(spark, small, "documents").limit(30).collect()]
    found = total = 0
    for item_id, text in bench * 4:
        w = decontaminate.words_of(text)
        for _ in range(decontaminate.allowed(len(w))):
            p, kind = rng.randrange(len(w)), rng.randrange(3)
            w[p : p + 1] = [[rng.choice(vocab)], [w[p], rng.choice(vocab)], []][kind]
        around = rng.choice(filler)
        cut = rng.randrange(len(around) + 1)
        got = [m for m in items.matches([around[:cut] + w + around[cut:]]) if m[1] == item_id]
        brute = decontaminate.best_stretch(items.items[items.ids.index(item_id)], np.array([items.vocab.get(x, 0) for x in around[:cut] + w + around[cut:]]))[0]
        assert all(m[4] == brute for m in got)
        found, total = found + bool(got), total + 1
    assert found / total >= 0.95


def test_short_items_match_whole(spark, rng):
    """Items of one to four words: found where the same words stand in a row, the first place, and no edits; no document goes for them."""
    vocab = ["a", "b", "c", "d"]
    bench = [(i, " ".join(rng.choice(vocab) for _ in range(rng.randrange(1, 5)))) for i in range(25)] + [(90, "!!"), (91, None), (92, "b a"), (92, "b a"), (93, "a b c d d c b a")]
    docs = [(i, " ".join(rng.choice([*vocab, "x"]) for _ in range(rng.randrange(12)))) for i in range(80)] + [(200, None), (201, "a"), (201, "B, A")]
    want = []
    for d, t in docs:
        ws = decontaminate.words_of(t)
        for i, item in bench:
            w = decontaminate.words_of(item)
            at = [k for k in range(len(ws) - len(w) + 1) if ws[k : k + len(w)] == w] if 0 < len(w) < decontaminate.MIN_WORDS else []
            want += [(d, i, at[0], len(w), 0, 1.0)] if at else []
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(bench, "item_id long, text string")
    assert sorted(tuple(r) for r in decontaminate.find(d, b.where("item_id != 93 OR item_id IS NULL")).collect()) == sorted(want)
    assert {tuple(r) for r in decontaminate.find(d, b).collect()} >= set(want)
    assert decontaminate.clean(d, b.where("item_id != 93")).count() == len(docs)


def test_decontamination_by_brute_force(spark, small):
    docs, bench = table(spark, small, "documents"), table(spark, small, "benchmark")
    got = {(r.doc_id, r.item_id) for r in decontaminate.find(docs, bench).collect()}
    exact = {(d.doc_id, b.item_id) for d in docs.collect() for b in bench.collect() if b.text in d.text}
    assert exact <= got
    kept = {r.doc_id for r in decontaminate.clean(docs, bench).collect()}
    assert kept == {r.doc_id for r in docs.collect()} - {d for d, _ in got}


EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")


def test_fast_patterns_match_plain_ones():
    rng = random.Random(6)
    for _ in range(5000):
        s = "".join(rng.choice("ab1.2@-+% ()3") for _ in range(rng.randrange(30)))
        assert [m.span() for m in EMAIL.finditer(s)] == list(pii.emails(s))
        assert [m.span() for m in IP.finditer(s)] == [m.span() for m in pii.IP.finditer(s)]
    assert not list(pii.emails("a" * 100_000 + "@"))


def test_tagger_gradients():
    t = pii.Tagger()
    rng = np.random.default_rng(0)
    codes, tags = rng.integers(0, pii.CLASSES, (3, 7)), rng.integers(0, pii.TAGS, (3, 7))
    _, g = t.step(codes, tags)
    for k in t.p:
        at = (int(codes[0, 0]), 3) if k == "emb" else tuple(int(rng.integers(0, s)) for s in t.p[k].shape)
        old = t.p[k][at]
        t.p[k][at] = old + 1e-2
        a, _ = t.step(codes, tags)
        t.p[k][at] = old - 1e-2
        b, _ = t.step(codes, tags)
        t.p[k][at] = old
        assert abs((a - b) / 2e-2 - g[k][at]) < 2e-3


PLAIN = {"email": EMAIL, "ip": IP, "card": re.compile(r"[0-9]([\x20-]?[0-9])+"), "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")}


def _plain_spans(text):
    """Base spans by the patterns as they are stated."""
    out = []
    for k, (kind, pattern) in enumerate(PLAIN.items()):
        for m in pattern.finditer(text):
            digits = [int(c) for c in m[0] if c in "0123456789"]
            luhn = sum(sum(divmod(d * (1 + i % 2), 10)) for i, d in enumerate(reversed(digits))) % 10 == 0
            if {"email": True, "ip": kind == "ip" and all(int(p) <= 255 for p in m[0].split(".")), "card": 12 <= len(digits) <= 19 and luhn, "phone": 9 <= len(digits) <= 15}[kind]:
                out.append((m.start(), k, m.end()))
    return sorted(out)


def test_base_columns_by_brute_force(spark):
    rng = random.Random(12)
    texts = [r.text for r in table(spark, "/root/testdata/sf0.01", "documents").collect()]
    alphabet = [*"0123456789", ".", " ", "-", "+", "@", "(", "ab", "c.d", "é"]
    texts += ["".join(rng.choice(alphabet) for _ in range(rng.randrange(60))) for _ in range(3000)]
    texts += ["0000000010.0.0.1", "1.2.3.256", "000.000.000.0000", "4111 1111 1111 1111", "+1 (202) 555-0143", "0" * 4000 + "1.2.3.4"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    for r in pii.find(docs, None).collect():
        want = _plain_spans(texts[r.doc_id] or "")
        said = ",".join(f"{list(PLAIN)[k]}:{a}:{b}" for a, k, b in want)
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == i for _, k, _ in want) for i in range(4)]
        assert r.base_sha256 == hashlib.sha256(said.encode()).hexdigest() and r.spans == said and (r.n_added, r.n_spans) == (0, len(want))


def test_rewritten_forms_are_added(spark):
    """On documents outside the sample: spans rewritten in place are found again, and base spans stay."""
    docs = table(spark, "/root/testdata/sf0.1", "documents")
    tagger = pii.train(docs.where("doc_id % 3 != 0"))
    texts = [r.text for r in docs.where("doc_id % 3 = 0").select("text").collect() if r.text]
    rng = np.random.default_rng(1)
    found, total = Counter(), Counter()
    for text in texts:
        for a, k, b in pii.base_spans(text):
            new = pii.rewritten(k, text[a:b], rng)
            part = text[max(0, a - 150) : a] + new + text[b : b + 150]
            at = min(a, 150)
            base = pii.base_spans(part)
            if any(x < at + len(new) and at < y for x, _, y in base) or not pii.added_valid(pii.KINDS[k], new):
                continue
            total[k] += 1
            found[k] += (at, k, at + len(new)) in tagger.spans(part, base)
    assert total and sum(found.values()) >= 0.9 * sum(total.values()), (found, total)
    for r in pii.find(docs.limit(200), tagger).collect():
        assert r.n_spans >= r.n_email + r.n_ip + r.n_card + r.n_phone
    assert pii.redacted("no data here at all", tagger) == "no data here at all"
    assert pii.redacted("ip 46.139.188.94.", None) == "ip <IP>."


def test_parts_and_margins_change_nothing(rng, monkeypatch):
    tagger = pii.Tagger(seed=1)
    text = "".join(rng.choice("abc d1@.") for _ in range(3000))
    codes, anchors = pii.classes(text), np.arange(3000)
    (start, whole), = tagger.stretches(codes, anchors)
    monkeypatch.setattr(pii, "PART", 7)
    (again, parts), = tagger.stretches(codes, anchors)
    assert start == again == 0 and len(whole) == 3000 and (whole == parts).all()
    text = "".join(rng.choice("abc d") for _ in range(400)) + " 12 " + "".join(rng.choice("abc d") for _ in range(400))
    (at, few), = tagger.stretches(pii.classes(text), np.array([401, 402]))
    assert at <= 401 - pii.STRIDE and at + len(few) >= 402 + pii.STRIDE


def test_merge_gives_common_prefixes():
    """Common prefixes of neighbouring suffixes in merged order, against the texts."""
    rng = random.Random(5)
    for step in (1, 2):
        strings = ["".join(rng.choice("ab") for _ in range(rng.randrange(2, 40))).encode() for _ in range(12)]
        shards = [bwt.Shard(strings[i : i + 3], step) for i in range(0, 12, 3)]
        source, place, common = bwt.merge(shards, 4)
        joined = [b"\0".join(strings[i : i + 3]) + b"\0" for i in range(0, 12, 3)]

        def blocks(k, p):
            s = joined[k][p:]
            s = s[: s.index(b"\0")] if b"\0" in s else s
            return [s[i : i + step] for i in range(0, len(s) - step + 1, step)]

        for i in range(1, len(place)):
            a, b = blocks(source[i - 1], place[i - 1]), blocks(source[i], place[i])
            n = next((j for j in range(4) if j >= min(len(a), len(b)) or a[j] != b[j]), 4)
            assert common[i] == n


def test_long_leaks_with_edits_are_found():
    rng = random.Random(8)
    vocab = [f"v{i}" for i in range(3000)]
    for n, times in ((41, 60), (59, 60), (150, 40), (400, 12), (1000, 5)):
        some = [[rng.choice(vocab) for _ in range(n)] for _ in range(3)]
        items = decontaminate.Items(list(enumerate(some)))
        for _ in range(times):
            i = rng.randrange(3)
            w = list(some[i])
            for _ in range(decontaminate.allowed(n)):
                p, kind = rng.randrange(len(w)), rng.randrange(3)
                w[p : p + 1] = [[rng.choice(vocab)], [w[p], rng.choice(vocab)], []][kind]
            before, after = ([rng.choice(vocab) for _ in range(rng.randrange(80))] for _ in range(2))
            text = before + w + after
            got = items.matches([["short"], text, some[i][: n // 2]])
            brute = decontaminate.best_stretch(items.items[i], np.array([items.vocab.get(x, 0) for x in text]))
            assert [(m[0], m[1], m[4]) for m in got] == [(1, i, brute[0])]
        whole = items.matches([before + some[0] + after])
        assert whole == [(0, 0, len(before), n, 0, 1.0)]
