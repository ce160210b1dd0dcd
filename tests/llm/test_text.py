"""BPE, token files, language and toxicity against the library, brute force and held-out accuracy."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from fixgap.llm import binary_ids, bpe, langid, toxicity, words
from fixgap.llm.base import table

TOK = public_tokenizers.path("word_bpe_49k.json")
PARTS = ["a", "B", "é", "É", "J̌", "é", ".", ",", "'", "s", "'S", "1", "2", " ", "\n", " ", " ", "İ", "ß", "<|endoftext|>", "<|ENDOFTEXT|>", "<|", "|>", "\t", "-", "!", "ͅ", "ǅ", "Σ", "ﬁ", "゙", "か", "\x85", "\x1f", "%"]


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(TOK)


def test_words_encode_as_the_library(library):
    rng = random.Random(4)
    table_ = words.Table(library, "<u2")
    for _ in range(1500):
        text = "".join(rng.choice(PARTS) for _ in range(rng.randrange(25)))
        assert table_.ids(table_.places(words.split(text.encode()))).tolist() == library.encode(text, add_special_tokens=False).ids, text


def test_forgetting_words_changes_nothing(library):
    small, large = words.Table(library, "<u2", room=3), words.Table(library, "<u2")
    for text in ("a b c d e f", "a b z", "b c d e", "a"):
        assert small.ids(small.places(text.encode().split())).tolist() == large.ids(large.places(text.encode().split())).tolist()


def test_bpe_and_files(spark, small, library):
    docs = table(spark, small, "documents")
    rows = {r.doc_id: r.text or "" for r in docs.collect()}
    ids = {i: library.encode(t, add_special_tokens=False).ids for i, t in rows.items()}
    for r in bpe.digests(docs, TOK).collect():
        assert r.n_tokens == len(ids[r.doc_id])
        assert r.ids_sha256 == hashlib.sha256(np.array(ids[r.doc_id], "<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(library.decode(ids[r.doc_id], skip_special_tokens=False).encode()).hexdigest()
    at = 0
    got = binary_ids.read(spark, binary_ids.write(docs, TOK)).orderBy("start").collect()
    assert [r.doc_id for r in got] == sorted(rows)
    for r in got:
        want = np.array([*ids[r.doc_id], 2], "<u4")
        assert (r.start, r.n_tokens, r.ids_crc32) == (at, len(want), zlib.crc32(want.tobytes()))
        at += len(want)


def test_many_chunks(spark, small, monkeypatch):
    docs = table(spark, small, "documents")
    one = sorted(map(tuple, bpe.digests(docs, TOK).collect()))
    monkeypatch.setattr(bpe, "CHUNK_BYTES", 30_000)
    assert sorted(map(tuple, bpe.digests(docs, TOK).collect())) == one


def test_decode_join(spark, small, library):
    docs = table(spark, small, "documents").where("doc_id < 20")
    back = {r.doc_id: r.decoded for r in bpe.decode(bpe.encode(docs, TOK), TOK).collect()}
    both = {r.doc_id: r.decoded for r in bpe.round_trip(docs, TOK).collect()}
    for r in docs.collect():
        assert back[r.doc_id] == both[r.doc_id] == library.decode(library.encode(r.text, add_special_tokens=False).ids, skip_special_tokens=False)


def test_spark_splits_as_python(spark, rng):
    al = [*"AbC.,\n \t\r\x0b\x0c1é", "É", "İ", "<|", "|>", "\u0301", "\u2028", "\x85", "\x1c", "\xa0", "ß", "x", ".", " ", "\0"]
    texts = ["".join(rng.choice(al) for _ in range(rng.randrange(25))) for _ in range(4000)]
    rows = spark.createDataFrame([(t,) for t in texts], "t string").select("t", words.split_column(F.col("t")).alias("w")).collect()
    assert all([w.encode() for w in r.w] == words.split(r.t.encode()) for r in rows)


def test_decode_keeps_repeated_rows_apart(spark, odd_docs, clashing, empty_docs, library):
    def said(t):
        return library.decode(library.encode(t or "", add_special_tokens=False).ids, skip_special_tokens=False)

    for docs in (odd_docs, clashing):
        encoded = bpe.encode(docs, TOK)
        got = sorted(str((r.doc_id, r.decoded)) for r in bpe.decode(encoded, TOK).collect())
        assert got == sorted(str((r.doc_id, said(r.text))) for r in docs.select("doc_id", "text").collect())
    assert bpe.decode(bpe.encode(empty_docs, TOK), TOK).collect() == []


def test_texts_without_letters_are_und(spark):
    model = langid.fit({"en": Counter({"word": 5}), "fr": Counter({"mot": 5})}, {"en": 3, "fr": 9}, ["w", "o", "r", "d", "m", "t"])
    docs = spark.createDataFrame([(0, "\u00bd \u00b2 5"), (1, "\u2167"), (2, "a\u00b2word"), (3, "\u0301")], "doc_id long, text string")
    assert [r.lang_pred for r in langid.predict(docs, model).orderBy("doc_id").collect()] == ["und", "und", "en", "und"]
    assert langid.words_of("x\u00b2y \u00c9t\u00e9_2a") == ["x", "y", "\u00e9t\u00e9", "a"]


def test_forward_sums_all_segmentations():
    pieces = [" a", "a", "b", "ab", " ab", "ba"]
    rng = np.random.default_rng(1)
    logp = np.log(rng.dirichlet(np.ones(len(pieces) + 1), 2).T)
    model = langid.Model(pieces, ["x", "y"], logp, np.zeros(2))
    ids = {p: i for i, p in enumerate(pieces)}

    def brute(s):
        if not s:
            return np.ones(2)
        out = np.zeros(2)
        for k in range(1, len(s) + 1):
            i = ids.get(s[:k], len(pieces) if k == 1 else None)
            if i is not None:
                out += np.exp(logp[i]) * brute(s[k:])
        return out

    for w in ("a", "ab", "abab", "zab", "bb", "a" * 40):
        if len(w) < 10:
            assert np.allclose(np.exp(model.word_scores([w])[0]), brute(" " + w))
        lattice = langid.Lattice(pieces).of([w])
        assert np.allclose(langid.forward(lattice, logp)[:, -1], model.word_scores([w]))


def test_expected_uses_sum_to_lengths():
    pieces = [" a", "a", "ab", "b"]
    lattice = langid.Lattice(pieces).of(["abab"])
    uses = langid.expected(lattice, np.log(np.full((5, 1), 0.2)), np.ones((1, 1)))
    assert np.isclose((uses[:, 0] * np.array([2, 1, 2, 1, 1])).sum(), 5)


def test_language_held_out(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    model = langid.train(docs, langid.public_pieces(public_tokenizers.path("piece_bpe_32k.model")), sample_docs=60)
    got = langid.predict(docs, model).where("held_out").join(docs.select("doc_id", "lang"), "doc_id")
    assert got.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0] > 0.98


def test_nn_pu_separates_hidden_positives():
    rng = np.random.default_rng(0)
    y = rng.random(4000) < 0.2
    x = (rng.random((4000, 6)) < np.where(y[:, None], [0.8, 0.7, 0.1, 0.3, 0.3, 0.3], [0.05, 0.05, 0.1, 0.3, 0.3, 0.3])).astype(np.float32)
    pos = x[y][:200]
    w, b = toxicity.nn_pu(pos, x, 0.2)
    assert ((x @ w + b > 0) == y).mean() > 0.9


def test_risk_and_its_gradient_against_plain_forms():
    """The risk summed document by document, and its gradient by finite differences, on both sides of the correction."""
    rng, sides = np.random.default_rng(3), set()
    for _ in range(20):
        xp, xu = (rng.random((n, 5)) < 0.4 for n in (7, 9))
        w, prior = np.round(rng.normal(size=6) * 8) / 4, rng.choice([0.1, 0.9])

        def parts(w, xp=xp, xu=xu, prior=prior):
            loss = lambda z: math.log1p(math.exp(z))
            z = lambda x: sum(wi for wi, on in zip(w, x, strict=False) if on) + w[-1]
            return prior * sum(loss(-z(x)) for x in xp) / len(xp), sum(loss(z(x)) for x in xu) / len(xu) - prior * sum(loss(z(x)) for x in xp) / len(xp)

        pos, neg, grad = toxicity.risk_step(xp.astype(np.float32), xu.astype(np.float32), w, prior, gamma=0.5)
        assert np.allclose((pos, neg), parts(w), atol=1e-5)
        sides.add(neg < 0)
        aim = lambda w, neg=neg, parts=parts: -0.5 * parts(w)[1] if neg < 0 else sum(parts(w))
        slope = [(aim(w + d) - aim(w - d)) / 2e-4 for d in np.eye(6) * 1e-4]
        assert np.allclose(grad, slope, atol=1e-4)
    assert sides == {True, False}


def test_toxicity_scores_by_definition(spark, odd_docs):
    model = toxicity.Model(["word", "wor*", "text", "twic*", "same"], np.array([1.5, 9.0, -2.0, 0.25, 0.5]), -0.5, 0.1)
    for r in toxicity.score(odd_docs, model).join(odd_docs.select("doc_id", "text"), "doc_id").where("doc_id != 3").collect():
        words = set(re.findall(r"[^\W_]+", (r.text or "").lower()))
        on = words | {w[:n] + "*" for w in words for n in (4, 5, 6) if len(w) > n}
        want = 1 / (1 + math.exp(0.5 - sum(w for n, w in zip(model.names, model.weights, strict=True) if n in on)))
        assert abs(r.score - want) < 1e-12 and r.predicted == int(want >= 0.5)


def test_toxicity_on_planted(spark, rng):
    vocab = ["".join(rng.choice("abcdefgh") for _ in range(5)) for _ in range(300)]
    rows, labels = [], []
    for i in range(900):
        ws = [rng.choice(vocab) for _ in range(60)]
        if i % 5 == 0:
            ws[3:6] = rng.sample(["awful", "vile", "nasty", "brute"], 3)
        rows.append((i, " ".join(ws)))
        if i % 2 == 0:
            labels.append((i, int(i % 5 == 0)))
    docs, lab = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    got = toxicity.score(docs, toxicity.train(docs, lab)).collect()
    assert sum(r.predicted == int(r.doc_id % 5 == 0) for r in got) / len(got) > 0.98
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got)
