"""Nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns, for every operator."""

import public_tokenizers
import pytest

from fixgap.llm import binary_ids, bpe, decontaminate, langid, media, pii, repeats, simhash, toxicity

TOK = public_tokenizers.path("word_bpe_49k.json")


def _labels(spark):
    return spark.createDataFrame([(1, 1, 1), (3, 1, 0), (3, 0, 1), (None, 1, 1), (99, 1, None)], "doc_id long, quality int, toxic int")


def _bench(spark):
    return spark.createDataFrame([(1, "word word word word word word"), (2, None), (3, ""), (3, "a b"), (None, "no item is like this one here")], "item_id long, text string")


OPS = {
    "toxicity": lambda s, d: toxicity.score(d, toxicity.train(d, _labels(s))),
    "token_files": lambda s, d: binary_ids.read(s, binary_ids.write(d, TOK)),
    "media": lambda s, d: media.digests(d),
    "language": lambda s, d: langid.predict(d, langid.train(d, ["a", " a", "b", "wo", "rd", " word"])),
    "bpe": lambda s, d: bpe.digests(d, TOK),
    "pii": lambda s, d: pii.find(d, pii.train(d, epochs=1)),
    "repeats": lambda s, d: repeats.remove(d),
    "simhash": lambda s, d: simhash.near_duplicates(d),
}


@pytest.mark.parametrize("name", OPS)
def test_odd_rows(spark, odd_docs, clashing, name):
    """A row for each row, the same with clashing columns."""
    a = OPS[name](spark, odd_docs).orderBy("doc_id", *OPS[name](spark, odd_docs.limit(0)).columns[1:]).collect()
    b = OPS[name](spark, clashing).collect()
    assert len(a) == odd_docs.count()
    assert sorted(map(str, a)) == sorted(map(str, b))


@pytest.mark.parametrize("name", OPS)
def test_empty_table(spark, empty_docs, name):
    assert OPS[name](spark, empty_docs).collect() == []


def test_decontamination_edges(spark, odd_docs, clashing, empty_docs):
    got = decontaminate.find(odd_docs, _bench(spark)).collect()
    assert [(r.doc_id, r.item_id, r.edits) for r in got] == [(7, 1, 0)]
    assert decontaminate.find(clashing, _bench(spark)).count() == 1
    assert decontaminate.find(empty_docs, _bench(spark)).count() == 0
    assert decontaminate.find(odd_docs, _bench(spark).limit(0)).count() == 0
    assert decontaminate.clean(odd_docs, _bench(spark)).count() == odd_docs.count() - 1
    assert decontaminate.clean(clashing, _bench(spark)).columns == clashing.columns


def test_null_and_empty_results(spark, odd_docs):
    by = {r.doc_id: r for r in media.digests(odd_docs).collect()}
    assert (by[0].n_bytes, by[0].payload_bytes) == (0, 64) and by[0].media_sha256 == by[1].media_sha256
    ids = {r.doc_id: r for r in binary_ids.read(spark, binary_ids.write(odd_docs, TOK), ids=True).collect()}
    assert ids[0].ids == ids[1].ids == ids[2].ids == [2]
    lang = {r.doc_id: r for r in OPS["language"](spark, odd_docs).collect()}
    assert {lang[i].lang_pred for i in (0, 1, 2, 4)} == {"und"} and lang[0].score == 0
    same = {r.doc_id: r.component_id for r in simhash.near_duplicates(odd_docs).collect()}
    assert same[0] == same[1] == same[2] == 0 and same[9] == 8


def test_no_labels_and_no_spans(spark, odd_docs):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {r.predicted for r in toxicity.score(odd_docs, toxicity.train(odd_docs, none)).collect()} == {0}
    assert pii.train(odd_docs) is None


def test_stages_keep_columns(spark, clashing):
    model = toxicity.train(clashing, _labels(spark))
    for out in (toxicity.clean(clashing, model), simhash.keep_one(clashing), pii.redact(clashing, None)):
        assert out.columns == clashing.columns


def test_keep_one(spark, odd_docs, empty_docs):
    kept = simhash.keep_one(odd_docs)
    groups = simhash.near_duplicates(odd_docs).select("component_id").distinct().count()
    assert kept.count() == groups
    assert simhash.keep_one(odd_docs.where("doc_id in (8, 9)")).first().doc_id == 8
    assert simhash.keep_one(empty_docs).count() == 0
