"""Encoding without decoding."""

from __future__ import annotations

import public_tokenizers

from fixgap.llm import bpe

TOK = public_tokenizers.path("word_bpe_49k.json")


def test_encode_makes_no_pieces_and_gives_the_librarys_ids(spark, odd_docs):
    """The pipeline's last stage asks for ids alone: no id is joined with its piece, which an executor had no memory for."""
    from fixgap.llm import words

    encoded = bpe.encode(odd_docs, TOK)
    plan = encoded._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" not in plan and "piece" not in plan
    library = words.load(TOK)
    want = sorted((str(r.doc_id), library.encode(r.text or "", add_special_tokens=False).ids) for r in odd_docs.collect())
    assert sorted((str(r.doc_id), list(r.ids)) for r in encoded.collect()) == want
