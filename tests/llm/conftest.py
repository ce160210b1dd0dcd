import random

import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"

#: A document of each kind that must not break an operator: null and empty, blank, one word, no letter, odd characters, a long
#: text without spaces, a long text, and rows that repeat or have no id.
ODD = [None, "", "   \n\t ", "x", "12 34 !!", "Zero\x00width​ é É ß ﬁ \U0001f600 <|endoftext|>", "a" * 5000, "word " * 20000, "same text twice", "same text twice"]


@pytest.fixture(scope="session")
def odd_docs(spark):
    rows = [(i, t, "en" if i % 2 else None, "s", len(t or "")) for i, t in enumerate(ODD)]
    rows += [(None, "no id", "en", None, 5), (3, "x", "en", "s", 1), (3, "another text of id three", "de", "s", 24)]
    return spark.createDataFrame(rows, DOCS).repartition(3)


@pytest.fixture(scope="session")
def empty_docs(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="session")
def clashing(odd_docs):
    """Extra columns named as operators name theirs."""
    from pyspark.sql import functions as F

    return odd_docs.withColumns({c: F.lit("z") for c in ("fp", "n", "raw", "chunk", "bucket", "k1", "k2", "h", "u", "toxic", "held_out", "score", "component_id", "words", "ids", "media", "spans")})


@pytest.fixture
def rng():
    return random.Random(5)
