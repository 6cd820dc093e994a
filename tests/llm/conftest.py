"""Small documents with every odd case: nulls, empty and long texts, ties, repeated rows, clashing extra columns."""

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score double, _id long, fp long"


@pytest.fixture(scope="session")
def odd(spark):
    def make(rows):
        return spark.createDataFrame([(i, t, lang, s, len(t or ""), 9.0, 1, 2) for i, t, lang, s in rows], SCHEMA)

    return make


@pytest.fixture(scope="session")
def corpus(odd):
    long = " ".join(f"word{i % 977}x{i % 13}" for i in range(30_000))
    rows = [
        (1, "Hello big World, hello there", "en", "a"), (2, "hello BIG world, hello there", "en", "a"), (3, None, None, None), (4, "", "en", None),
        (None, "no id here", "de", "b"), (None, "no id here", "de", "b"), (5, "tie", "fr", "b"), (5, "tie", "fr", "b"), (5, "other text", "fr", "b"),
        (6, long, "en", "c"), (7, long + " end", "en", "c"), (8, long.upper(), "en", "c"), (9, "  \n\t ", "en", "a"), (10, "Über été 中文   x", "de", "a"), (-3, "negative id", "es", "b"),
    ]
    return odd(rows)


@pytest.fixture(scope="session")
def empty(odd):
    return odd([])
