import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, shard int, slot long, fp long, copies int, score double, host string, word string, kept boolean, salt int, k0 string, target double, rate double"
EXTRA = (1, 2, 3, 4, 5, 0.5, "h", "w", True, 6, "k", 1.0, 2.0)


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty and very long texts, ties, repeated rows, and extra columns with clashing names."""
    long = " ".join(f"word{i % 977} token{i % 31}" for i in range(60_000))
    rows = [
        (1, "Hello world this is a text about nothing much at all really", "en", "a"),
        (1, "Hello world this is a text about nothing much at all really", "en", "a"),
        (2, None, "en", "a"), (3, "", None, "b"), (4, "   \n\t ", "de", None), (None, "no id here but words", "fr", "b"), (None, None, None, None),
        (5, long, "en", "a"), (6, long, "en", "b"), (7, "x", "en", "c"), (8, "é ü ß ✓ 𝄞 emoji", "es", "c"), (7, "same id other text", "en", "c"), (9, "12345 !!! ???", "en", "a"),
    ]
    return spark.createDataFrame([(i, t, g, s, None if t is None else len(t), *EXTRA) for i, t, g, s in rows], SCHEMA)


@pytest.fixture(scope="session")
def no_docs(odd_docs):
    return odd_docs.limit(0)
