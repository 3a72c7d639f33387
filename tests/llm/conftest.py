import pytest

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, row string, key string"


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty and long texts, repeated rows, ties, and columns whose names clash with inner ones."""
    long = " ".join(f"w{i}" for i in range(30_000))
    rows = [
        (1, None, None, None, None, None, None), (2, "", "en", "a", 0, "x", "y"), (3, "   ", "en", "a", 3, "x", "y"), (4, long, "en", "b", 1, "x", "y"), (5, long, "en", "b", 1, "x", "y"),
        (6, "One two three four", "en", "b", 1, "x", "y"), (7, "one TWO three four", "en", "b", 1, "x", "y"), (7, "one TWO three four", "en", "b", 1, "x", "y"),
        (None, "one two three four", "de", "c", 1, "x", "y"), (8, "short", "de", "c", 1, "x", "y"), (9, "ab " * 500, "de", None, 1, "x", "y"),
    ]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], DOCS)
