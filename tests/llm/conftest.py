import pytest

WEIRD = [
    (1, None, "x"), (2, "", "x"), (3, " \t\n", None), (4, "one two three", "x"), (5, "ONE two  three", "x"), (6, "one two three four", "y"),
    (7, "one two three four five", "y"), (8, "A" * 50_000, "y"), (9, "é à ü 日本 語 ü é à", "z"), (10, "é à ü 日本 語 ü é à", "z"),
    (11, "word " * 3000, "z"), (None, "no id here at all friends", "z"),
]


@pytest.fixture(scope="session")
def weird(spark):
    """Nulls, empties, ties, long texts and columns whose names clash with those inside."""
    rows = [(i, t, s, 1, 2, 3) for i, t, s in WEIRD]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, n int, digest int, log_bytes int")


@pytest.fixture(scope="session")
def nothing(weird):
    return weird.limit(0)
