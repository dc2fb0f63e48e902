import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"

#: Nulls in any column, empty texts, ties, repeated rows.
ODD = [
    (1, "the token: abcdef123456 and more words " * 3, "en", "a", 10),
    (1, "the token: abcdef123456 and more words " * 3, "en", "a", 10),
    (2, None, None, None, None),
    (None, "some text without an id, of a few words", "en", "b", 1),
    (None, None, None, None, None),
    (3, "", "fr", "a", 0),
    (4, " \n\t ", "fr", None, 4),
    (5, "é" * 3000 + " ünï 日本", "de", "c", 3),
    (6, "x " * 30_000, "en", "a", 60_000),
]


@pytest.fixture(scope="session")
def odd(spark):
    """The odd rows with further columns whose names operators use inside."""
    rows = [(*r, "s", 1, "t", 0.5) for r in ODD]
    return spark.createDataFrame(rows, DOCS + ", size string, rid int, kept string, score double").repartition(3)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOCS)
