import pytest

LONG = " ".join(f"word{i % 977}" for i in range(30_000))


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty and blank texts, a very long text, ties, repeated rows, clashing extra columns."""
    rows = [
        (1, None, "en", "a"), (2, "", None, "a"), (3, " \t\n ", "en", None), (4, "one two three", "en", "b"), (5, "one two three", "de", "b"), (5, "one two three", "de", "b"),
        (6, LONG, "en", "c"), (7, LONG + " end", "en", "c"), (8, "12 34 !!", "en", "a"), (None, "a null key here with some words", "en", "a"), (9, "é ß ñ 你好 😀 <|endoftext|> it's", "fr", ""), (10, "a" * 5000, "en", "a"),
    ]
    data = [(i, t, lang, s, 7, "x", 1, 2, True, 0.5, "e") for i, t, lang, s in rows]
    return spark.createDataFrame(data, "doc_id long, text string, lang string, source string, id long, t string, at long, n long, kept boolean, score double, digest string")


@pytest.fixture(scope="session")
def documents(spark):
    return spark.read.parquet("/root/testdata/sf0.001/documents.parquet")


@pytest.fixture(scope="session")
def texts(documents):
    return {r["doc_id"]: r["text"] for r in documents.select("doc_id", "text").collect()}
