import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture
def docs(spark):
    """Makes a documents table of (doc_id, text) pairs."""
    return lambda rows: spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], DOCS)


#: Nulls in any column, empty and blank texts, repeated rows, ties and a long text.
ODD = [(1, None), (None, "alone words here"), (2, ""), (3, "   \n\t "), (4, "a b c"), (4, "a b c"), (5, "word " * 30_000), (6, "é日本 ß\x00 ok"), (None, None)]
