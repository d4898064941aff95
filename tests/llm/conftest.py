import pytest

DOCS = "doc_id long, text string, lang string, source string, score double, fp long, row string, size long"


@pytest.fixture
def docs(spark):
    """Makes documents with columns whose names clash with those that the operators use."""

    def make(rows):
        return spark.createDataFrame([(i, t, lang, source, 1.5, 7, "row", 3) for i, t, lang, source in rows], DOCS)

    return make


#: Null and empty texts, null ids, repeated rows, ties, marks only, very long texts, other scripts.
ODD = [
    (1, None, "en", "a"), (2, "", "en", None), (3, "one", None, "b"), (3, "one", None, "b"), (None, "one two three", "de", "c"), (None, None, None, None), (5, "…!? 123 \n\t ", "en", "a"),
    (6, "Wort " * 30_000, "de", "a"), (7, "ΑΣ 日本 🙂 é́ İ", "el", "d"), (8, "one two three", "en", "a"), (9, "<|endoftext|> x", "en", "a"), (10, "x" * 5000, "en", "b"),
]
