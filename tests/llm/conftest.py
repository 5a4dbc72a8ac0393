import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def make_docs(spark):
    """Documents from texts, with columns whose names operators use themselves."""

    def make(texts, first=0, lang="en", source="s"):
        rows = [(first + i, t, lang, source, len(t or "")) for i, t in enumerate(texts)]
        df = spark.createDataFrame(rows, DOCS)
        return df.selectExpr("*", "'x' AS t", "1 AS key", "2 AS row", "3 AS n", "'y' AS whole_")

    return make


ODD_TEXTS = [None, "", "   \n\t", "word", "a" * 20_000, "wörd ünï 日本語 \U0001f600 test", "same text here", "same text here"]
