import pytest


@pytest.fixture(scope="session")
def docs_of(spark):
    """A documents table with a clashing extra column."""

    def make(rows):
        return spark.createDataFrame([(i, t, "en", s, None if t is None else len(t), "x", 1) for i, t, s in rows], "doc_id long, text string, lang string, source string, n_chars long, digest string, `size.x` int")

    return make


ODD = [(1, None, "a"), (2, "", "a"), (None, "some text of no document", None), (3, "é😀 tie", None), (3, "é😀 tie", None), (4, "x" * 70_000, "b"), (5, "word " * 30_000, "b"), (6, "\n\n \t\n", "a")]


@pytest.fixture(scope="session")
def odd():
    return ODD
