import pytest


@pytest.fixture
def docs_of(spark):
    """documents with the given texts, ids from 0, and columns whose names clash with inner ones."""

    def make(texts, ids=None):
        rows = [(i if ids is None else ids[i], t, "en", None, i, "x") for i, t in enumerate(texts)]
        return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, g long, kind string")

    return make
