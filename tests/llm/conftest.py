import pytest


@pytest.fixture
def docs_of(spark):
    """Documents from (id, text) pairs, with an extra column of a clashing name."""

    def make(rows):
        return spark.createDataFrame([(i, t, "en", "src0", 0, "x") for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, spans string")

    return make
