import pytest


@pytest.fixture(scope="session")
def docs_of(spark):
    """Rows (doc_id, text) as a documents table with its other columns."""

    def make(rows, source="s"):
        return spark.createDataFrame([(i, t, "en", source, len(t) if t is not None else None) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")

    return make
