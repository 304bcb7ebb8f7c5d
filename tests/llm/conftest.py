import pytest


@pytest.fixture(scope="session")
def make(spark):
    """Documents from (doc_id, text) pairs, with columns that could clash with the operators' own."""

    def of(rows):
        full = [(i, t, "en", "src0", len(t or ""), "x", "y") for i, t in rows]
        return spark.createDataFrame(full, "doc_id long, text string, lang string, source string, n_chars long, id string, rid string")

    return of
