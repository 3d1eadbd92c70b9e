import pytest


@pytest.fixture(scope="session")
def docs_of(spark):
    """A documents table of (doc_id, text) or (doc_id, text, lang, source) rows, with an extra column of a clashing name."""

    def make(rows):
        full = [(*r, None, None)[:4] if len(r) < 4 else r for r in rows]
        return spark.createDataFrame([(*r, len(r[1] or ""), "x") for r in full], "doc_id long, text string, lang string, source string, n_chars long, key string")

    return make
