import pytest

EDGE_TEXTS = [None, "", " ", "\n\n", "a", "One two three four five six.", "One two three four five six.", "é ü 漢字 \U0001f600", "!!! $$$ 123", "x" * 5000, "word " * 30_000]


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls, empty, very long and repeated texts, repeated rows, null ids, and extra columns with likely names."""
    rows = [(k, t, None if k % 3 else "en", None if k % 2 else "s", None, "u", 1, 2.0, "x", "y", "z") for k, t in enumerate(EDGE_TEXTS)]
    rows += [rows[5], (None, "One two three four five six.", "en", "s", 3, "u", 1, 2.0, "x", "y", "z"), (None,) * 11]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, uid string, size int, score double, _language string, _clean string, _Digest string").cache()


@pytest.fixture(scope="session")
def no_docs(spark, odd_docs):
    return odd_docs.where("false")
