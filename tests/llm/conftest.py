import pytest


@pytest.fixture(scope="session")
def docs_of(spark):
    """Documents from texts, with columns that clash with names used inside the operators."""

    def make(texts, ids=None, sources=None):
        ids = ids or range(len(texts))
        rows = [
            (i, t, "en", (sources[n] if sources else f"s{n % 3}"), len(t or ""), 1, "x", 2)
            for n, (i, t) in enumerate(zip(ids, texts))
        ]
        return spark.createDataFrame(
            rows, "doc_id long, text string, lang string, source string, n_chars long, key int, id string, size int"
        )

    return make
