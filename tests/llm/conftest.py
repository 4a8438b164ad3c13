import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, score double"


@pytest.fixture(scope="session")
def docs_of(spark):
    """Documents with clashing extra columns from (doc_id, text) pairs."""

    def make(rows):
        return spark.createDataFrame([(i, t, "en", "s", len(t or ""), "k", 0.5) for i, t in rows], SCHEMA)

    return make


@pytest.fixture(scope="session")
def odd():
    """Nulls, blanks, ties, repeats and one very long text."""
    long = " ".join(f"w{i % 977}x{i}" for i in range(30_000))
    return [(1, None), (2, ""), (3, " \n\t "), (4, "one two three four five six"), (4, "one two three four five six"), (None, "one two three four five six"), (5, "!!! 123"), (6, long), (7, "Ünïcödé ☃ 漢字")]
