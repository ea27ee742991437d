import pytest

EXTRA = "key long, rid long, n long, x string, t string, score string, weight string, prob string, sampled string, node long, comp long, band string, trusted string, predicted string, lang_pred string, spans string"
LONG = "lorem ipsum dolor sit amet " * 20_000


@pytest.fixture(scope="session")
def edge(spark):
    """Nulls in each column, empty, blank and very long texts, ties and repeated rows, and extra columns with names that operators use."""
    base = "The quick brown fox jumps over the lazy dog and runs away from all of the other animals in the wide green forest today"
    rows = [
        (1, base, "en", "a"), (2, base, "en", "a"), (2, base, "en", "a"), (3, None, "en", "a"), (4, "", None, "a"), (5, " \n\t ", "en", None), (None, base + " x", "en", "b"),
        (None, None, None, None), (6, LONG, "la", "b"), (7, LONG + "end", "la", "b"), (8, "a", "en", "b"), (9, "12345 67890 !!", "en", "b"), (10, "one two three four", "en", "b"), (11, "one two three four", "en", "b"),
    ]
    n = len(EXTRA.split(","))
    return spark.createDataFrame([(*r, len(r[1] or ""), *[None] * n) for r in rows], f"doc_id long, text string, lang string, source string, n_chars long, {EXTRA}")


@pytest.fixture(scope="session")
def none(edge):
    return edge.limit(0)
