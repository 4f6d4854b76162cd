import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"

LONG = ("lorem ipsum dolor sit amet " * 3000).strip()
PROSE = "the quick brown fox jumps over the lazy dog and then it rests under the old oak tree near the river bank"


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls, empty and very long texts, ties, repeated rows, and extra columns whose names clash with inner ones."""
    rows = [
        (1, PROSE), (2, None), (3, ""), (4, LONG), (5, PROSE), (5, PROSE), (None, PROSE), (7, "   \n\t "), (8, "ÉCOLE Straße 日本語 🙂 İΣ"),
        (9, "x"), (10, None), (None, None), (11, PROSE.upper()),
    ]
    named = [(*r, "en", None, 5, 1, "p", 0, 3.5, "q", 9) for r in rows]
    return spark.createDataFrame(named, "doc_id long, text string, lang string, source string, n_chars long, piece int, token string, part int, score double, fp string, row int")


@pytest.fixture(scope="session")
def no_docs(odd_docs):
    return odd_docs.limit(0)
