from __future__ import annotations

import pytest

TEXTS = [
    None, "", "   \n\t ", "one", "one two", "Ünï çödé   straße", "a" * 5000, "word " * 3000, "the same text again and again", "the same text again and again",
    "THE SAME text again and again", "1234 5678", "<|endoftext|> kept as the library reads it", "tab\tand\nnew line   nbsp",
]


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty and long texts, ties, repeated rows, and extra columns whose names clash with operators' own."""
    rows = [(k, t, ["en", None, "de"][k % 3], ["a", None, "b", ""][k % 4], 7, "x", 0.5) for k, t in enumerate(TEXTS)]
    rows += [rows[4], rows[4], (None, "no id here", None, None, None, None, None), (None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, component_id string, score double")


@pytest.fixture(scope="session")
def no_docs(odd_docs):
    return odd_docs.limit(0)
