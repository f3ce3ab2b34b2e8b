"""Small document tables with every awkward case in them."""

import pytest

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, n_words string, base_failed string, __id string, component_id string"


@pytest.fixture
def make(spark):
    """Rows of (doc_id, text[, lang[, source]]) as documents with extra columns whose names clash with results."""

    def table(rows):
        full = [(r[0], r[1], r[2] if len(r) > 2 else "en", r[3] if len(r) > 3 else "s", None if r[1] is None else len(r[1]), "x", "y", "z", "w") for r in rows]
        return spark.createDataFrame(full, SCHEMA)

    return table


@pytest.fixture
def awkward(make):
    """Nulls, empties, white space, repeated rows, ties, a very long text."""
    long = " ".join(f"word{i % 997} of number{i}" for i in range(20_000))
    return make([(1, None), (2, ""), (3, " \t\n \r"), (None, "a null id"), (4, "Same text here, twice over."), (4, "Same text here, twice over."), (5, "Same text here, twice over."), (6, long, None, None), (7, "!!! ???", "fr", None)])
