import pytest

LONG = "word " * 40_000
DIRTY = [
    (1, None), (2, ""), (3, " \n\t"), (4, "Plain short text."), (4, "Plain short text."), (5, "Plain short text."), (None, "no id here a@b.co"), (6, LONG),
    (7, "ünï çødé 日本語 text 😀 mail x@y.zz now"), (8, "9" * 5000), (9, "!!! ??? ...\n\n"), (10, "Plain short text!"),
]


@pytest.fixture
def dirty(spark):
    """Nulls, empties, a long text, repeats and ties, and extra columns named like the operators' own."""
    rows = [(i, t, "x", 1, 0.5, i) for i, t in DIRTY]
    return spark.createDataFrame(rows, "doc_id long, text string, spans string, n_words int, score double, _a long")


@pytest.fixture
def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, spans string")
