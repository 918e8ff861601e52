import pytest
from pyspark.sql import functions as F

#: Texts that every operator must bear: null, empty, blanks, ties, repeats, one very long word, one very long text.
LONG = " ".join(f"word{i % 997} tail{i % 31}" for i in range(6000))
TEXTS = [None, "", "   \n\t", "one", "two words", LONG, LONG, "x" * 30000, "é ü\u00a0ß\n\nline line line", "a b c " * 40, "a b c " * 40]


@pytest.fixture(scope="session")
def odd(spark):
    """Odd texts, repeated rows, a null id, and columns named like the operators' own."""
    rows = [(i, t, "k", 1.0) for i, t in enumerate(TEXTS)] + [(3, "one", "k", 1.0), (None, "no id at all", None, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, key string, rate double").withColumns({"k1": F.lit(1), "n": F.lit("n"), "spans": F.lit(0)})


@pytest.fixture(scope="session")
def none(odd):
    return odd.where("false")
