import pytest
from pyspark.sql import types as T

DOCS = T.StructType(
    [
        T.StructField("doc_id", T.LongType()),
        T.StructField("text", T.StringType()),
        T.StructField("lang", T.StringType()),
        T.StructField("source", T.StringType()),
        T.StructField("n_chars", T.LongType()),
        T.StructField("target", T.StringType()),  # clashes with a column of the mix
    ]
)


@pytest.fixture(scope="session")
def make_docs(spark):
    def make(rows):
        full = [(i, t, "en", s, None if t is None else len(t), "x") for i, t, s in rows]
        return spark.createDataFrame(full, DOCS)

    return make


BASE = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon " * 6


@pytest.fixture(scope="session")
def odd_rows():
    """Nulls, empty and long texts, ties, repeated rows, white space and special strings."""
    return [
        (1, None, "a"),
        (2, "", None),
        (3, "Hello World", "a"),
        (4, "hello world", "b"),
        (4, "hello world", "b"),
        (5, " \t\n", "a"),
        (6, "x" * 40_000, "b"),
        (7, BASE, "a"),
        (8, BASE.replace("kappa", "cappa", 1), "c"),
        (9, "naïve café — 'tis we'll  see\n\n  1234567   end <|endoftext|> tail　x", None),
        (None, "Hello World", "a"),
        (10, "one two", "c"),
        (11, "ÀÉ hello there", "c"),
    ]
