import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, empty and long texts, ties, repeated rows, and columns with names that operators use."""
    long = " ".join(f"word{i % 977}" for i in range(40_000))
    rows = [
        (1, "the same text of some words that is long enough to make a few shingles here", "en", "a", 1), (1, "the same text of some words that is long enough to make a few shingles here", "en", "a", 1),
        (2, "the same text of some words that is long enough to make a few shingles here", "en", None, 1), (3, None, "en", "a", None), (4, "", None, "b", 0), (None, "a text without id", "en", "a", 3),
        (5, long, "en", "a", 9), (6, "one", "fr", "b", 3), (7, " \n\t ", "fr", "b", 4), (8, "Ünï çödé \U0001f600 line\n\nline\nline", "de", "b", 4), (9, None, None, None, None),
    ]
    df = spark.createDataFrame(rows, SCHEMA)
    from pyspark.sql import functions as F

    return df.withColumns({"id": F.lit("clash"), "token": F.lit(1), "component": F.lit(0), "n": F.lit(2), "rank": F.lit(3), "mix_position": F.lit(-1), "value": F.lit("x"), "kept": F.lit("?")})


@pytest.fixture(scope="module")
def none(odd):
    return odd.limit(0)
