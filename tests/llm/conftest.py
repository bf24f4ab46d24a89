import pytest

LONG = "word " * 60_000
ODD = [
    (1, None, None, None, None), (2, "", "en", "s", 0), (3, " \n\t ", "en", "s", 4), (4, "One two three.", "en", "s", 14), (4, "One two three.", "en", "s", 14),
    (None, "Null id here, with some words to read.", "de", None, 38), (5, "!!! 123 ???", "fr", "s", 11), (6, LONG, "en", "s", len(LONG)), (7, "x" * 50_000, "es", "s", 50_000), (8, "naïve ñandú 中文     end", None, "s", 20), (-9, "One two three.", "en", "s", 14),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty and very long texts, ties, repeated rows; columns whose names clash with ours."""
    from pyspark.sql import functions as F

    df = spark.createDataFrame(ODD, SCHEMA)
    for c in ("node", "component", "digest", "span", "hits", "items", "spans", "word", "n", "row", "score", "value", "bucket", "kept", "of", "place"):
        df = df.withColumn(c, F.lit("clash"))
    return df


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], SCHEMA)
