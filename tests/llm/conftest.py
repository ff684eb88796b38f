"""Small tables with every odd case: nulls, empty and long texts, ties, repeated rows, clashing extra columns."""

import pytest
from pyspark.sql import functions as F

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()
LONG = " ".join(WORDS[(i * i + i // 7) % 20] + str(i % 13) for i in range(6000))
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
CLASHING = ["_id", "size", "kept", "name", "token", "words", "row", "cell", "bucket", "_found", "_hash", "item_id", "n_shingles", "held_out", "score", "y", "w"]


def odd_rows():
    base = " ".join(WORDS * 3)
    near = base.replace("kappa lambda", "kappa omega", 1)
    return [
        (1, base, "en", "a", 1), (2, base, "en", "a", 1), (2, base, "en", "a", 1), (3, base.replace(" ", "\n\t"), "en", "a", 1), (4, near, None, None, None), (5, "", "en", "a", 0), (6, None, None, "a", None),
        (7, "  \n ", "fr", "b", 3), (8, "one two three", "fr", "b", 1), (9, "One Two Three", "fr", "b", 1), (10, LONG, "en", "b", len(LONG)), (11, LONG + " tail", "en", "b", 1), (None, base, "en", "a", 1),
        (None, "nobody's row, with <|endoftext|> inside", "en", "a", 1), (12, "日本語 テキスト ½ é́", "xx", "c", 1), (13, "12345 67 !!!", None, "c", 1),
    ]


@pytest.fixture(scope="session")
def odd(spark):
    df = spark.createDataFrame(odd_rows(), SCHEMA)
    for c in CLASHING:
        df = df.withColumn(c, F.lit("x"))
    return df.repartition(3)


@pytest.fixture(scope="session")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)
