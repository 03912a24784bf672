import pytest
from pyspark.sql import types as T

DATA = "/root/testdata/sf0.001"

#: Nulls, empty and blank texts, ties, repeated rows, a long word and a long text; "kept" and "text_" clash with names the operators make.
ROWS = [
    (1, "the quick brown fox jumps over the lazy dog. " * 30, "en", "a"),
    (2, None, "en", "a"),
    (3, "", None, "b"),
    (4, " \n\t ", "fr", None),
    (5, "one two three", "fr", "b"),
    (5, "one two three", "fr", "b"),
    (5, "one two four", None, "c"),
    (None, "a null id has words too, and quite a few of them at that", "de", "c"),
    (6, "x" * 5000, "de", "é"),
    (7, " ".join(f"w{i % 977}" for i in range(20000)), "es", "a"),
    (8, "Line one here.\nLine one here.\nÜber straße #### $$$ token = 'abcdef123456'\n<b>|", "en", "z"),
]


@pytest.fixture(scope="session")
def odd(spark):
    fields = [("doc_id", T.LongType()), ("text", T.StringType()), ("lang", T.StringType()), ("source", T.StringType()), ("kept", T.StringType()), ("Node", T.StringType()), ("q__n_words", T.StringType())]
    schema = T.StructType([T.StructField(n, t) for n, t in fields])
    return spark.createDataFrame([(*r, "k", "n", "q") for r in ROWS], schema).repartition(3)


@pytest.fixture(scope="session")
def empty(odd):
    return odd.where("1 = 0")


@pytest.fixture(scope="session")
def docs(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet")
