import pytest
from pyspark.sql import types as T

#: Nulls, empty and blank texts, a lone letter, ties and repeated rows, a very long text, and columns whose names the operators use themselves.
SCHEMA = T.StructType([T.StructField(c, t) for c, t in (("doc_id", T.LongType()), ("text", T.StringType()), ("lang", T.StringType()), ("source", T.StringType()), ("n_chars", T.LongType()), ("_text", T.StringType()), ("score", T.DoubleType()), ("block", T.StringType()), ("fp", T.StringType()))])
TEXTS = [None, "", "   \n\t ", "a", "7 7 7", "The cat sat on the mat. " * 6, "The cat sat on the mat. " * 6, "The cat sat on the mat. " * 6, "Élan vital été <|endoftext|> où  \n\n naïve don't I'll x²", "word " * 30_000, "one two", "The quick brown fox jumps over the lazy dog near the river bank today"]
IDS = [0, 1, 2, 3, 4, 5, 6, 6, 7, 8, None, 9]


@pytest.fixture(scope="session")
def odd(spark):
    rows = [(i, t, None if k % 3 == 0 else "en", "s", 0, "x", 1.0, "b", "f") for k, (i, t) in enumerate(zip(IDS, TEXTS, strict=True))]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def docs(spark):
    return spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
