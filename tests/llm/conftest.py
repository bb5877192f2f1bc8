import pytest
from pyspark.sql import types as T


@pytest.fixture(scope="session")
def docs_of(spark):
    """Documents from ``(doc_id, text)`` pairs, with the other columns and one that clashes with inner names."""

    def make(pairs):
        schema = T.StructType(
            [
                T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()),
                T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType()), T.StructField("size", T.StringType()), T.StructField("h", T.StringType()),
            ]
        )
        rows = [(i, t, None, None if (i or 0) % 5 == 4 else f"s{(i or 0) % 3}", len(t or ""), "clash", "clash") for i, t in pairs]
        return spark.createDataFrame(rows, schema)

    return make


#: Nulls, empty, very long, repeated rows and ids, odd characters.
ODD = [(1, None), (2, ""), (3, "   "), (4, "one"), (5, "word " * 30_000), (6, "one"), (6, "one"), (None, "no id here"), (7, "ÄÖÜ ▁ \u0000 \U0001f600\n\ttabs"), (8, "!!! ??? ...")]
