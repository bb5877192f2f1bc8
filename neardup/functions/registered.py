"""Functions and table functions for SQL users."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.functions import varbyte


def register(spark: SparkSession) -> None:
    """``hamming``, ``lsh_terms``, ``mlp_score``, ``mean_vector`` and the table functions ``explode_terms``, ``decode_postings``."""
    from neardup.operators.scorers import forward, random_weights, unpacked

    @F.pandas_udf("int")
    def hamming(a: pd.Series, b: pd.Series) -> pd.Series:
        far = [int(np.bitwise_count(np.asarray(x, np.uint64) ^ np.asarray(y, np.uint64)).sum()) for x, y in zip(a, b, strict=True)]
        return pd.Series(far, dtype="int32")

    @F.pandas_udf("array<long>")
    def lsh_terms(vec: pd.Series, width: pd.Series) -> pd.Series:
        return pd.Series([_terms(v, int(w)) for v, w in zip(vec, width, strict=True)])

    weights = random_weights(64, (32, 16, 8), 0)

    @F.pandas_udf("double")
    def mlp_score(a: pd.Series, b: pd.Series) -> pd.Series:
        xor = pd.Series([np.asarray(x, np.int64) ^ np.asarray(y, np.int64) for x, y in zip(a, b, strict=True)])
        return pd.Series(forward(weights, unpacked(xor, 64))[-1][:, 0].astype(np.float64) if len(xor) else [])

    @F.pandas_udf("array<double>")
    def mean_vector(v: pd.Series) -> list:
        return np.mean(np.stack([np.asarray(x, np.float64) for x in v]), axis=0).tolist()

    for name, f in {"hamming": hamming, "lsh_terms": lsh_terms, "mlp_score": mlp_score, "mean_vector": mean_vector}.items():
        spark.udf.register(name, f)

    @F.udtf(returnType="term: bigint")
    class ExplodeTerms:
        def eval(self, vec, width: int):
            for t in _terms(vec, width):
                yield (int(t),)

    @F.udtf(returnType="id: bigint")
    class DecodePostings:
        def eval(self, blob):
            for i in varbyte.decode_ids(bytes(blob)):
                yield (int(i),)

    spark.udtf.register("explode_terms", ExplodeTerms)
    spark.udtf.register("decode_postings", DecodePostings)


def _terms(vec, width: int) -> np.ndarray:
    """Terms of a real vector's sign bits in disjoint groups."""
    bits = (np.asarray(vec, np.float64) > 0).astype(np.int64)
    n = len(bits) // width
    value = bits[: n * width].reshape(n, width) @ (1 << np.arange(width))
    return (np.arange(n) << width) + value


def views(spark: SparkSession, **tables: DataFrame) -> None:
    """Registers DataFrames as temporary views: ``items, terms, postings, candidates, scored, clusters``."""
    for name, df in tables.items():
        df.createOrReplaceTempView(name)
