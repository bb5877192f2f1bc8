"""Readers of the given tables. Only Spark opens paths, so any Hadoop file system works."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = (
    "region nation customer supplier part orders lineitem events documents "
    "embeddings pages benchmark labels conversations"
).split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of ``TABLES`` as a DataFrame over ``<sf_dir>/<name>.parquet``."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vector_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The given vectors as items: ``(item_id, vec)``."""
    e = table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("item_id"), F.col("embedding").alias("vec"))


def text_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main corpus: ``(item_id, text, lang, source, n_chars)``."""
    d = table(spark, sf_dir, "documents")
    return d.select(F.col("doc_id").alias("item_id"), "text", "lang", "source", "n_chars")
