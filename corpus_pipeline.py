"""The corpus pipeline: five stages over documents, each one of the training-data operators.

Every stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame that is written as Parquet and read back
as the next one's ``docs``; all but the last keep the columns of documents. Stages work on every row and
every whole text that their predecessor kept. Rows with a null id pass every stage that does not judge them by
their text: near duplicates never take them out, as nothing names them. A null text counts as empty and stays null.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from neardup.llm import mixing, pieces, pii, simhash, toxicity
from neardup.sources.lineage import written
from neardup.sources.tables import table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored toxic go. Labels are learned from those rows that are not held out."""
    return toxicity.drop_toxic(docs, table(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of texts the smallest id stays: linked are fingerprints of at most three differing bits, and texts with a similarity of 0.8 or more over five-word shingles."""
    return simhash.drop_linked(docs, max_bits=3, similarity=0.8, shingle=5)


def redact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data in each text is replaced by its kind."""
    return pii.redact(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as its source's share of the mix takes it."""
    return mixing.mix(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of each text, and whether they decode to it exactly."""
    return pieces.encode(docs, pieces.load())


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash", near_duplicates),
    ("pii", redact),
    ("mixing", mix_sources),
    ("sentencepiece", encode),
]

#: Learned scores, fingerprint links and piece ids are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order over the whole ``documents`` table."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
