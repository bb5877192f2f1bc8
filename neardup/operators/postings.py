"""Inverted index over terms, plain and compressed."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.functions import varbyte


def build(rows: DataFrame) -> DataFrame:
    """``(item_id, term)`` rows to posting lists ``(term, ids)``, ids ascending."""
    return rows.groupBy("term").agg(F.array_sort(F.collect_list("item_id")).alias("ids"))


def chunked(rows: DataFrame, chunk: int = 1 << 20) -> DataFrame:
    """Posting lists in pieces ``(term, piece, ids)`` of about ``chunk`` ids: no list grows beyond one row's room."""
    sizes = rows.groupBy("term").agg(F.ceil(F.count("*") / chunk).alias("pieces"))
    piece = F.pmod(F.xxhash64("item_id"), F.col("pieces"))
    return rows.join(sizes, "term").withColumn("piece", piece).groupBy("term", "piece").agg(F.array_sort(F.collect_list("item_id")).alias("ids"))


def encode(lists: DataFrame, codec: str = "both", codes: DataFrame | None = None) -> DataFrame:
    """``(term, ids)`` to ``(term, n, blob)``.

    ``none``: eight bytes an id; ``varbyte``: gaps in variable bytes; ``dictionary``: ids replaced by the
    dense codes in ``codes(item_id, code)``, four bytes each; ``both``: codes, then gaps in variable bytes.
    """
    if codec in ("dictionary", "both"):
        coded = lists.select("term", F.explode("ids").alias("item_id")).join(codes, "item_id")
        lists = coded.groupBy("term").agg(F.array_sort(F.collect_list("code")).alias("ids"))

    @F.pandas_udf("binary")
    def packed(ids: pd.Series) -> pd.Series:
        if codec == "none":
            return pd.Series([np.asarray(x, "<i8").tobytes() for x in ids])
        if codec == "dictionary":
            return pd.Series([np.asarray(x, "<i4").tobytes() for x in ids])
        return pd.Series([varbyte.encode_ids(x) for x in ids])

    return lists.select("term", F.size("ids").alias("n"), packed("ids").alias("blob"))


def decode(coded: DataFrame, codec: str = "both", codes: DataFrame | None = None) -> DataFrame:
    """The ``(term, ids)`` of ``encode``."""

    @F.pandas_udf("array<long>")
    def unpacked(blobs: pd.Series) -> pd.Series:
        if codec in ("none", "dictionary"):
            kind = "<i8" if codec == "none" else "<i4"
            return pd.Series([np.frombuffer(x, kind).astype(np.int64) for x in blobs])
        return pd.Series([varbyte.decode_ids(x) for x in blobs])

    lists = coded.select("term", unpacked("blob").alias("ids"))
    if codec in ("dictionary", "both"):
        rows = lists.select("term", F.explode("ids").alias("code")).join(codes, "code")
        lists = rows.groupBy("term").agg(F.array_sort(F.collect_list("item_id")).alias("ids"))
    return lists


def storage_report(coded: DataFrame) -> DataFrame:
    """``lists, postings, raw_bytes, coded_bytes, saving`` of an encoded index (raw: eight bytes an id)."""
    raw = (F.sum("n") * 8).cast("long")
    size = F.sum(F.length("blob")).cast("long")
    return coded.agg(
        F.count("*").alias("lists"), F.sum("n").cast("long").alias("postings"), raw.alias("raw_bytes"), size.alias("coded_bytes"), (1 - size / raw).alias("saving")
    )


def gap_bytes(rows: DataFrame) -> DataFrame:
    """Bytes of the gap coding by arithmetic alone, without coding: ``postings, coded_bytes``."""
    from pyspark.sql import Window

    gap = F.col("item_id") - F.coalesce(F.lag("item_id").over(Window.partitionBy("term").orderBy("item_id")), F.lit(0))
    size = sum((F.when(F.col("gap") >= (1 << s), 1).otherwise(0) for s in range(7, 63, 7)), F.lit(1))
    return rows.select(gap.alias("gap")).agg(F.count("*").alias("postings"), F.sum(size).cast("long").alias("coded_bytes"))
