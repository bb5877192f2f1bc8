"""Candidate augmentation: members close to a head stand in for it."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def pool(mapping: DataFrame, top_k: int, min_sim: float = 0.0) -> DataFrame:
    """``(head_id, member_id, place)``: the ``top_k`` members nearest to each head, by similarity, then id.

    ``mapping(item_id, head_id, score_to_head)``; the head itself is no member.
    """
    members = mapping.where((F.col("item_id") != F.col("head_id")) & (F.col("score_to_head") >= min_sim))
    place = F.row_number().over(Window.partitionBy("head_id").orderBy(F.desc("score_to_head"), "item_id"))
    return members.withColumn("place", place).where(F.col("place") <= top_k).select("head_id", F.col("item_id").alias("member_id"), "place")


def expand(cands: DataFrame, mapping: DataFrame, top_k: int = 2, min_sim: float = 0.0) -> DataFrame:
    """``cands(query_id, index_id)`` over heads to ``(query_id, head_id, member_id, place)``; the head has place 0."""
    heads = cands.select("query_id", F.col("index_id").alias("head_id"))
    own = heads.select("query_id", "head_id", F.col("head_id").alias("member_id"), F.lit(0).alias("place"))
    if top_k == 0:
        return own
    more = heads.join(pool(mapping, top_k, min_sim), "head_id").where("query_id <> member_id")
    return own.unionByName(more.select("query_id", "head_id", "member_id", "place"))


def accept(scored: DataFrame, threshold: float) -> DataFrame:
    """``(query_id, head_id, score, via)``: the best head of each query with any pair strictly above the threshold.

    ``scored(query_id, head_id, member_id, score)``; a member's match counts for its head. Highest score,
    then smallest head, then smallest member.
    """
    best = F.min(F.struct((-F.col("score")).alias("low"), "head_id", "member_id")).alias("m")
    return (
        scored.where(F.col("score") > threshold)
        .groupBy("query_id")
        .agg(best)
        .select("query_id", F.col("m.head_id").alias("head_id"), (-F.col("m.low")).alias("score"), F.col("m.member_id").alias("via"))
    )


def accept_in_two_passes(cands: DataFrame, mapping: DataFrame, score, threshold: float, top_k: int = 2, min_sim: float = 0.0):
    """``accept`` that scores members only for queries that no head takes. ``score(pairs)`` adds ``score``.

    Returns the assignment and the pairs of the second pass; saves up to ``k / (k + 1)`` of the predictions.
    """
    heads = cands.select("query_id", F.col("index_id").alias("head_id"), F.col("index_id").alias("member_id"))
    first = accept(score(heads), threshold)
    left = cands.join(first, "query_id", "left_anti")
    second_pairs = expand(left, mapping, top_k, min_sim).where("place > 0")
    second = accept(score(second_pairs), threshold)
    return first.unionByName(second), second_pairs
