"""Heads of clusters: chosen once, at a cluster's birth, by engagement and content."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def elect(members: DataFrame, weight: DataFrame, content: DataFrame) -> DataFrame:
    """``(cluster, head_id)`` of ``members(item_id, cluster)``.

    Order: engagement of ``weight(item_id, weight)``, quality and length of ``content(item_id, quality,
    n_chars)``, each the higher the better and 0 where unknown, then the smallest id.
    """
    known = members.join(weight, "item_id", "left").join(content, "item_id", "left")
    zero = lambda c: -F.coalesce(F.col(c), F.lit(0))
    order = F.struct(zero("weight").alias("w"), zero("quality").alias("q"), zero("n_chars").alias("n"), "item_id")
    return known.groupBy("cluster").agg(F.min(order)["item_id"].alias("head_id"))
