"""Greedy approximate cut of components: a head keeps what matches it, the rest goes round again."""

from __future__ import annotations

import hashlib
from itertools import count

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.functions import bits as B
from neardup.operators import search
from neardup.sources.lineage import drop_written, written

#: Components up to this size may be cut in one task.
SMALL = 10_000


def _order(head_rule: str, seed: int, weight: str | None):
    drawn = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("component").cast("string"), F.col("item_id").cast("string")))
    if head_rule == "seeded":
        return F.struct(drawn.alias("o"), "item_id")
    if head_rule == "lowest":
        return F.struct("item_id")
    if head_rule == "engagement":
        return F.struct((-F.coalesce(F.col(weight), F.lit(0))).alias("o"), "item_id")
    raise ValueError(head_rule)


def greedy_cut(
    components: DataFrame, items: DataFrame, max_distance: int | None = None, scorer=None, threshold: float | None = None,
    seed: int = 0, head_rule: str = "seeded", log: list | None = None,
) -> DataFrame:
    """``(item_id, head_id, distance or score)`` from ``components(item, component)``.

    Matching means at most ``max_distance`` differing bits of ``items(item_id, words)``, or a score of
    ``scorer`` strictly above ``threshold``. Every round takes at least the head out of each component, so
    it ends; a head without matches is a cluster of its own. ``engagement`` needs ``items.weight``.
    """
    weight = "weight" if head_rule == "engagement" else None
    keep = ["item_id", "component", "words", *([weight] if weight else [])]
    pending = written(components.select(F.col("item").alias("item_id"), "component").join(items, "item_id").select(*keep))
    done = []
    for n in count():
        heads = pending.groupBy("component").agg(F.min(_order(head_rule, seed, weight))["item_id"].alias("head_id"))
        if scorer is None:
            words = pending.select(F.col("item_id").alias("head_id"), F.col("words").alias("head_words"))
            at = pending.join(heads.join(words, "head_id"), "component")
            judged = at.withColumn("value", B.hamming("words", "head_words").cast("double")).drop("head_words")
            hit = F.col("value") <= max_distance
        else:
            at = pending.join(heads, "component")
            others = at.where("item_id <> head_id")
            scored = scorer.score(others, pending.select("item_id", "words"), "head_id", "item_id").withColumnRenamed("score", "value")
            own = at.where("item_id = head_id").withColumn("value", F.lit(1.0))
            judged = own.select(*keep, "head_id", "value").unionByName(scored.select(*keep, "head_id", "value"))
            hit = F.col("value") > threshold
        judged = written(judged.withColumn("taken", hit | (F.col("item_id") == F.col("head_id"))))
        done.append(judged.where("taken").select("item_id", "head_id", "value"))
        left = judged.where("not taken").select(*keep)
        if log is not None:
            log.append({"round": n + 1, "pending": left.count()})
        if n > 0:
            drop_written(pending)
        pending = left
        if left.isEmpty():
            break
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out


def cut_by_pairs(items: DataFrame, near: DataFrame, seed: int = 0, component: int = 0) -> DataFrame:
    """``greedy_cut`` of one component with seeded heads from all its pairs within the distance: ``(item_id, head_id)``.

    Items in the order of the draw: one without an earlier head among its pairs ``near(a, b)`` is a head, another goes to
    the first such head. A round decides every item whose earlier partners are decided, so rounds are few however many
    heads there are.
    """
    drawn = F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(str(component)), F.col("item_id").cast("string")))
    place = lambda c: items.select(F.col("item_id").alias(c), F.struct(drawn.alias("o"), "item_id").alias(f"p{c}"))
    both = near.select("a", "b").join(place("a"), "a").join(place("b"), "b")
    first = F.col("pa") < F.col("pb")
    pairs = written(both.select(F.when(first, F.col("pa")).otherwise(F.col("pb")).alias("early"), F.when(first, F.col("b")).otherwise(F.col("a")).alias("late")).distinct())
    left, heads, round_ = pairs, None, 0
    while not left.isEmpty():
        late = left.select("late").distinct()
        new = written(left.select("early").distinct().join(late, F.col("early.item_id") == F.col("late"), "left_anti").withColumnRenamed("early", "head"))
        heads = new if heads is None else heads.unionByName(new)
        taken = left.join(new, left["early"] == new["head"], "left_semi").select("late").distinct()
        rest = left.join(taken, "late", "left_anti")
        after = written(rest.join(taken.select(F.col("late").alias("gone")), F.col("early.item_id") == F.col("gone"), "left_anti"))
        if round_:
            drop_written(left)
        left, round_ = after, round_ + 1
    if heads is None:
        return items.select("item_id", F.col("item_id").alias("head_id"))
    # An item that no head took is a head as well, with or without pairs.
    joined = pairs.join(heads, pairs["early"] == heads["head"], "left_semi").groupBy("late").agg(F.min("early")["item_id"].alias("head_id"))
    return items.select("item_id").join(joined.withColumnRenamed("late", "item_id"), "item_id", "left").select("item_id", F.coalesce("head_id", "item_id").alias("head_id"))


def cut_all(items: DataFrame, max_distance: int, seed: int = 0) -> DataFrame:
    """``(item_id, head_id)``: the greedy cut of ``items(item_id, words)`` as one component, number 0; every pair is compared once.

    Of equal words only the first of the draw is compared, the others go with it.
    """
    drawn = F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit("0"), F.col("item_id").cast("string")))
    firsts = items.groupBy("words").agg(F.min(F.struct(drawn.alias("o"), "item_id"))["item_id"].alias("first"))
    firsts = written(firsts)
    reps = firsts.select(F.col("first").alias("item_id"), "words")
    heads = cut_by_pairs(reps, search.near_everywhere(reps, max_distance), seed).withColumnRenamed("item_id", "first")
    return items.join(firsts, "words").select("item_id", "first").join(heads, "first").select("item_id", "head_id")


def cut_small(components: DataFrame, items: DataFrame, max_distance: int, seed: int = 0) -> DataFrame:
    """``greedy_cut`` by distance with seeded heads, one task a component of at most ``SMALL`` items: ``(item_id, head_id, value)``.

    Larger components must go to ``greedy_cut``; ``route`` tells them apart.
    """

    def cut(rows: pd.DataFrame) -> pd.DataFrame:
        ids = rows["item_id"].to_numpy()
        words = np.stack([np.asarray(w, np.uint64) for w in rows["words"]])
        draw = [hashlib.md5(f"{seed}|{rows['component'].iloc[0]}|{i}".encode()).hexdigest() for i in ids]
        left, head, value = np.lexsort((ids, draw)), np.empty(len(ids), np.int64), np.zeros(len(ids))
        while len(left):
            first = left[0]
            far = np.bitwise_count(words[left] ^ words[first]).sum(1)
            hit = (far <= max_distance) | (left == first)
            head[left[hit]], value[left[hit]] = ids[first], far[hit]
            left = left[~hit]
        return pd.DataFrame({"item_id": ids, "head_id": head, "value": value})

    rows = components.select(F.col("item").alias("item_id"), "component").join(items.select("item_id", "words"), "item_id")
    return rows.groupBy("component").applyInPandas(cut, "item_id long, head_id long, value double")


def route(components: DataFrame, small: int = SMALL) -> tuple[DataFrame, DataFrame]:
    """Components of at most ``small`` items, and larger ones."""
    sizes = components.groupBy("component").agg(F.count("*").alias("n"))
    sized = components.join(sizes, "component")
    return sized.where(F.col("n") <= small).drop("n"), sized.where(F.col("n") > small).drop("n")


def cut(components: DataFrame, items: DataFrame, max_distance: int, seed: int = 0) -> DataFrame:
    """Small components in one task each, larger ones in distributed rounds; the same result either way."""
    few, many = route(written(components))
    out = cut_small(few, items, max_distance, seed)
    return out if many.isEmpty() else out.unionByName(greedy_cut(many, items, max_distance, seed=seed))
