"""Measures of accuracy, cost, corpus and engagement."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _by_score(df: DataFrame, score: str, label: str) -> DataFrame:
    """Positives and rows by distinct score with running sums from the top; ties are one step."""
    g = df.groupBy(F.col(score).alias("s")).agg(F.sum(label).cast("long").alias("p"), F.count("*").alias("n"))
    top = Window.orderBy(F.desc("s"))
    upto = top.rowsBetween(Window.unboundedPreceding, 0)
    return g.withColumn("tp", F.sum("p").over(upto)).withColumn("rows", F.sum("n").over(upto)).withColumn("before", F.col("rows") - F.col("n"))


def pr_auc(df: DataFrame, score: str = "score", label: str = "label") -> DataFrame:
    """Step-wise average precision, one row ``pr_auc``; null without positives."""
    g = _by_score(df, score, label)
    value = F.sum(F.col("p") * F.col("tp") / F.col("rows")) / F.sum("p")
    return g.agg(F.round(value, 6).alias("pr_auc"))


def roc_auc(df: DataFrame, score: str = "score", label: str = "label") -> DataFrame:
    """Rank-sum area with mean ranks for ties, one row ``roc_auc``; null with one class only."""
    g = _by_score(df, score, label)
    # From the top: rank counted from the bottom is total - before - (n - 1) / 2.
    total, pos = F.max("rows"), F.sum("p")
    above = F.sum(F.col("p") * (F.col("before") + (F.col("n") - 1) / 2))
    ranks = pos * total - above
    value = (ranks - pos * (pos + 1) / 2) / F.nullif(pos * (total - pos), F.lit(0))
    return g.agg(F.round(value, 6).alias("roc_auc"))


def at_threshold(df: DataFrame, t: float, score: str = "score", label: str = "label") -> DataFrame:
    """``tp, fp, fn, precision, recall`` of keeping scores strictly above ``t``."""
    hit = F.col(score) > t
    tp, fp, fn = (F.count_if(x).cast("long") for x in (hit & (F.col(label) == 1), hit & (F.col(label) == 0), ~hit & (F.col(label) == 1)))
    one = df.agg(tp.alias("tp"), fp.alias("fp"), fn.alias("fn"))
    share = lambda a, b: F.round(F.col(a) / F.nullif(F.col(a) + F.col(b), F.lit(0)), 6)
    return one.withColumn("precision", share("tp", "fp")).withColumn("recall", share("tp", "fn"))


def operating_point(df: DataFrame, min_precision: float, score: str = "score", label: str = "label") -> DataFrame:
    """``threshold, precision, recall``: most recall among the scores whose precision is high enough; then the highest score."""
    g = _by_score(df, score, label)
    total = F.max("tp").over(Window.partitionBy())
    g = g.withColumn("precision", F.col("tp") / F.col("rows")).withColumn("recall", F.col("tp") / total)
    best = g.where(F.col("precision") >= min_precision).orderBy(F.desc("recall"), F.desc("s")).limit(1)
    return best.select(F.col("s").alias("threshold"), F.round("precision", 6).alias("precision"), F.round("recall", 6).alias("recall"))


def candidate_recall(cands: DataFrame, positives: DataFrame) -> DataFrame:
    """``positives, missed, recall``: accepted pairs ``(a, b)`` that are among the candidates."""
    marked = positives.select("a", "b").join(cands.select("a", "b", F.lit(1).alias("hit")), ["a", "b"], "left")
    n, missed = F.count("*"), F.count_if(F.col("hit").isNull())
    return marked.agg(n.alias("positives"), missed.alias("missed"), F.round(1 - missed / n, 6).alias("recall"))


def recall_at_k(found: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """Share of the true ``k`` nearest (``exact(query_id, index_id, distance)``) that ``found`` returns."""
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("distance", "index_id"))
    near = exact.withColumn("r", rank).where(F.col("r") <= k)
    hit = near.join(found.select("query_id", "index_id", F.lit(1).alias("hit")), ["query_id", "index_id"], "left")
    return hit.agg(F.count("*").alias("wanted"), F.count("hit").alias("found"), F.round(F.count("hit") / F.count("*"), 6).alias("recall"))


def recall_at_distance(found: DataFrame, exact: DataFrame, distances: list[int]) -> DataFrame:
    """For each distance the share of pairs ``exact(a, b, distance)`` within it that ``found(a, b)`` returns."""
    hit = exact.join(found.select("a", "b", F.lit(1).alias("hit")), ["a", "b"], "left")
    at = hit.withColumn("within", F.explode(F.array(*(F.lit(d) for d in distances)))).where(F.col("distance") <= F.col("within"))
    return at.groupBy("within").agg(F.count("*").alias("pairs"), F.count("hit").alias("found"), F.round(F.count("hit") / F.count("*"), 6).alias("recall"))


def recall_lift(without: DataFrame, with_: DataFrame, truth: DataFrame) -> DataFrame:
    """Recall of two runs ``(query_id, head_id)`` against ``truth`` and the gain, absolute and relative."""
    t = truth.select("query_id", "head_id")
    n = t.agg(F.count("*").alias("n"))
    a = t.join(without, ["query_id", "head_id"], "left_semi").agg(F.count("*").alias("a"))
    b = t.join(with_, ["query_id", "head_id"], "left_semi").agg(F.count("*").alias("b"))
    one = n.crossJoin(a).crossJoin(b)
    return one.select(
        F.round(F.col("a") / F.col("n"), 6).alias("recall_without"), F.round(F.col("b") / F.col("n"), 6).alias("recall_with"),
        F.round((F.col("b") - F.col("a")) / F.col("n"), 6).alias("gain"), F.round((F.col("b") - F.col("a")) / F.nullif(F.col("a"), F.lit(0)), 6).alias("relative_gain"),
    )


def sizes(mapping: DataFrame) -> DataFrame:
    """``(head_id, size)`` of a mapping ``(item_id, head_id)``."""
    return mapping.groupBy("head_id").agg(F.count("*").alias("size"))


def duplicate_ratio(mapping: DataFrame, n_items: int | None = None, exclude: DataFrame | None = None) -> DataFrame:
    """``items, duplicates, ratio``: share of items in clusters of two or more; ``exclude(item_id)`` does not count."""
    sized = mapping.join(sizes(mapping), "head_id")
    if exclude is not None:
        sized = sized.join(exclude, "item_id", "left_anti")
    dup = F.count_if(F.col("size") >= 2)
    total = F.count("*") if n_items is None else F.lit(n_items).cast("long")
    return sized.agg(total.alias("items"), dup.alias("duplicates"), F.round(dup / total, 6).alias("ratio"))


def cluster_stats(mapping: DataFrame) -> DataFrame:
    """``clusters, items, mode_size, mean_size, largest`` over clusters of two or more; the smallest mode."""
    many = sizes(mapping).where(F.col("size") >= 2)
    by = many.groupBy("size").agg(F.count("*").alias("n"))
    return by.agg(
        F.coalesce(F.sum("n"), F.lit(0)).alias("clusters"), F.coalesce(F.sum(F.col("n") * F.col("size")), F.lit(0)).alias("items"),
        F.min(F.struct((-F.col("n")).alias("low"), "size"))["size"].alias("mode_size"),
        F.round(F.sum(F.col("n") * F.col("size")) / F.sum("n"), 6).alias("mean_size"), F.max("size").alias("largest"),
    )


def size_distribution(mapping: DataFrame) -> DataFrame:
    """``(size, clusters)`` of clusters of two or more."""
    return sizes(mapping).where(F.col("size") >= 2).groupBy("size").agg(F.count("*").alias("clusters"))


def power_law(distribution: DataFrame) -> DataFrame:
    """Exponent of ``(size, clusters)``: the usual approximate discrete estimate from size 2, and the log-log slope."""
    n = F.sum("clusters")
    alpha = 1 + n / F.sum(F.col("clusters") * F.log(F.col("size") / 1.5))
    slope = F.regr_slope(F.log("clusters"), F.log("size"))
    return distribution.agg(n.alias("clusters"), F.round(alpha, 6).alias("exponent"), F.round(slope, 6).alias("slope"))


def trend(mapping: DataFrame, days: DataFrame, exclude: DataFrame | None = None) -> DataFrame:
    """``day, items, duplicates, ratio`` by day of arrival."""
    sized = mapping.join(sizes(mapping), "head_id").join(days, "item_id")
    if exclude is not None:
        sized = sized.join(exclude, "item_id", "left_anti")
    dup = F.count_if(F.col("size") >= 2)
    return sized.groupBy("day").agg(F.count("*").alias("items"), dup.alias("duplicates"), F.round(dup / F.count("*"), 6).alias("ratio"))


def false_positives(copies: DataFrame, truth: DataFrame) -> DataFrame:
    """``reviewed, wrong, upper``: copies ``(original_id, item_id)`` not in the truth, and the 95 % bound of the rate if none is wrong."""
    marked = copies.join(truth.select("original_id", "item_id", F.lit(1).alias("ok")), ["original_id", "item_id"], "left")
    wrong = F.count_if(F.col("ok").isNull())
    return marked.agg(F.count("*").alias("reviewed"), wrong.alias("wrong"), F.when(wrong == 0, F.round(3 / F.count("*"), 6)).alias("upper"))


def graph_shrink(before: DataFrame, after: DataFrame) -> DataFrame:
    """Nodes, edges and mean degree of two bipartite graphs ``(left, item, weight)`` and the factor between them."""

    def counts(g, tag):
        return g.agg(F.countDistinct("item").alias(f"items_{tag}"), F.countDistinct("left").alias(f"left_{tag}"), F.count("*").alias(f"edges_{tag}"))

    one = counts(before, "before").crossJoin(counts(after, "after"))
    degree = lambda t: F.round(F.col(f"edges_{t}") / F.col(f"items_{t}"), 6).alias(f"degree_{t}")
    return one.select("*", F.round(F.col("items_before") / F.col("items_after"), 6).alias("factor"), degree("before"), degree("after"))


def lift(df: DataFrame, arm: str = "arm", value: str = "value") -> DataFrame:
    """``control, treated, lift``: means by arm (0 and 1) and treated over control less one."""
    mean = lambda a: F.avg(F.when(F.col(arm) == a, F.col(value)))
    return df.agg(F.round(mean(0), 6).alias("control"), F.round(mean(1), 6).alias("treated"), F.round(mean(1) / mean(0) - 1, 6).alias("lift"))


def agreement(pairs: DataFrame, votes: str = "votes") -> DataFrame:
    """``pairs, unanimous, mean_agreement``: of judges' votes with their majority."""
    n, ones = F.size(votes), F.aggregate(votes, F.lit(0), lambda s, v: s + v)
    with_majority = F.greatest(ones, n - ones)
    return pairs.agg(F.count("*").alias("pairs"), F.count_if(with_majority == n).alias("unanimous"), F.round(F.avg(with_majority / n), 6).alias("mean_agreement"))


def balance(pairs: DataFrame) -> DataFrame:
    """``pairs, positives, share``."""
    return pairs.agg(F.count("*").alias("pairs"), F.sum("label").cast("long").alias("positives"), F.round(F.avg("label"), 6).alias("share"))


def pairwise(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """Precision, recall, F1 and Rand of two partitions ``(item_id, head_id)``, by contingency counts alone."""
    j = pred.select("item_id", F.col("head_id").alias("p")).join(truth.select("item_id", F.col("head_id").alias("t")), "item_id")
    two = lambda n: n * (n - 1) / 2
    cells = j.groupBy("p", "t").agg(F.count("*").alias("n"))
    both = cells.agg(F.sum(two(F.col("n"))).alias("both"), F.sum("n").alias("items"))
    one = lambda k: cells.groupBy(k).agg(F.sum("n").alias("n")).agg(F.sum(two(F.col("n"))).alias(f"in_{k}"))
    r = both.crossJoin(one("p")).crossJoin(one("t"))
    p, q = F.col("both") / F.nullif(F.col("in_p"), F.lit(0.0)), F.col("both") / F.nullif(F.col("in_t"), F.lit(0.0))
    rand = 1 - (F.col("in_p") + F.col("in_t") - 2 * F.col("both")) / two(F.col("items"))
    return r.select(F.round(p, 6).alias("precision"), F.round(q, 6).alias("recall"), F.round(2 * p * q / (p + q), 6).alias("f1"), F.round(rand, 6).alias("rand"))
