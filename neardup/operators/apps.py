"""Applications on top of a mapping ``(item_id, head_id)``; an item without a row is a cluster of its own."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from neardup.config import DEFAULT, Config
from neardup.functions import bits as B
from neardup.functions import text as T
from neardup.operators.search import shared
from neardup.operators.signatures import collapse_exact
from neardup.operators.terms import exploded, search_terms
from neardup.sources.lineage import written


def with_head(df: DataFrame, mapping: DataFrame) -> DataFrame:
    """``df`` with the cluster of its ``item_id``."""
    return df.join(mapping.select("item_id", "head_id"), "item_id", "left").withColumn("head_id", F.coalesce("head_id", "item_id"))


def dedupe_ranked(results: DataFrame, mapping: DataFrame) -> DataFrame:
    """``results(request, rank, item_id)`` with the best-ranked item of each cluster only; ranks are counted anew as ``place``."""
    first = Window.partitionBy("request", "head_id").orderBy("rank", "item_id")
    kept = with_head(results, mapping).withColumn("n", F.row_number().over(first)).where("n = 1")
    place = F.row_number().over(Window.partitionBy("request").orderBy("rank", "item_id"))
    return kept.select("request", "rank", "item_id", "head_id", place.alias("place"))


def feed(results: DataFrame, mapping: DataFrame | None, dedupe: bool = True) -> DataFrame:
    """A ranked list with or without the filter."""
    if dedupe:
        return dedupe_ranked(results, mapping)
    place = F.row_number().over(Window.partitionBy("request").orderBy("rank", "item_id"))
    return results.select("request", "rank", "item_id", F.col("item_id").alias("head_id"), place.alias("place"))


def aggregate_metadata(bookmarks: DataFrame, mapping: DataFrame) -> DataFrame:
    """Per cluster: ``head_id, bookmarks, users, weight, boards`` pooled over its items; ``bookmarks(item_id, user_id, weight, board)``."""
    return (
        with_head(bookmarks, mapping)
        .groupBy("head_id")
        .agg(
            F.count("*").alias("bookmarks"), F.countDistinct("user_id").alias("users"), F.round(F.sum("weight"), 4).alias("weight"),
            F.array_join(F.array_sort(F.collect_set("board")), ",").alias("boards"),
        )
    )


def cluster_keywords(texts: DataFrame, mapping: DataFrame, k: int = 5, min_length: int = 4) -> DataFrame:
    """``head_id, word, items, place``: the words most items of a cluster hold, then in order of words."""
    words = with_head(texts, mapping).select("head_id", "item_id", F.explode(F.array_distinct(T.words())).alias("word"))
    counted = words.where(F.length("word") >= min_length).groupBy("head_id", "word").agg(F.countDistinct("item_id").alias("items"))
    place = F.row_number().over(Window.partitionBy("head_id").orderBy(F.desc("items"), "word"))
    return counted.withColumn("place", place).where(F.col("place") <= k)


def condense_graph(edges: DataFrame, mapping: DataFrame) -> DataFrame:
    """Bipartite ``edges(left, item, weight)`` with items of a cluster as one node; total weight stays."""
    heads = with_head(edges.withColumnRenamed("item", "item_id"), mapping)
    return heads.groupBy("left", F.col("head_id").alias("item")).agg(F.sum("weight").alias("weight"))


def canonical(mapping: DataFrame, items: DataFrame, contexts: DataFrame) -> DataFrame:
    """``context, head_id, item_id``: for each language context the member in that language, else the most used one.

    ``items(item_id, lang, weight)``, ``contexts(context)``; then smallest id.
    """
    members = with_head(items, mapping)
    at = members.crossJoin(F.broadcast(contexts))  # a handful of languages
    best = F.min(F.struct((F.col("lang") != F.col("context")).alias("other"), (-F.col("weight")).alias("low"), "item_id"))
    return at.groupBy("context", "head_id").agg(best["item_id"].alias("item_id"))


def passages(items: DataFrame, size: int, step: int) -> DataFrame:
    """Sliding windows of words ``(item_id, passage, text)``; a short text is one window. Whole texts, no cap."""
    w = items.select("item_id", T.words().alias("w"))
    starts = F.sequence(F.lit(1), F.greatest(F.size("w") - size + 1, F.lit(1)), F.lit(step))
    runs = F.transform(starts, lambda i: F.array_join(F.slice("w", i, size), " "))
    return w.select("item_id", F.posexplode(runs).alias("passage", "text"))


def copies_of(originals: DataFrame, corpus: DataFrame, anchor: int = 8) -> DataFrame:
    """``(original_id, item_id)``: items that hold the whole text of an original, found by passages and checked.

    Every run of ``anchor`` words of the corpus is a posting; an original is looked up by its first run (its
    whole text, if shorter, by containment of it as a run of words). Texts are compared as words.
    """
    o = originals.select(F.col("item_id").alias("original_id"), T.words().alias("w")).where(F.size("w") > 0)
    o = o.select("original_id", F.concat(F.lit(" "), F.array_join("w", " "), F.lit(" ")).alias("full"), F.least(F.size("w"), F.lit(anchor)).alias("n"), F.array_join(F.slice("w", 1, anchor), " ").alias("key"))
    lengths = [r["n"] for r in o.select("n").distinct().collect()]  # at most ``anchor`` numbers
    w = corpus.select("item_id", T.words().alias("w"))
    joined = F.concat(F.lit(" "), F.array_join("w", " "), F.lit(" ")).alias("body")
    out = None
    for n in lengths:
        keys = w.select("item_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - n + 1, F.lit(1))), lambda i: F.array_join(F.slice("w", i, n), " ")))).alias("key"))
        hits = keys.join(o.where(F.col("n") == n), "key").select("original_id", "item_id", "full")
        out = hits if out is None else out.unionByName(hits)
    if out is None:
        return w.select(F.col("item_id").alias("original_id"), "item_id").limit(0)
    return out.join(w.select("item_id", joined), "item_id").where(F.col("body").contains(F.col("full"))).select("original_id", "item_id").distinct()


def edited_copies(originals: DataFrame, corpus: DataFrame, size: int = 12, step: int = 4, cfg: Config = DEFAULT, salts: int = 1) -> DataFrame:
    """``(original_id, item_id, windows, share)``: items that hold passages near to those of an original, edited or in part.

    Windows of ``size`` words, at every word of the originals (a word of an original is in up to ``size`` of them) and at
    every ``step``-th of the corpus, are signed and searched by terms; a pair of windows is near within
    ``cfg.design_distance`` bits. ``windows`` counts an original's near windows, ``share`` divides by all of its own. A
    copied run of ``size + step - 1`` words holds a whole corpus window, so it is found where it has no edit; other near
    windows are found with the layout's probability. Shorter originals are left to ``copies_of``. Equal signatures are one
    entry on either side; windows without words are left out, and an original without words has no row.
    """
    sign = T.signature_udf(cfg.bits)

    def windows(df: DataFrame, by: int) -> DataFrame:
        runs = passages(df, size, by).where("text <> ''")
        return written(runs.select(F.struct("item_id", "passage").alias("item_id"), sign("text").alias("words")))

    left, right = windows(originals, 1), windows(corpus, step)
    (a, of_a), (b, of_b) = ((written(d) for d in collapse_exact(side)) for side in (left, right))
    cfg = cfg.for_items(b.count())
    q, i = ((exploded(search_terms(side, cfg)).select(F.col("item_id").alias(name), "term")) for side, name in ((a, "query_id"), (b, "index_id")))
    found = shared(q, i, "rows", salts).select("query_id", "index_id").distinct()
    words = lambda side, name: side.select(F.col("item_id").alias(name), F.col("words").alias(f"__{name}"))
    near = found.join(words(a, "query_id"), "query_id").join(words(b, "index_id"), "index_id")
    near = near.where(B.hamming("__query_id", "__index_id") <= cfg.design_distance).select("query_id", "index_id")
    spread = lambda of, name, out: of.select(F.col("rep_id").alias(name), F.col("item_id").alias(out))
    near = near.join(spread(of_b, "index_id", "at"), "index_id").select("query_id", F.col("at.item_id").alias("item_id")).distinct()
    hits = near.join(spread(of_a, "query_id", "of"), "query_id").groupBy(F.col("of.item_id").alias("original_id"), "item_id").agg(F.count("*").alias("windows"))
    every = left.groupBy(F.col("item_id.item_id").alias("original_id")).agg(F.count("*").alias("n"))
    return hits.join(every, "original_id").select("original_id", "item_id", "windows", F.round(F.col("windows") / F.col("n"), 6).alias("share"))


def pool_labels(labels: DataFrame, mapping: DataFrame) -> DataFrame:
    """``item_id, pooled``: labels ``(item_id, label)`` replaced by the majority of the cluster; ties count as 1."""
    heads = with_head(labels, mapping)
    mean = heads.groupBy("head_id").agg((F.avg("label") >= 0.5).cast("int").alias("pooled"))
    return heads.join(mean, "head_id").select("item_id", "pooled")
