"""Mixing sources to target weights: capped water-filling and seeded repetitions, all in DataFrame functions.

The fixed point of "give each source its share, clamp at ``epochs`` times its size, reshare the excess by
weight" is reached directly: with sources in order of cap per weight, the clamped ones are a prefix, and
running sums give the level of the rest.

A source's repetitions are ``target / size``: the whole part for every document, and one more for some of
them, drawn in the order of a seeded hash of id and text until the words still wanted are reached. The end of
that order is one number for each source, found from sums over hash buckets, then over ever finer buckets
within the one that holds it while that has over ``SPLIT`` rows, and at last row by row. At last one document of about the size still missing (or over) is taken once more (or less). So a
row's repetitions follow from its source's few numbers and its own id: texts are neither sorted nor shuffled.

Defined cases: a null text has size 0 and is taken 0 words; a null source is a source of its own, last in
order; rows with equal id and text are drawn together, rows without an id by their text; a source of size 0 has target 0; extra columns are ignored;
an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from neardup.sources.lineage import written

#: Weights in order of the sources, repeating: fixed values of the query's contract.
WEIGHTS = (5.0, 2.0, 1.0)
EPOCHS, BITS, FEW, SPLIT = 3, 12, 10_000, 100_000


def word_count(text: str = "text") -> Column:
    """Number of maximal runs without ASCII white space."""
    return F.coalesce(F.regexp_count(text, F.lit("[^\\x20\\x09-\\x0D]+")), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights=WEIGHTS, epochs: int = EPOCHS) -> DataFrame:
    """``sizes(source, source_size)`` with ``weight`` and ``target``: shares of all words, capped and reshared."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*(F.lit(float(w)) for w in weights)), F.col("no") % len(weights) + 1)
    w = sizes.withColumn("no", F.row_number().over(by_name) - 1).withColumn("weight", weight)
    cap = F.col("source_size") * F.lit(epochs)
    order = Window.orderBy(cap / F.col("weight"), "no")
    whole = Window.partitionBy()
    w = (
        w.withColumn("cap", cap.cast("double"))
        .withColumn("before", F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("left", F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("total", F.sum("source_size").over(whole))
        .withColumn("level", (F.col("total") - F.col("before")) / F.col("left"))
    )
    # The first source in this order that its level does not clamp sets the level of all after it.
    ratio = F.col("cap") / F.col("weight")
    free = F.min(F.when(F.col("level") <= ratio, F.struct(ratio.alias("ratio"), "no", "level"))).over(whole)
    return w.withColumn("free", free).select(
        "source", "source_size", "weight", F.least("cap", F.coalesce(F.col("free.level") * F.col("weight"), F.col("cap"))).alias("target")
    )


def _drawn(seed: int) -> Column:
    """A row's place in the seeded order, from 0 to 2^63, of ``docs(doc_id, text)``."""
    return F.shiftrightunsigned(F.xxhash64("doc_id", "text", F.lit(seed)), 1)


def _small(df: DataFrame) -> DataFrame:
    """A table of one row a source, written, and broadcast where it is small."""
    df = written(df)
    return F.broadcast(df) if df.count() <= FEW else df


def _at(source: str = "s") -> Column:
    return F.col("source").eqNullSafe(F.col(source))


def decisions(sized: DataFrame, weights=WEIGHTS, epochs: int = EPOCHS, split: int = SPLIT) -> DataFrame:
    """One row a source of ``sized(source, size, h)``, ``h`` the place in the order: ``s, source_size, target, whole, until, turned, by``.

    A document is taken ``whole`` times, once more if drawn up to ``until``, and ``by`` more if drawn at ``turned``.
    """
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    goal = (
        targets(per, weights, epochs)
        .withColumn("whole", F.least(F.floor(rate), F.lit(epochs)).cast("long"))
        .withColumn("wanted", F.when(F.col("whole") < epochs, F.col("target") - F.col("whole") * F.col("source_size")).otherwise(F.lit(0.0)))
        .select(F.col("source").alias("s"), "source_size", "target", "whole", "wanted")
    )
    goal = _small(goal)
    placed = sized
    inside, bits = placed.withColumn("before", F.lit(0).cast("long")), BITS
    while True:
        bucket = F.shiftright("h", 63 - bits).alias("bucket")
        upto = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
        sums = inside.groupBy("source", "before", bucket).agg(F.sum("size").alias("words"), F.count("*").alias("n"))
        sums = sums.withColumn("sum", F.col("before") + F.sum("words").over(upto))
        edge = (
            sums.join(goal, _at())
            .where((F.col("sum") - F.col("words") < F.col("wanted")) & (F.col("wanted") <= F.col("sum")))
            .groupBy("s")
            .agg(F.min(F.struct("bucket", (F.col("sum") - F.col("words")).alias("before"), "wanted", "n")).alias("e"))
            .select("s", F.col("e.bucket").alias("edge"), "e.before", "e.wanted", "e.n")
        )
        edge = _small(edge)
        inside = placed.join(edge, _at() & (F.shiftright("h", 63 - bits) == F.col("edge")))
        if bits + BITS > 62 or (edge.agg(F.max("n")).first()[0] or 0) <= split:
            break
        inside, bits = inside.select("source", "size", "h", "before"), bits + BITS
    running = F.col("before") + F.sum("size").over(Window.partitionBy("source").orderBy("h").rangeBetween(Window.unboundedPreceding, 0))
    stop = inside.withColumn("got", running).groupBy("s").agg(
        F.min(F.struct(F.abs(F.col("got") - F.col("wanted")).alias("off"), "h", "got")).alias("at"), F.first("before").alias("before"), F.first("edge").alias("edge"), F.first("wanted").alias("wanted")
    )
    # Stopping before the first row of the bucket may be nearer than after any of its rows.
    none = F.col("wanted") - F.col("before") <= F.col("at.off")
    first = F.shiftleft(F.col("edge"), 63 - bits) - 1
    stop = stop.select(F.col("s").alias("s2"), F.when(none, first).otherwise(F.col("at.h")).alias("until"), F.when(none, F.col("before")).otherwise(F.col("at.got")).alias("got"))
    cut = goal.join(stop, F.col("s").eqNullSafe(F.col("s2")), "left").drop("s2")
    cut = cut.withColumn("until", F.coalesce("until", F.lit(-1).cast("long"))).withColumn("short", F.col("wanted") - F.coalesce("got", F.lit(0)))
    cut = _small(cut)
    miss = F.abs(F.col("size") - F.abs("short"))
    can = F.when(F.col("short") > 0, (F.col("h") > F.col("until")) & (F.col("whole") < epochs)).otherwise(F.col("h") <= F.col("until"))
    turned = (
        placed.join(cut, _at())
        .where(can & (miss < F.abs("short")))
        .groupBy("s")
        .agg(F.min(F.struct(miss.alias("miss"), "h", F.signum("short").cast("long").alias("by"))).alias("t"))
        .select(F.col("s").alias("s2"), F.col("t.h").alias("turned"), "t.by")
    )
    return _small(cut.join(turned, F.col("s").eqNullSafe(F.col("s2")), "left").select("s", "source_size", "target", "whole", "until", "turned", "by"))


def _times(epochs: int, drawn: Column, at: str = "") -> Column:
    col = lambda c: F.col(at + c)
    extra = (drawn <= col("until")).cast("long") + F.when(drawn == col("turned"), col("by")).otherwise(F.lit(0))
    return F.least(col("whole") + extra, F.lit(epochs)).cast("long")


def plan(docs: DataFrame, weights=WEIGHTS, epochs: int = EPOCHS, seed: int = 0) -> DataFrame:
    """One row per row of ``docs(doc_id, source, text)``: ``doc_id, size, source, source_size, target, times``."""
    sized = written(docs.select("doc_id", "source", word_count().alias("size"), _drawn(seed).alias("h")))
    chosen = decisions(sized, weights, epochs)
    return sized.join(chosen, _at()).select("doc_id", "size", "source", "source_size", "target", _times(epochs, F.col("h")).alias("times"))


def mix(docs: DataFrame, weights=WEIGHTS, epochs: int = EPOCHS, seed: int = 0) -> DataFrame:
    """``docs`` with every document as often as the mix takes it; columns unchanged."""
    sized = written(docs.select("source", word_count().alias("size"), _drawn(seed).alias("h")))
    chosen = decisions(sized, weights, epochs).select(F.col("s").alias("__s"), F.struct("whole", "until", "turned", "by").alias("__d"))
    times = _times(epochs, _drawn(seed), "__d.").cast("int")
    few = F.broadcast(chosen) if chosen.count() <= FEW else chosen
    rows = docs.join(few, _at("__s")).withColumn("__times", times).where("__times > 0")
    return rows.withColumn("__times", F.explode(F.sequence(F.lit(1), F.col("__times")))).select(*docs.columns)
