"""Planted inputs derived from the given tables by integer and md5 arithmetic alone, so SQL can rebuild them."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from neardup.functions import text as T
from neardup.operators import closure, search, sets, signatures
from neardup.operators.terms import exploded, search_terms
from neardup.sources.lineage import drop_written, kept, written
from neardup.sources.tables import table, text_items, vector_items

#: Flipped bits of the planted copies, and the words of the overlay: fixed values.
FLIPS = (0, 1, 2, 4, 8, 16)
BANNER = "follow this board for more great ideas like this one every day"
KINDS = ("crop", "flip", "rotate", "scale", "noise", "overlay")


def h32(*parts) -> Column:
    """First eight hex digits of the md5 of the parts joined by ``|``, as a number."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *(c.cast("string") for c in cols))), 1, 8), 16, 10).cast("long")


def vector_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sign bits of the given vectors: ``(item_id, words)``."""
    return signatures.binarize(vector_items(spark, sf_dir), 64)


def document_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Signatures of the documents, a snapshot of the application: ``(item_id, words)``."""
    return kept(spark, ("document_words",), [f"{sf_dir}/documents.parquet"], lambda: signatures.text_bits(text_items(spark, sf_dir)))


def arrivals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(item_id, arrival, day)``: a document arrives with event ``doc_id * (events // documents)``."""
    docs, events = table(spark, sf_dir, "documents"), table(spark, sf_dir, "events")
    each = max(1, events.count() // max(1, docs.count()))
    at = events.select((F.col("event_id") / each).cast("long").alias("item_id"), "event_id", F.col("ts").alias("arrival"))
    at = at.where(F.col("event_id") == F.col("item_id") * each)
    return docs.select(F.col("doc_id").alias("item_id")).join(at, "item_id").select("item_id", "arrival", F.datediff("arrival", F.lit("2024-01-01")).alias("day"))


def bookmarks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(event_id, ts, user_id, action, weight, item_id, board)``: an event as a bookmark of a document."""
    docs = table(spark, sf_dir, "documents")
    n = max(1, docs.count())
    e = table(spark, sf_dir, "events").select(
        "event_id", "ts", "user_id", F.col("event_type").alias("action"), F.col("value").alias("weight"), ((F.col("event_id") * 7919) % n).alias("item_id")
    )
    return e.join(docs.select(F.col("doc_id").alias("item_id"), F.col("source").alias("board")), "item_id")


def user_locale(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(user_id, nation, region, lang)``."""
    c, n, r = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    lang = F.element_at(F.array(*map(F.lit, ("en", "fr", "de", "es"))), (F.col("n_nationkey") % 4 + 1).cast("int"))
    joined = c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return joined.select(F.col("c_custkey").alias("user_id"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"), lang.alias("lang"))


def _mask(positions: Column, words: int = 2) -> Column:
    """Array of bit positions as packed bits."""
    value = lambda w: F.aggregate(
        F.filter(positions, lambda p: F.floor(p / 32) == w), F.lit(0).cast("long"), lambda s, p: s + F.pow(F.lit(2), p % 32).cast("long")
    )
    return F.array(*(value(w) for w in range(words)))


def _flipped(words: str, positions: Column) -> Column:
    return F.zip_with(words, _mask(positions), lambda w, m: w.bitwiseXOR(m))


def _drawn(*key) -> Column:
    """The 64 bit positions in the order of a hash."""
    by = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda p: F.struct(h32(*key, p).alias("h"), p.alias("p")))
    return F.transform(F.array_sort(by), lambda x: x["p"])


def plant(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(item_id, origin_id, flips, words)``: copies of every vector with 0 to 16 flipped bits."""
    base = vector_words(spark, sf_dir).select(F.col("item_id").alias("origin_id"), "words")
    rows = base.select("origin_id", "words", F.posexplode(F.array(*map(F.lit, FLIPS))).alias("no", "flips"))
    where = F.slice(_drawn(F.col("origin_id"), F.col("flips")), F.lit(1), F.col("flips"))
    return rows.select((F.lit(1_000_000) + F.col("origin_id") * 10 + F.col("no")).cast("long").alias("item_id"), "origin_id", "flips", _flipped("words", where).alias("words"))


def drift(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(item_id, head_id, role, words)``: a head, two members 6 bits off it, two queries 6 more bits off a member."""
    base = vector_words(spark, sf_dir).select(F.col("item_id").alias("v"), "words", _drawn(F.col("item_id"), F.lit("drift")).alias("o"))
    cut = lambda *spans: F.concat(*(F.slice("o", s, n) for s, n in spans))
    made = [
        ("head", F.slice("o", 1, 0)), ("member", cut((1, 6))), ("member", cut((7, 6))), ("query", cut((1, 6), (13, 6))), ("query", cut((7, 6), (19, 6))),
    ]
    each = F.array(*(F.struct(F.lit(i).alias("no"), F.lit(r).alias("role"), _flipped("words", p).alias("words")) for i, (r, p) in enumerate(made)))
    rows = base.select("v", F.explode(each).alias("x"))
    first = (F.lit(2_000_000) + F.col("v") * 10).cast("long")
    return rows.select((first + F.col("x.no")).alias("item_id"), first.alias("head_id"), "x.role", "x.words")


def chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(item_id, words)``: the bits of vector 0 turned into those of vector 1, four positions a hop."""
    w = vector_words(spark, sf_dir)
    a = w.where("item_id = 0").select(F.col("words").alias("x"))
    b = w.where("item_id = 1").select(F.col("words").alias("y"))
    differ = F.filter(
        F.sequence(F.lit(0), F.lit(63)),
        lambda p: F.floor(F.get("x", F.floor(p / 32).cast("int")).bitwiseXOR(F.get("y", F.floor(p / 32).cast("int"))) / F.pow(F.lit(2), p % 32)) % 2 == 1,
    )
    one = a.crossJoin(b).select(F.col("x").alias("words"), differ.alias("o"))
    hops = F.sequence(F.lit(0), F.ceil(F.size("o") / 4).cast("int"))
    rows = one.select("words", "o", F.explode(hops).alias("hop"))
    return rows.select(F.col("hop").cast("long").alias("item_id"), _flipped("words", F.slice("o", F.lit(1), F.col("hop") * 4)).alias("words"))


def text_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(item_id, origin_id, kind, text)``: modified copies of every document of 60 words or more."""
    w = F.col("w")
    d = text_items(spark, sf_dir).select(F.col("item_id").alias("origin_id"), "text", F.split("text", " ").alias("w"))
    d = d.where(F.size("w") >= 60).withColumn("n", F.size("w"))
    part = lambda x: F.floor(F.col("n") * x).cast("int")
    with_no = F.transform(w, lambda x, i: F.struct(x.alias("x"), i.alias("i")))
    made = {
        "crop": F.slice(w, F.lit(1), part(0.8)),
        "flip": F.array(F.array_join(F.reverse(F.split("text", r"\. ")), ". ")),
        "rotate": F.concat(F.slice(w, part(0.25) + 1, F.col("n")), F.slice(w, F.lit(1), part(0.25))),
        "scale": F.transform(F.filter(with_no, lambda s: s["i"] % 10 != 9), lambda s: s["x"]),
        "noise": F.transform(with_no, lambda s: F.when(h32(F.col("origin_id"), s["i"]) % 25 == 0, F.lit("noise")).otherwise(s["x"])),
        "overlay": F.concat(w, F.array(F.lit(BANNER))),
    }
    each = F.array(*(F.struct(F.lit(i).alias("no"), F.lit(k).alias("kind"), F.array_join(made[k], " ").alias("text")) for i, k in enumerate(KINDS)))
    rows = d.select("origin_id", F.explode(each).alias("v"))
    return rows.select((F.lit(1_000_000) + F.col("origin_id") * 10 + F.col("v.no")).cast("long").alias("item_id"), "origin_id", "v.kind", "v.text")


def shingle_rows(items: DataFrame) -> DataFrame:
    """``(item_id, s)``: distinct three-word shingles."""
    return items.select("item_id", T.words().alias("w")).select("item_id", F.explode(T.shingles("w")).alias("s"))


def shingle_pairs(items: DataFrame, at_least: float = 0.5) -> DataFrame:
    """Truth on documents: ``(a, b, jaccard)`` of shingle sets, exactly."""
    pairs = sets.expanded(*sets.similar_sets(items, at_least, make=sets.run_sets))
    return pairs.select("a", "b", (F.col("overlap") / (F.col("na") + F.col("nb") - F.col("overlap"))).alias("jaccard"))


def first_by(df: DataFrame, n: int, h: str) -> DataFrame:
    """The first ``n`` rows of ``df(a, b, h)`` by ``h``, a number below 2**32, then ``a`` and ``b``; no row reaches the driver.

    Rows are counted by the upper half of ``h``; those below the value at which ``n`` is reached are all taken, and of
    that value alone rows are put in order.
    """
    df = df.withColumn("__at", F.shiftright(h, 16))
    counts = df.groupBy("__at").count().orderBy("__at").collect()  # at most 65,536 rows
    left, edge = n, None
    for r in counts:
        if r["count"] > left:
            edge = r["__at"]
            break
        left -= r["count"]
    if edge is None:
        return df.drop("__at")
    ordered = F.row_number().over(Window.partitionBy("__at").orderBy(h, "a", "b"))
    last = df.where(F.col("__at") == edge).withColumn("__n", ordered).where(F.col("__n") <= left).drop("__n")
    return df.where(F.col("__at") < edge).unionByName(last).drop("__at")


def drawn_candidates(words: DataFrame, true: DataFrame, n: int) -> DataFrame:
    """The first ``n`` candidate pairs ``(a, b, h)`` outside ``true(a, b)`` by the hash ``n``; all of them if they are fewer.

    Candidates are hashed where their posting lists lie and only those below a bound are kept. The bound is set for twice the
    pairs wanted by the length of the lists, and raised until it keeps enough.
    """
    lists = exploded(search_terms(words)).groupBy("term").agg(F.count("*").alias("n"))
    meets = lists.agg(F.sum(F.col("n") * (F.col("n") - 1) / 2)).first()[0] or 0
    name = F.md5(F.concat_ws("|", F.lit("n"), "a", "b"))
    bound = math.ceil(2 * (n + true.count()) / max(1, meets) * (1 << 32))
    while True:
        low = search.pairs_in_lists(words).select("a", "b")
        if bound < 1 << 32:
            low = low.where(name < f"{bound:08x}")  # hex digits have the order of their numbers
        low = written(low)
        near = written(low.join(true.select("a", "b"), ["a", "b"], "left_anti").withColumn("h", h32("n", F.col("a"), F.col("b"))))
        drop_written(low)
        if bound >= 1 << 32 or near.count() >= n:
            return first_by(near, n, "h")
        drop_written(near)
        bound *= 4


def without_shared_term(pairs: DataFrame, words: DataFrame) -> DataFrame:
    """``pairs(a, b)`` of items of ``words(item_id, words)`` that are no candidates of one another."""
    terms = search_terms(words)
    side = lambda c: terms.select(F.col("item_id").alias(c), F.col("terms").alias(f"t{c}"))
    both = pairs.join(side("a"), "a", "left").join(side("b"), "b", "left")
    return both.where(~F.coalesce(F.arrays_overlap("ta", "tb"), F.lit(False))).select("a", "b")


def gold(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(a, b, truth, votes, label, split)``: 14 % near copies by shingles, 86 % others, five noisy votes each."""
    items = text_items(spark, sf_dir)
    words = document_words(spark, sf_dir)
    true = written(shingle_pairs(items).select("a", "b"))
    n_docs, n_true = items.count(), true.count()
    wanted = round(n_true * 86 / 14)
    near = drawn_candidates(words, true, wanted // 2).select("a", "b")
    ids = items.select("item_id")
    far = ids.select(F.col("item_id").alias("x"), ((F.col("item_id") * 7919 + 17) % max(1, n_docs)).alias("y")).where("x <> y")
    far = far.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct().join(true, ["a", "b"], "left_anti")
    far = written(without_shared_term(far, words).withColumn("h", h32("f", F.col("a"), F.col("b"))))
    far = first_by(far, wanted - wanted // 2, "h").select("a", "b")
    pairs = true.withColumn("truth", F.lit(1)).unionByName(near.withColumn("truth", F.lit(0))).unionByName(far.withColumn("truth", F.lit(0)))
    votes = F.array(*(F.when(h32(F.col("a"), F.col("b"), j) % 100 < 5, 1 - F.col("truth")).otherwise(F.col("truth")) for j in range(5)))
    pairs = pairs.withColumn("votes", votes)
    pairs = pairs.withColumn("label", (F.aggregate("votes", F.lit(0), lambda s, v: s + v) >= 3).cast("int"))
    comps = closure.components(true.select(F.col("a").alias("src"), F.col("b").alias("dst")))
    side = lambda end: comps.select(F.col("item").alias(end), F.col("component").alias(f"c{end}"))
    pairs = pairs.join(side("a"), "a", "left").join(side("b"), "b", "left")
    half = lambda end: h32("s", F.coalesce(F.col(f"c{end}"), F.col(end))) % 2
    split = F.when(half("a") != half("b"), "mixed").when(half("a") == 0, "train").otherwise("test")
    return pairs.select("a", "b", "truth", "votes", "label", split.alias("split"))
