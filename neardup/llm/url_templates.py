"""URL filter: rules first, then the purity of the url's path template.

Per host the distinct paths form a tree of segments. Segments with numbers or long hexadecimal ids become
wildcards, and so do the rare children of a node with very many different ones. Branches that differ in one
segment are merged when their share of bad labels does not differ significantly from that of all of them
together. A template is rejected when its share of bad labels, smoothed towards its host's (and that towards
the overall share), is over ``reject``.

All tree steps work on templates with their counts, aggregated before any other shuffle, so a host with a
third of all rows is a few rows. Paths count to their last segment: a level is worked on, however deep, where
some host has more than one segment.

Defined cases: a null url, or one without ``://``, has an empty host and path and the template of that
host's root; without labels nothing but a rule rejects; repeated rows are judged alike; extra columns are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from neardup.sources.lineage import written

#: (host, path, verdict): fixed values of the query's contract.
RULES = [
    ("com", "/", "allow"),
    ("example.com", "/en/", "block"),
    ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"),
    ("net", "/fr/", "block"),
]
#: Different children at which a node's rare ones become wildcards; strength of
#: smoothing; two-sided 5 % point of the similarity test; templates that may be broadcast.
CHILDREN, STRENGTH, SIMILAR, SMALL = 32, 8.0, 1.96, 50_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: str = "url") -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a url; both empty without ``://``."""
    part = lambda n: F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)([^?#]*)", n), F.lit(""))
    return F.translate(part(1), UPPER, LOWER), part(2)


def rule_of(rules=RULES, host: str = "host", path: str = "path") -> Column:
    """Struct ``(rule, verdict)`` of the longest rule that fits, or null. Equal lengths: the smaller string."""
    found = F.lit(None).cast("struct<rule:string,verdict:string>")
    for h, p, verdict in sorted(rules, key=lambda r: (-len(r[0] + r[1]), r[0] + r[1]), reverse=True):
        fits = ((F.col(host) == h) | F.col(host).endswith(f".{h}")) & F.col(path).startswith(p)
        found = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(found)
    return found


def path_shape(path: str = "path") -> Column:
    """All segments of a path, with ids as wildcards."""
    parts = F.filter(F.split(path, "/"), lambda s: s != "")
    return F.transform(parts, lambda s: F.regexp_replace(F.regexp_replace(s, r"[0-9a-fA-F-]*[0-9][0-9a-fA-F-]{7,}", "*"), r"[0-9]+", "*"))


def _tally(t: DataFrame) -> DataFrame:
    return t.groupBy("host", "segs").agg(F.sum("n").alias("n"), F.sum("labelled").alias("labelled"), F.sum("bad").alias("bad"))


def _at(p: int) -> Column:
    return F.try_element_at("segs", F.lit(p))


def _with_star(p: int) -> Column:
    return F.transform("segs", lambda s, i: F.when(i == p - 1, F.lit("*")).otherwise(s))


def templates(shapes: DataFrame) -> DataFrame:
    """``(host, shape, segs)``: for each distinct shape of a host the template that stands for it.

    ``shapes(host, shape, n, labelled, bad)`` has one row for each.
    """
    now = shapes.select("host", "shape", F.col("shape").alias("segs"), "n", "labelled", "bad")
    # How many segments a host has at each level bounds the children of any of its nodes there: one row a level.
    each = shapes.select("host", F.posexplode("shape").alias("p", "seg")).distinct().groupBy("host", "p").agg(F.count("*").alias("kinds"))
    kinds = {r["p"] + 1: r["kinds"] for r in each.groupBy("p").agg(F.max("kinds").alias("kinds")).collect()}
    for k, p in enumerate(sorted(p for p in kinds if kinds[p] > CHILDREN), 1):  # rare children of crowded nodes, from the root down
        node = now.where(F.size("segs") >= p).select("host", F.slice("segs", 1, p - 1).alias("above"), _at(p).alias("seg"), "n")
        child = node.groupBy("host", "above", "seg").agg(F.sum("n").alias("n"))
        crowd = child.groupBy("host", "above").agg(F.count("*").alias("kinds"), F.sum("n").alias("all")).where(F.col("kinds") > CHILDREN)
        rare = child.join(crowd, ["host", "above"]).where(F.col("n") < F.greatest(F.lit(2), 0.02 * F.col("all"))).select("host", "above", "seg", F.lit(True).alias("rare"))
        now = (
            now.withColumn("above", F.slice("segs", 1, p - 1))
            .withColumn("seg", _at(p))
            .join(rare, ["host", "above", "seg"], "left")
            .withColumn("segs", F.when(F.col("rare"), _with_star(p)).otherwise(F.col("segs")))
            .drop("above", "seg", "rare")
        )
        if k % 2 == 0:
            now = written(now)
    for k, p in enumerate(sorted((p for p in kinds if kinds[p] > 1), reverse=True), 1):  # similar branches, from the leaves up
        leaf = _tally(now).where(F.size("segs") >= p).withColumn("merged", _with_star(p))
        pool = leaf.groupBy("host", "merged").agg(F.sum("labelled").alias("of"), F.sum("bad").alias("hits"), F.count("*").alias("kinds")).where("kinds > 1")
        share = F.when(F.col("of") > 0, F.col("hits") / F.col("of")).otherwise(F.lit(0.0))
        spread = F.sqrt(share * (1 - share) / F.greatest("labelled", F.lit(1)))
        differs = (F.col("labelled") > 0) & (F.abs(F.col("bad") / F.greatest("labelled", F.lit(1)) - share) > SIMILAR * spread)
        similar = leaf.join(pool, ["host", "merged"]).where(~differs).select("host", "segs", "merged")
        now = now.join(similar, ["host", "segs"], "left").withColumn("segs", F.coalesce("merged", "segs")).drop("merged")
        if k % 2 == 0:
            now = written(now)
    return now


def judge(pages: DataFrame, labelled: DataFrame, rules=RULES, reject: float = 0.5) -> DataFrame:
    """One row per row of ``pages(page_id, url)``: ``page_id, host, path, rule, verdict, template, purity``.

    ``labelled(page_id, bad)`` marks some pages as bad (1) or good (0); ``purity`` is the template's smoothed
    share of good ones.
    """
    host, path = host_and_path()
    known = labelled.where("bad is not null").groupBy("page_id").agg(F.max("bad").cast("long").alias("bad"))
    rows = written(
        pages.select("page_id", "url").select("page_id", host.alias("host"), path.alias("path")).withColumn("shape", path_shape())
    )
    counted = rows.join(known, "page_id", "left")
    shapes = written(
        counted.groupBy("host", "shape").agg(
            F.count("*").alias("n"), F.count("bad").alias("labelled"), F.coalesce(F.sum("bad"), F.lit(0)).alias("bad")
        )
    )
    overall = shapes.agg(F.sum("bad").alias("bad"), F.sum("labelled").alias("labelled")).first()
    base = (overall["bad"] or 0) / max(1, overall["labelled"] or 0)
    hosts = shapes.groupBy("host").agg(
        ((F.sum("bad") + STRENGTH * base) / (F.sum("labelled") + STRENGTH)).alias("host_bad")
    )
    named = written(templates(shapes))
    scored = (
        _tally(named)
        .join(hosts, "host")
        .select("host", "segs", ((F.col("bad") + STRENGTH * F.col("host_bad")) / (F.col("labelled") + STRENGTH)).alias("bad_share"))
    )
    verdicts = written(
        named.select("host", "shape", "segs")
        .join(scored, ["host", "segs"])
        .select(
            "host",
            "shape",
            F.concat(F.lit("/"), F.array_join("segs", "/")).alias("template"),
            (1 - F.col("bad_share")).alias("purity"),
            F.when(F.col("bad_share") > reject, "block").otherwise("allow").alias("by_template"),
        )
    )
    small = F.broadcast(verdicts) if verdicts.count() <= SMALL else verdicts
    return (
        rows.join(small, ["host", "shape"], "left")
        .withColumn("r", rule_of(rules))
        .select("page_id", "host", "path", "r.rule", F.coalesce("r.verdict", "by_template").alias("verdict"), "template", "purity")
    )


def labels_by_document(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """``(page_id, bad)``: a page whose path names a document in ``/<language>/<id>`` takes that document's quality."""
    _, path = host_and_path()
    named = pages.select("page_id", F.regexp_extract(path, r"^/[a-z]{2}/([0-9]{1,18})(?:[./]|$)", 1).try_cast("long").alias("doc_id"))
    return named.join(labels.select("doc_id", "quality"), "doc_id").select("page_id", (F.col("quality") == 0).cast("int").alias("bad"))
