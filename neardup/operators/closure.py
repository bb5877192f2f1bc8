"""Connected components of a similarity graph: the closure step of the clustering.

Three engines give equal results. ``edge_min`` spreads the smallest edge label over shared nodes
(rounds grow with the diameter), ``star`` alternates the two star contractions published for
map-reduce (few rounds on any shape), ``jump`` spreads node labels and halves paths by pointer jumping.
Nothing but one scalar per round reaches the driver; every round is written to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.sources.lineage import drop_written, written

#: Rounds after which ``star`` gives up: it takes about the squared logarithm of the edges, 1,600 for 10^12 of them.
ROUNDS = 1600


def canonical_edges(edges: DataFrame) -> DataFrame:
    """Undirected ``(src, dst)`` once each with ``src < dst``; loops, nulls and repeats go."""
    return (
        edges.where("src is not null and dst is not null and src <> dst")
        .select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
        .distinct()
    )


def star_edges(scored: DataFrame, threshold: float, a: str = "a", b: str = "b") -> DataFrame:
    """One star per query: the pairs scoring strictly above ``threshold``, in canonical order."""
    return canonical_edges(scored.where(F.col("score") > threshold).select(F.col(a).alias("src"), F.col(b).alias("dst")))


def _mark(df: DataFrame, *cols: str) -> tuple:
    return tuple(df.agg(F.count("*"), F.sum(F.xxhash64(*cols).cast("decimal(38,0)"))).first())


def _star(edges: DataFrame, log: list | None) -> DataFrame:
    # Stored as child -> parent with parent < child, so the smallest neighbour of a node that has any
    # smaller one is the minimum over its own rows: a partial aggregate, even for a hub.
    now = written(edges.select(F.col("dst").alias("child"), F.col("src").alias("parent")))
    mark = _mark(now, "child", "parent")
    for n in range(ROUNDS):
        low = now.groupBy("child").agg(F.min("parent").alias("low"))
        up = (
            now.join(low.select(F.col("child").alias("parent"), "low"), "parent", "left")
            .select("child", F.coalesce("low", "parent").alias("parent"))
            .distinct()
        )
        low = up.groupBy("child").agg(F.min("parent").alias("low"))
        moved = up.join(low, "child").where("parent <> low").select(F.col("parent").alias("child"), F.col("low").alias("parent"))
        after = written(moved.union(low.select("child", F.col("low").alias("parent"))).distinct())
        drop_written(now)
        now, old, mark = after, mark, _mark(after, "child", "parent")
        if log is not None:
            log.append({"round": n + 1, "edges": mark[0]})
        if mark == old:
            return now.select(F.col("child").alias("item"), F.col("parent").alias("component"))
    raise RuntimeError(f"no convergence in {ROUNDS} rounds")


def _edge_min(edges: DataFrame, log: list | None) -> DataFrame:
    start = edges.withColumn("label", F.struct("src", "dst"))
    now, changed, n = written(start), 1, 0
    while changed:
        both = now.select(F.explode(F.array("src", "dst")).alias("node"), "label")
        low = both.groupBy("node").agg(F.min("label").alias("low"))
        at = lambda end: low.select(F.col("node").alias(end), F.col("low").alias(f"{end}_low"))
        after = written(
            now.join(at("src"), "src")
            .join(at("dst"), "dst")
            .select("src", "dst", F.least("src_low", "dst_low").alias("label"), F.col("label").alias("was"))
        )
        changed = after.where("label <> was").count()
        drop_written(now)
        now, n = after.drop("was"), n + 1
        now._neardup_path = after._neardup_path
        if log is not None:
            log.append({"round": n, "labels_changed": changed})
    return now.select(F.explode(F.array("src", "dst")).alias("item"), F.col("label.src").alias("component")).distinct()


def _jump(edges: DataFrame, log: list | None) -> DataFrame:
    both = written(edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))))
    now = written(both.groupBy("src").agg(F.least(F.min("dst"), F.col("src")).alias("label")).withColumnRenamed("src", "item"))
    changed, n = 1, 0
    while changed:
        seen = both.join(now.select(F.col("item").alias("dst"), "label"), "dst").groupBy("src").agg(F.min("label").alias("near"))
        near = now.join(seen.withColumnRenamed("src", "item"), "item").select(
            "item", F.least("label", "near").alias("label"), F.col("label").alias("was")
        )
        far = now.select(F.col("item").alias("label"), F.col("label").alias("jump"))
        after = written(near.join(far, "label").select("item", F.least("label", "jump").alias("label"), "was"))
        changed = after.where("label <> was").count()
        drop_written(now)
        now, n = after.drop("was"), n + 1
        now._neardup_path = after._neardup_path
        if log is not None:
            log.append({"round": n, "labels_changed": changed})
    return now.select("item", F.col("label").alias("component"))


def components(edges: DataFrame, method: str = "star", log: list | None = None) -> DataFrame:
    """``(item, component)`` for every node of ``edges(src, dst)``; a component's id is its smallest item.

    ``log``, when given, gets one dict per round (the iteration measures).
    """
    clean = written(canonical_edges(edges))
    if clean.isEmpty():
        return clean.select(F.col("src").alias("item"), F.col("dst").alias("component"))
    found = {"star": _star, "edge_min": _edge_min, "jump": _jump}[method](clean, log)
    if method == "star":
        roots = found.select(F.col("component").alias("item"), "component").distinct()
        found = found.union(roots)
    return found
