"""Embedding near-dedup: spherical k-means cells, blocked cosine products within cells, one kept a group.

Only rows of equal, non-null label are compared. Equal vectors of a label become one entry with a count.
Every entry has a home cell (nearest centroid) and also visits each later cell that could hold a partner: if
``y`` at home in cell C is within chord ``r`` of ``x`` at home in B, then ``(x.b - x.c) / |b - c| <= r``, as
``x`` lies at most ``r`` beyond the plane between the cells. So no link is lost (``slack=1``), and each pair
of entries meets in one cell only. Cells are compared in blocks of at most about ``BLOCK`` rows, one task a
pair of blocks; a task returns per entry its number of links and one edge of a forest that spans the links,
never the pairs. On vectors without any structure most entries visit most cells; a smaller ``slack`` visits
fewer and may lose links.

Defined cases: vectors that are null, empty, zero or hold null or non-finite components, and rows without a
label, link with nothing; vectors of another length than most are compared with their like only; repeated
rows of one id stay one row each, count as other vectors and are linked each by its own vector and label; extra columns are ignored; an empty table gives
an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.llm.blocks import dense_roots, forest
from neardup.llm.cells import MOST, fit_cells, stacked, unit, usable
from neardup.operators.closure import components
from neardup.sources.lineage import written

#: Entries that a cell of one label should hold, and rows a block.
CELL, BLOCK = 4096, 2048


def _pairs(rows: pd.DataFrame, i: int, j: int, threshold: float) -> pd.DataFrame:
    z, own = unit(stacked(rows["vec"])), rows["own"].to_numpy()
    ids, copies = rows["rep"].to_numpy(), rows["copies"].to_numpy()
    a = np.flatnonzero(own == i)
    b = a if i == j else np.flatnonzero(own == j)
    linked = np.zeros((len(a), len(b)), bool)
    for s in range(0, len(a), 512):
        linked[s : s + 512] = z[a[s : s + 512]] @ z[b].T >= threshold
    if i == j:
        np.fill_diagonal(linked, False)
        root = dense_roots(linked)
        hit = np.flatnonzero(linked.any(1))
        return pd.DataFrame({"rep": ids[hit], "links": linked[hit] @ copies[b], "root": ids[a[root[hit]]]})
    rows_hit, cols_hit = np.flatnonzero(linked.any(1)), np.flatnonzero(linked.any(0))
    x, y = [ids[a[rows_hit]], ids[b[cols_hit]]], [ids[b[linked[rows_hit].argmax(1)]], ids[a[linked[:, cols_hit].argmax(0)]]]
    while True:
        child, parent = forest(np.concatenate(x), np.concatenate(y))
        at = pd.Series(parent, child)
        label = pd.Series(ids).map(at).fillna(pd.Series(ids)).to_numpy()
        cross = linked & (label[a][:, None] != label[b][None, :])
        more = np.flatnonzero(cross.any(1))
        if not len(more):
            break
        x, y = [child, ids[a[more]]], [parent, ids[b[cross[more].argmax(1)]]]
    hit = np.concatenate([a[rows_hit], b[cols_hit]])
    links = np.concatenate([linked[rows_hit] @ copies[b], copies[a] @ linked[:, cols_hit]])
    return pd.DataFrame({"rep": ids[hit], "links": links, "root": label[hit]})


def near_duplicates(
    vectors: DataFrame, threshold: float = 0.93, slack: float = 1.0, cell: int = CELL, block: int = BLOCK, most: int = MOST
) -> DataFrame:
    """One row per row of ``vectors(vec_id, embedding, label)``: ``vec_id, n_links, component_id, kept``."""
    spark = vectors.sparkSession
    rows = written(
        vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("vec"), "label")
        .withColumn("ok", usable() & F.col("label").isNotNull() & F.col("vec_id").isNotNull())
        .withColumn("h1", F.xxhash64("label", "vec"))
        .withColumn("h2", F.hash("vec", F.lit(1)))
    )
    reps = written(
        rows.where("ok")
        .groupBy("h1", "h2")
        .agg(F.min("vec_id").alias("least"), F.count("*").alias("copies"), F.first("label").alias("label"), F.first("vec").alias("vec"))
        # An id may be repeated with another vector or label, so entries have numbers of their own.
        .withColumn("rep", F.monotonically_increasing_id())
    )
    sizes = reps.groupBy(F.size("vec").alias("dim"), "label").count()
    at_most = sizes.groupBy("dim").agg(F.max("count").alias("n")).collect()  # a row for each vector length
    parts = []
    chord = math.sqrt(max(0.0, 2 - 2 * threshold)) * (1 + 1e-9) * slack
    for dim, n in ((r["dim"], r["n"]) for r in at_most):
        own = reps.where(F.size("vec") == dim)
        cells = spark.sparkContext.broadcast(fit_cells(own.select(F.col("least").alias("id"), "vec"), -(-n // cell), most=most))

        def place(batches, cells=cells):
            for pdf in batches:
                if len(pdf):
                    row, at, guest = cells.value.place(unit(stacked(pdf["vec"])), chord)
                    yield pdf.iloc[row].assign(cell=at.astype("int32"), guest=guest)

        kind = dict(reps.dtypes)["label"]
        parts.append(
            own.select("rep", "copies", "label", "vec").mapInPandas(
                place, f"rep long, copies long, label {kind}, vec array<double>, cell int, guest boolean"
            ).withColumn("dim", F.lit(dim))
        )
    if not parts:
        return rows.select(
            "vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").cast("long").alias("component_id"), F.lit(True).alias("kept")
        )
    placed = parts[0]
    for p in parts[1:]:
        placed = placed.union(p)
    placed = written(placed)
    sized = placed.groupBy("dim", "label", "cell").agg(
        F.ceil(F.count_if(~F.col("guest")) / block).cast("int").alias("homes"),
        F.ceil(F.count_if("guest") / block).cast("int").alias("guests"),
    ).where("homes > 0")
    # Blocks 0..homes-1 hold residents, the next ones guests; guests are not compared with one another.
    own = F.when(F.col("guest"), F.col("homes") + F.pmod(F.xxhash64("rep"), F.col("guests"))).otherwise(
        F.pmod(F.xxhash64("rep"), F.col("homes"))
    ).cast("int")
    others = F.when(F.col("guest"), F.sequence(F.lit(0), F.col("homes") - 1)).otherwise(
        F.sequence(F.lit(0), F.col("homes") + F.col("guests") - 1)
    )
    units = F.transform(others, lambda o: F.struct(F.least("own", o).alias("i"), F.greatest("own", o).alias("j")))
    dealt = (
        placed.join(sized, ["dim", "label", "cell"])
        .withColumn("own", own)
        .select("dim", "label", "cell", "rep", "copies", "vec", "own", F.explode(units).alias("u"))
        .select("dim", "label", "cell", "rep", "copies", "vec", "own", "u.i", "u.j")
    )

    def compare(at: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        i, j = int(at[3]), int(at[4])
        own = pdf["own"].to_numpy()
        if not (own == i).any() or not (own == j).any():
            return pd.DataFrame({"rep": [], "links": [], "root": []}).astype("int64")
        return _pairs(pdf, i, j, threshold).astype("int64")

    found = written(dealt.groupBy("dim", "label", "cell", "i", "j").applyInPandas(compare, "rep long, links long, root long"))
    links = found.groupBy("rep").agg(F.sum("links").alias("links"))
    joined = components(found.where("rep <> root").select(F.col("rep").alias("src"), F.col("root").alias("dst")))
    joined = joined.select(F.col("item").alias("rep"), "component")
    named = joined.join(reps.select("rep", "least"), "rep").groupBy("component").agg(F.min("least").alias("component_id"))
    per_rep = (
        reps.select("h1", "h2", "rep", "least", "copies")
        .join(links, "rep", "left")
        .join(joined.join(named, "component").select("rep", "component_id"), "rep", "left")
        .select(
            "h1", "h2", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n"), F.coalesce("component_id", "least").alias("component")
        )
    )
    out = rows.where("ok").select("vec_id", "h1", "h2").join(per_rep, ["h1", "h2"]).select("vec_id", F.col("n").alias("n_links"), "component")
    rest = rows.where("not ok").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").cast("long").alias("component"))
    return out.union(rest).select(
        "vec_id", "n_links", F.col("component").alias("component_id"), F.coalesce(F.col("vec_id") == F.col("component"), F.lit(True)).alias("kept")
    )


def deduplicate(vectors: DataFrame, threshold: float = 0.93) -> DataFrame:
    """``vectors`` with only the smallest-id row of each group of linked vectors; columns unchanged."""
    kept = near_duplicates(vectors.select("vec_id", "embedding", "label"), threshold).where("kept").select("vec_id").distinct()
    return vectors.join(kept, "vec_id", "left_semi")
