"""Spherical k-means cells of vectors, shared by the vector operators.

The centroids are fitted on a bounded sample (at most ``SAMPLE`` rows, the smallest by a hash of the id, so
reruns agree); every row is then assigned. More than ``MOST`` cells are fitted in two levels: each of some
hundred coarse cells is split by its own centroids, fitted in one task each on at most ``40`` sampled rows a
cell. Nothing but samples and at most ``MOST * MOST / 64`` centroids reaches the driver.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Rows that the centroids are fitted on, and the most cells.
SAMPLE, MOST = 20_000, 2048


def usable(col: str = "vec"):
    """Whether a vector is not null, not empty, not zero and has only finite components."""
    bad = lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))
    return F.coalesce((F.size(col) > 0) & ~F.exists(col, bad) & F.exists(col, lambda v: v != 0), F.lit(False))


def stacked(vectors: pd.Series) -> np.ndarray:
    """Rows of equal length as a matrix of doubles."""
    return np.stack([np.asarray(v, np.float64) for v in vectors]) if len(vectors) else np.zeros((0, 1))


def unit(x: np.ndarray) -> np.ndarray:
    """Rows scaled to length one; scaling by the largest component first keeps tiny and huge rows finite."""
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def sampled(vectors: DataFrame, rows: int, seed: int = 0) -> np.ndarray:
    """At most ``rows`` rows of ``vectors(id, vec)``, the smallest by a hash of the id."""
    few = vectors.select("vec", F.xxhash64("id", F.lit(seed)).alias("h")).orderBy("h").limit(rows)
    return stacked(few.select("vec").toArrow().to_pandas()["vec"])


def lloyd(x: np.ndarray, k: int, seed: int, rounds: int) -> np.ndarray:
    """``k`` unit centroids of unit rows; the rows themselves where there are no more."""
    if len(x) <= k:
        return x
    c = x[np.random.default_rng(seed).permutation(len(x))[:k]].copy()
    for _ in range(rounds):
        home = np.concatenate([(x[s : s + 2048] @ c.T).argmax(1) for s in range(0, len(x), 2048)])
        total = np.zeros_like(c)
        np.add.at(total, home, x)
        norm = np.linalg.norm(total, axis=1)
        ok = norm > 1e-9
        c[ok] = total[ok] / norm[ok, None]
    return c


def fit(vectors: DataFrame, k: int, seed: int = 0, rounds: int = 8) -> np.ndarray:
    """``k`` (at most ``MOST``) unit centroids from the sample of ``vectors(id, vec)``; all vectors have the same length."""
    k = max(1, min(k, MOST))
    return lloyd(unit(sampled(vectors, min(SAMPLE, 40 * k), seed)), k, seed, rounds)


class Cells:
    """Cells in one or two levels: ``coarse`` centroids and, for each, the ``fine`` ones of its cell."""

    def __init__(self, coarse: np.ndarray, fine: list[np.ndarray] | None = None):
        self.coarse, self.fine = coarse, fine
        self.offset = np.cumsum([0, *(len(f) for f in fine)]) if fine else np.arange(len(coarse) + 1)

    @staticmethod
    def _visits(x: np.ndarray, c: np.ndarray, chord: float, later: bool):
        """Nearest centroid of each row, and which others (later ones only) may be at home to a row within ``chord``.

        A row within ``chord`` of ``x`` lies at most that far beyond the plane between two centroids.
        """
        sim = x @ c.T
        home = sim.argmax(1)
        apart = np.sqrt(np.maximum(2 - 2 * c[home] @ c.T, 1e-30))
        visit = (sim[np.arange(len(sim)), home][:, None] - sim) / apart <= chord + 1e-9
        if later:
            visit &= np.arange(len(c))[None, :] > home[:, None]
        return home, visit

    def place(self, x: np.ndarray, chord: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """``row, cell, guest`` of unit rows: each at home once, and a guest wherever a partner of a later cell may be at home."""
        home, visit = self._visits(x, self.coarse, chord, True)
        r, c = np.nonzero(visit)
        row, cell, guest = np.concatenate([np.arange(len(x)), r]), np.concatenate([home, c]), np.arange(len(x) + len(r)) >= len(x)
        if not self.fine:
            return row, cell, guest
        out = []
        for at in np.unique(cell):
            for is_guest in (False, True):
                rows = row[(cell == at) & (guest == is_guest)]
                if not len(rows):
                    continue
                near, more = self._visits(x[rows], self.fine[at], chord, not is_guest)
                i, j = np.nonzero(more)
                if not is_guest:
                    out.append((rows, self.offset[at] + near, np.zeros(len(rows), bool)))
                out.append((rows[i], self.offset[at] + j, np.ones(len(i), bool)))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def fit_cells(vectors: DataFrame, k: int, seed: int = 0, rounds: int = 8, most: int = MOST) -> Cells:
    """About ``k`` cells of ``vectors(id, vec)``, in two levels beyond ``most``."""
    if k <= most:
        return Cells(lloyd(unit(sampled(vectors, min(SAMPLE, 40 * k), seed)), max(1, k), seed, rounds))
    wide = min(most, max(2, round(k**0.5)))
    deep = max(2, min(-(-k // wide), most // 8))
    coarse = lloyd(unit(sampled(vectors, min(SAMPLE, 40 * wide), seed)), wide, seed, rounds)
    shared, each = vectors.sparkSession.sparkContext.broadcast(coarse), 40 * deep

    def home(batches):
        for pdf in batches:
            if len(pdf):
                yield pdf.assign(cell=(unit(stacked(pdf["vec"])) @ shared.value.T).argmax(1).astype("int32"))

    def split(pdf: pd.DataFrame) -> pd.DataFrame:
        c = lloyd(unit(stacked(pdf.sort_values("h")["vec"])), deep, seed, rounds)
        return pd.DataFrame({"cell": pdf["cell"].iloc[0], "vec": list(c)})

    kind = dict(vectors.dtypes)["vec"]
    share = min(1.0, 4.0 * each * wide / max(1, vectors.count()))
    rows = vectors.select("vec", F.xxhash64("id", F.lit(seed + 1)).alias("h")).where(F.pmod("h", F.lit(1 << 40)) <= int(share * (1 << 40)))
    rows = rows.mapInPandas(home, f"vec {kind}, h long, cell int")
    rank = F.row_number().over(Window.partitionBy("cell").orderBy("h"))
    found = rows.withColumn("rank", rank).where(F.col("rank") <= each).drop("rank").groupBy("cell").applyInPandas(split, "cell int, vec array<double>")
    by_cell = found.toArrow().to_pandas().groupby("cell")["vec"]
    own = {int(at): stacked(v) for at, v in by_cell}
    return Cells(coarse, [own.get(at, coarse[at : at + 1]) for at in range(len(coarse))])
