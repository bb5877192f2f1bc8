"""From vectors and texts to selected, packed bits."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from neardup.functions import bits as B
from neardup.functions import text as T


def text_embedding(df: DataFrame, dims: int = 256, shingle: int = 3) -> DataFrame:
    """``df(item_id, text)`` to ``(item_id, vec)``: signed feature hashing of word shingles."""
    return df.select("item_id", T.embedding_udf(dims, shingle)("text").alias("vec"))


def text_bits(df: DataFrame, dims: int = 256, shingle: int = 3) -> DataFrame:
    """``text_embedding`` and ``binarize`` in one pass: ``(item_id, words)``."""
    return df.select("item_id", T.signature_udf(dims, shingle)("text").alias("words"))


def binarize(df: DataFrame, dims: int, rule: str = "sign", seed: int = 0) -> DataFrame:
    """``df(item_id, vec)`` to packed bits ``(item_id, words)``.

    ``sign``: a component over 0; ``median``: over the component's exact median of all items (``medians``); ``hyperplane``: the side of ``dims`` seeded random planes.
    """
    if rule == "sign":
        flags = F.transform("vec", lambda v: v > 0)
        return df.select("item_id", B.pack_array(flags, dims).alias("words"))
    if rule == "median":
        middle = F.array(*(F.lit(m) for m in medians(df, dims)))
        flags = F.zip_with("vec", middle, lambda v, m: v > m)
        return df.select("item_id", B.pack_array(flags, dims).alias("words"))
    if rule == "hyperplane":

        @F.pandas_udf("array<long>")
        def side(vecs: pd.Series) -> pd.Series:
            if not len(vecs):
                return pd.Series([], dtype=object)
            x = np.stack([np.asarray(v, np.float64) for v in vecs])
            planes = np.random.default_rng(seed).normal(size=(x.shape[1], -(-dims // 32) * 32))
            planes[:, dims:] = 0
            packed = np.packbits(x @ planes > 0, axis=1, bitorder="little").view("<u4")
            return pd.Series(list(packed.astype(np.int64)))

        return df.select("item_id", side("vec").alias("words"))
    raise ValueError(rule)


def medians(df: DataFrame, dims: int, edge: float = 0.001) -> list[float]:
    """The lower median of each of ``dims`` components of ``df(vec)``, exactly; 0 for a component without values.

    An approximate aggregate brackets it; values outside the bracket are counted alone, those inside are ranked.
    """
    value = lambda i: F.col("vec")[i]
    row = df.agg(*(F.percentile_approx(value(i), [0.5 - edge, 0.5 + edge], 10_000).alias(f"m{i}") for i in range(dims))).first()
    bound = lambda k: F.get(F.array(*(F.lit(float(x[k]) if x else None).cast("double") for x in row)), F.col("p"))
    each = df.select(F.posexplode(F.slice("vec", 1, dims)).alias("p", "v")).select("p", F.col("v").cast("double").alias("v")).where("v is not null")
    side = F.when(F.col("v") < bound(0), 0).when(F.col("v") <= bound(1), 1).otherwise(2)
    counted = each.withColumn("side", side).groupBy("p", "side", F.when(F.col("side") == 1, F.col("v")).alias("v")).agg(F.count("*").alias("n"))
    upto = F.sum("n").over(Window.partitionBy("p").orderBy("side", "v"))
    ranked = counted.withColumn("upto", upto).withColumn("all", F.sum("n").over(Window.partitionBy("p"))).where("2 * upto >= all")
    found = {r["p"]: r["m"] for r in ranked.groupBy("p").agg(F.min(F.struct("side", "v")).alias("m")).collect()}
    if any(m["side"] != 1 for m in found.values()):  # a bracket missed it
        return medians(df, dims, 0.5)
    return [float(found[p]["v"]) if p in found else 0.0 for p in range(dims)]


def seeded_positions(bits: int, n: int, seed: int = 0) -> list[int]:
    """A seeded draw of ``n`` of ``bits`` positions, in order."""
    return sorted(np.random.default_rng(seed).permutation(bits)[:n].tolist())


def bit_positions(df: DataFrame, bits: int, n: int, by: str = "prefix", seed: int = 0) -> list[int]:
    """Which ``n`` of ``bits`` to keep: the first, a seeded draw, the most balanced, or balanced and uncorrelated ones.

    The last two read the data once; what reaches the driver has one number for each bit or pair of bits.
    """
    if by == "prefix":
        return list(range(n))
    if by == "seeded":
        return seeded_positions(bits, n, seed)
    ones = df.agg(*(F.avg(B.bit("words", p)).alias(f"b{p}") for p in range(bits))).first()
    even = [(abs(float(x if x is not None else 0) - 0.5), p) for p, x in enumerate(ones)]
    if by == "entropy":
        return sorted(p for _, p in sorted(even)[:n])
    if by == "decorrelated":

        def gram(batches):
            total = np.zeros((bits, bits))
            for pdf in batches:
                if len(pdf):
                    w = np.stack([np.asarray(x, np.int64) for x in pdf["words"]])
                    b = np.unpackbits(w.astype("<u4").view(np.uint8), axis=1, bitorder="little")[:, :bits] * 2.0 - 1
                    total += b.T @ b
            yield pd.DataFrame({"row": np.repeat(np.arange(bits), bits), "col": np.tile(np.arange(bits), bits), "v": total.ravel()})

        g = df.select("words").mapInPandas(gram, "row int, col int, v double").groupBy("row", "col").agg(F.sum("v").alias("v")).toPandas()
        m = g.pivot(index="row", columns="col", values="v").to_numpy()
        m = np.abs(m) / max(1.0, m[0, 0])
        kept: list[int] = []
        for _, p in sorted(even):  # greedily, the most balanced first, without its near copies
            if len(kept) < n and all(m[p, q] < 0.5 for q in kept):
                kept.append(p)
        kept += [p for _, p in sorted(even) if p not in kept][: n - len(kept)]
        return sorted(kept)
    raise ValueError(by)


def select_bits(df: DataFrame, bits: int, n: int, by: str = "prefix", seed: int = 0) -> DataFrame:
    """``df(item_id, words)`` with ``n`` of its ``bits``."""
    if by == "prefix" and n == bits:
        return df
    return df.withColumn("words", B.chosen("words", bit_positions(df, bits, n, by, seed)))


def collapse_exact(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Representatives ``(item_id, words)`` of equal bit strings, and the mapping ``(item_id, rep_id)``."""
    reps = df.groupBy("words").agg(F.min("item_id").alias("rep_id"))
    return reps.select(F.col("rep_id").alias("item_id"), "words"), df.join(reps, "words").select("item_id", "rep_id")
