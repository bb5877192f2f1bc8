"""Pair scorers: distance, word overlap, and the network over differing bits. Scores lie in 0..1 and are symmetric."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.functions import bits as B


def attach_bits(pairs: DataFrame, items: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``pairs`` with ``xor``, the differing bits of both sides, packed; one join a side."""
    left = items.select(F.col("item_id").alias(a), F.col("words").alias("__wa"))
    right = items.select(F.col("item_id").alias(b), F.col("words").alias("__wb"))
    xor = F.zip_with("__wa", "__wb", lambda x, y: x.bitwiseXOR(y))
    return pairs.join(left, a).join(right, b).withColumn("xor", xor).drop("__wa", "__wb")


class HammingScorer:
    """One less the share of differing bits."""

    def __init__(self, bits: int = 256):
        self.bits = bits

    def score(self, pairs: DataFrame, items: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
        out = attach_bits(pairs, items, a, b)
        n = F.aggregate("xor", F.lit(0), lambda s, x: s + F.bit_count(x).cast("int"))
        return out.withColumn("score", 1 - n / self.bits).drop("xor")


class WordJaccard:
    """Jaccard similarity of word sets ``items(item_id, terms)``: the published baseline."""

    def score(self, pairs: DataFrame, items: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
        left = items.select(F.col("item_id").alias(a), F.col("terms").alias("__ta"))
        right = items.select(F.col("item_id").alias(b), F.col("terms").alias("__tb"))
        both = F.size(F.array_intersect("__ta", "__tb"))
        any_ = F.size(F.array_union("__ta", "__tb"))
        out = pairs.join(left, a).join(right, b)
        return out.withColumn("score", F.when(any_ > 0, both / any_).otherwise(F.lit(1.0))).drop("__ta", "__tb")


def unpacked(words: pd.Series, bits: int) -> np.ndarray:
    """Packed bits as a matrix of 0 and 1."""
    if not len(words):
        return np.zeros((0, bits), np.float32)
    w = np.stack([np.asarray(x, np.int64) for x in words]).astype("<u4")
    return np.unpackbits(w.view(np.uint8).reshape(len(w), -1), axis=1, bitorder="little")[:, :bits].astype(np.float32)


def forward(weights: list[tuple[np.ndarray, np.ndarray]], x: np.ndarray) -> list[np.ndarray]:
    """Activations of every layer: rectified hidden layers, then one sigmoid unit."""
    out = [x]
    for n, (w, b) in enumerate(weights):
        z = out[-1] @ w + b
        out.append(np.maximum(z, 0) if n + 1 < len(weights) else 1 / (1 + np.exp(-np.clip(z, -60, 60))))
    return out


class MlpScorer:
    """Differing bits through three fully connected layers and a sigmoid; weights are broadcast once."""

    def __init__(self, weights: list[tuple[np.ndarray, np.ndarray]], bits: int = 256):
        self.weights, self.bits = weights, bits

    @property
    def parameters(self) -> int:
        return sum(w.size + b.size for w, b in self.weights)

    def score(self, pairs: DataFrame, items: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
        shared, bits = pairs.sparkSession.sparkContext.broadcast(self.weights), self.bits

        @F.pandas_udf("double")
        def predict(xor: pd.Series) -> pd.Series:
            x = unpacked(xor, bits)
            parts = [forward(shared.value, x[s : s + 2048])[-1][:, 0] for s in range(0, len(x), 2048)]
            return pd.Series(np.concatenate(parts).astype(np.float64) if parts else np.zeros(0))

        return attach_bits(pairs, items, a, b).withColumn("score", predict("xor")).drop("xor")


def random_weights(bits: int = 256, hidden: tuple[int, ...] = (128, 64, 32), seed: int = 0) -> list[tuple[np.ndarray, np.ndarray]]:
    """Seeded start weights. ``hidden=(2048, 2048, 2048)`` has about nine million."""
    draw, sizes = np.random.default_rng(seed), (bits, *hidden, 1)
    return [
        ((draw.normal(size=(m, n)) * np.sqrt(2 / m)).astype(np.float32), np.zeros(n, np.float32))
        for m, n in zip(sizes, sizes[1:], strict=False)
    ]


def distance_pairs(pairs: DataFrame, items: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``pairs`` with the number of differing bits as ``distance``."""
    n = F.aggregate("xor", F.lit(0), lambda s, x: s + F.bit_count(x).cast("int"))
    return attach_bits(pairs, items, a, b).withColumn("distance", n).drop("xor")


hamming = B.hamming
