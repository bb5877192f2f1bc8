"""Labels and training of the pair network."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.operators.scorers import attach_bits, forward, random_weights, unpacked
from neardup.sources.lineage import written


def bootstrap_labels(cands: DataFrame, items: DataFrame, old_scorer, threshold: float) -> DataFrame:
    """``(a, b, label)``: what the previous generation says of candidate pairs, at a strict threshold."""
    scored = old_scorer.score(cands.select("a", "b"), items)
    return scored.select("a", "b", (F.col("score") > threshold).cast("int").alias("label"))


def adversarial_pairs(scored: DataFrame, accepted: DataFrame, threshold: float) -> DataFrame:
    """``(a, b, label)`` positives: queries taken through a member whose head itself scored no more than the threshold."""
    direct = scored.where("place = 0").select("query_id", "head_id", F.col("score").alias("direct"))
    hard = accepted.join(direct, ["query_id", "head_id"]).where(F.col("direct") <= threshold)
    return hard.select(F.least("query_id", "head_id").alias("a"), F.greatest("query_id", "head_id").alias("b"), F.lit(1).alias("label"))


def make_set(kind: str, bootstrap: DataFrame, adversarial: DataFrame | None = None, share: float = 1.0, seed: int = 0) -> DataFrame:
    """Training pairs: ``base`` takes a seeded share of the bootstrap labels, ``hard`` all of them and the adversarial ones."""
    draw = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), "a", "b")), 1, 8), 16, 10).cast("long") / float(1 << 32)
    if kind == "base":
        return bootstrap.where(draw < share)
    if kind != "hard":
        raise ValueError(kind)
    return bootstrap.unionByName(adversarial).groupBy("a", "b").agg(F.max("label").alias("label"))


def gradient(weights, x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[list[tuple[np.ndarray, np.ndarray]], float]:
    """Summed gradient and log loss of the network on rows ``x`` with labels ``y``."""
    layers = forward(weights, x)
    p = layers[-1][:, 0]
    loss = float(-(weight * (y * np.log(p + 1e-12) + (1 - y) * np.log(1 - p + 1e-12))).sum())
    back, out = (weight * (p - y))[:, None], []
    for n in range(len(weights) - 1, -1, -1):
        out.append((layers[n].T @ back, back.sum(0)))
        if n:
            back = (back @ weights[n][0].T) * (layers[n] > 0)
    return out[::-1], loss


class Adam:
    """The adaptive-moment update on the driver."""

    def __init__(self, weights, rate: float):
        self.rate, self.n = rate, 0
        self.m = [[np.zeros_like(p) for p in layer] for layer in weights]
        self.v = [[np.zeros_like(p) for p in layer] for layer in weights]

    def step(self, weights, grads):
        self.n += 1
        out = []
        for layer, grad, m, v in zip(weights, grads, self.m, self.v, strict=True):
            new = []
            for j in range(2):
                m[j] = 0.9 * m[j] + 0.1 * grad[j]
                v[j] = 0.999 * v[j] + 0.001 * grad[j] ** 2
                move = (m[j] / (1 - 0.9**self.n)) / (np.sqrt(v[j] / (1 - 0.999**self.n)) + 1e-8)
                new.append((layer[j] - self.rate * move).astype(np.float32))
            out.append(tuple(new))
        return out


def fit_mlp(
    pairs: DataFrame, items: DataFrame, bits: int = 256, hidden: tuple[int, ...] = (128, 64, 32), epochs: int = 30,
    rate: float = 3e-3, seed: int = 0, local_steps: int = 8,
) -> tuple[list[tuple[np.ndarray, np.ndarray]], list[float]]:
    """Weights and the mean loss of each epoch, from ``pairs(a, b, label)``.

    An epoch is ``local_steps`` jobs, each on one hash share of the pairs: every partition sums its gradient,
    the sums meet on the driver (one row a partition), which makes one step. Classes weigh alike.
    """
    spark = pairs.sparkSession
    data = attach_bits(pairs, items).select("xor", F.col("label").cast("double").alias("y"), F.pmod(F.xxhash64("a", "b", F.lit(seed)), F.lit(local_steps)).alias("share"))
    data = written(data)
    n, positive = data.agg(F.count("*"), F.avg("y")).first()
    up = (1.0 if not positive else 0.5 / positive), (1.0 if positive in (None, 1) else 0.5 / (1 - positive))
    weights = random_weights(bits, hidden, seed)
    adam, losses = Adam(weights, rate), []
    for _ in range(epochs):
        total = 0.0
        for share in range(local_steps):
            shared = spark.sparkContext.broadcast(weights)

            def partial(batches, shared=shared):
                grads, loss, rows = None, 0.0, 0
                for pdf in batches:
                    if not len(pdf):
                        continue
                    y = pdf["y"].to_numpy(np.float32)
                    g, one = gradient(shared.value, unpacked(pdf["xor"], bits), y, np.where(y > 0.5, up[0], up[1]).astype(np.float32))
                    grads = g if grads is None else [(a + c, b + d) for (a, b), (c, d) in zip(grads, g, strict=True)]
                    loss, rows = loss + one, rows + len(pdf)
                if grads is not None:
                    flat = np.concatenate([x.ravel() for layer in grads for x in layer]).astype(np.float32)
                    yield pd.DataFrame({"g": [flat.tobytes()], "loss": [loss], "rows": [rows]})

            parts = data.where(F.col("share") == share).select("xor", "y").mapInPandas(partial, "g binary, loss double, rows long").collect()
            shared.unpersist()
            if not parts:
                continue
            rows = sum(p["rows"] for p in parts)
            flat, at, grads = sum(np.frombuffer(p["g"], np.float32) for p in parts) / rows, 0, []
            for w, b in weights:
                grads.append((flat[at : at + w.size].reshape(w.shape), flat[at + w.size : at + w.size + b.size]))
                at += w.size + b.size
            weights = adam.step(weights, grads)
            total += sum(p["loss"] for p in parts)
        losses.append(total / max(1, n))
    return weights, losses
