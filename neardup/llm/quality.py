"""Quality classifier: a weak-label model over heuristic labellers trains a hashed linear scorer.

Labellers look at a whole text and vote good (1), bad (0) or nothing (-1). How often each pattern of votes
occurs is counted over all documents (at most 3 to the number of labellers patterns, whatever the input);
expectation-maximisation on these counts estimates, for both classes, how each labeller votes, from a start
at the majority. The posterior of its pattern labels each document. A logistic scorer over hashed word and
word-shape features is then fitted to the posteriors of a bounded sample (about ``SAMPLE`` documents, by a
hash of the id) and scores every whole text.

Defined cases: a null text counts as empty; an empty text gets votes and a score like any other; repeated
rows score alike; ties (a posterior of one half) count as good; extra columns are ignored; an empty table
gives an empty result.
"""

from __future__ import annotations

import math
from collections import Counter
from zlib import crc32

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.llm.batches import by_row

#: Bound on the training sample, hashed features, passes of the fit and of the estimation.
SAMPLE, FEATURES, PASSES, ROUNDS = 8_000, 1 << 16, 12, 60
#: Tokens a worker remembers what it made of, and the longest of them.
CACHE, LONG = 200_000, 64
KEEP = 0.5
LABELLERS = ("capitals", "symbols", "marks", "bars", "repeats", "variety", "length", "ends", "lines")
#: Letters beyond ASCII count as letters; marks that join repeats of noise.
_MARKS = frozenset("!#$%&*|~^=<>{}[]\\")


def _shape(token: str) -> tuple[int, int, int, int]:
    """Letters, capitals, noise marks and other characters of a token."""
    letters = sum(c.isalpha() for c in token)
    capitals = sum(c.isupper() for c in token)
    marks = sum(c in _MARKS for c in token)
    return letters, capitals, marks, len(token) - letters - marks


_shapes: dict[str, tuple[int, int, int, int]] = {}


def _shape_of(token: str) -> tuple[int, int, int, int]:
    got = _shapes.get(token)
    if got is None:
        got = _shape(token)
        if len(token) > LONG:
            return got
        if len(_shapes) >= CACHE:
            _shapes.clear()
        _shapes[token] = got
    return got


def votes(text: str | None) -> tuple[int, ...]:
    """A vote of each of ``LABELLERS``."""
    text = text or ""
    tokens = text.split()
    n = len(tokens)
    if not n:
        return (0,) * len(LABELLERS)
    counts = Counter(tokens)
    letters = capitals = marks = other = noisy = 0
    for t, c in counts.items():
        a, b, m, o = _shape_of(t)
        letters, capitals, marks, other, noisy = letters + c * a, capitals + c * b, marks + c * m, other + c * o, noisy + c * (m > 0)
    size = letters + marks + other
    same = sum(a == b for a, b in zip(tokens, tokens[1:], strict=False))
    top = max(counts.values())
    lines = [x.strip() for x in text.split("\n") if x.strip()]
    last = text.rstrip()[-1:]
    judge = lambda bad, good: 0 if bad else 1 if good else -1
    return (
        judge(capitals > 0.4 * max(1, letters), capitals < 0.15 * letters),
        judge(marks + other > 0.3 * size, marks + other < 0.1 * size),
        judge(noisy > 0.25 * n, noisy < 0.02 * n),
        judge(counts["|"] > 0.15 * n, counts["|"] < 0.02 * n),
        judge(same > 0.2 * n, same < 0.05 * n),
        judge(n > 20 and top > 0.3 * n, n > 20 and top < 0.15 * n),
        judge(n < 8, n > 40),
        judge(last.isalnum() and n > 20, last in ".!?…\"'"),
        judge(len(lines) > 4 and len(set(lines)) < 0.6 * len(lines), len(set(lines)) == len(lines)),
    )


def estimate(patterns: list[tuple[int, ...]], counts: np.ndarray) -> tuple[np.ndarray, float, np.ndarray]:
    """Posterior of good for each pattern, share of good, and how each labeller votes by class (class, labeller, vote + 1)."""
    v = np.array(patterns, np.int64).reshape(len(patterns), -1)
    good, bad = (v == 1).sum(1), (v == 0).sum(1)
    # A start at the majority, with the bad votes weighed up: most labellers see one kind of fault only.
    p = 1 / (1 + np.exp(-(good - 3.0 * bad)))
    for _ in range(ROUNDS):
        share = float((p @ counts + 1) / (counts.sum() + 2))
        table = np.zeros((2, v.shape[1], 3))
        for x in range(3):
            hit = v == x - 1
            table[1, :, x] = ((p * counts)[:, None] * hit).sum(0)
            table[0, :, x] = (((1 - p) * counts)[:, None] * hit).sum(0)
        table = (table + 1) / (table + 1).sum(2, keepdims=True)
        ll = [np.log(table[c][np.arange(v.shape[1])[None, :], v + 1]).sum(1) for c in (0, 1)]
        odds = math.log(share / (1 - share)) + ll[1] - ll[0]
        new = 1 / (1 + np.exp(-np.clip(odds, -500, 500)))
        if np.abs(new - p).max() < 1e-9:
            break
        p = new
    return p, share, table


_hashes: dict[str, tuple[int, int]] = {}


def _hashed(token: str) -> tuple[int, int]:
    """Feature numbers of a token's lower-case form and of its shape."""
    got = _hashes.get(token)
    if got is None:
        shape, last = [], ""
        for c in token:
            k = "A" if c.isupper() else "a" if c.isalpha() else "0" if c.isdigit() else c
            if k != last:
                shape.append(k)
            last = k
        got = crc32(token.lower().encode("utf-8", "surrogatepass")) % FEATURES, crc32(("^" + "".join(shape)).encode("utf-8", "surrogatepass")) % FEATURES
        if len(token) > LONG:
            return got
        if len(_hashes) >= CACHE:
            _hashes.clear()
        _hashes[token] = got
    return got


def features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Sorted feature numbers and weights (length one) of a whole text."""
    tokens = (text or "").split()
    found: Counter = Counter()
    for t, c in Counter(tokens).items():
        word, shape = _hashed(t)
        found[word] += c
        found[shape] += c
    found[crc32(b"same again") % FEATURES] += sum(a == b for a, b in zip(tokens, tokens[1:], strict=False))
    found[crc32(b"always") % FEATURES] += 1
    at = np.fromiter(found, np.int64, len(found))
    w = np.fromiter(found.values(), np.float64, len(found))
    order = np.argsort(at)
    return at[order], (w / np.linalg.norm(w))[order]


def fit_linear(rows: list[tuple[np.ndarray, np.ndarray]], target: np.ndarray, seed: int = 0) -> np.ndarray:
    """Logistic weights by adaptive steps over shuffled rows; the last entry is the intercept."""
    w, scale = np.zeros(FEATURES + 1), np.full(FEATURES + 1, 1e-3)
    draw = np.random.default_rng(seed)
    share = target.mean() if len(target) else 0.5
    weight = np.where(target >= 0.5, 0.5 / max(share, 1e-3), 0.5 / max(1 - share, 1e-3))  # both classes weigh alike
    for _ in range(PASSES):
        for i in draw.permutation(len(rows)):
            at, x = rows[i]
            err = weight[i] * (1 / (1 + math.exp(-max(-30.0, min(30.0, w[at] @ x + w[-1])))) - target[i])
            g = err * x
            scale[at] += g * g
            w[at] -= 0.5 * g / np.sqrt(scale[at])
            scale[-1] += err * err
            w[-1] -= 0.1 * err / math.sqrt(scale[-1])
    return w


class Scorer:
    """The fitted linear scorer."""

    def __init__(self, weights: np.ndarray):
        self.weights = weights.astype(np.float32)

    def score(self, text: str | None) -> float:
        at, x = features(text)
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, float(self.weights[at] @ x + self.weights[-1])))))


def fit(docs: DataFrame, sample: int = SAMPLE, seed: int = 0) -> tuple[Scorer, DataFrame]:
    """The scorer, and ``(pattern, n, posterior)``: all vote patterns of ``docs(doc_id, text)`` with their posterior."""
    spark = docs.sparkSession
    share = min(1.0, sample / max(1, docs.count()))
    # The draw is by id and text, so neither a repeated id nor rows without one are drawn as one.
    drawn = F.pmod(F.xxhash64("doc_id", "text", F.lit(seed)), F.lit(1 << 40)) <= int(share * (1 << 40))
    voted = by_row(lambda: lambda t: "".join("-01"[v + 1] for v in votes(t)), "string")
    hashed = by_row(lambda: lambda t: tuple(x.astype(k) for x, k in zip(features(t), (np.int32, np.float32), strict=True)), "at array<int>, x array<float>")
    counted = docs.select(voted("text").alias("pattern")).groupBy("pattern").agg(F.count("*").alias("n")).orderBy("pattern").toPandas()
    seen = [tuple("-01".index(c) - 1 for c in p) for p in counted["pattern"]]
    p, _, _ = estimate(seen, counted["n"].to_numpy(np.float64)) if len(seen) else (np.zeros(0), 0.5, None)
    table = spark.createDataFrame(pd.DataFrame({"pattern": counted["pattern"].astype(object), "n": counted["n"].astype("int64"), "posterior": p}), "pattern string, n long, posterior double")
    some = docs.where(drawn).select("doc_id", voted("text").alias("pattern"), hashed("text").alias("f"))
    data = some.join(F.broadcast(table.select("pattern", "posterior")), "pattern").select("doc_id", "posterior", "f.*").toArrow().to_pandas()
    # One order of steps, whatever the partitions.
    data["first"] = [tuple(a[:8].tolist()) + (len(a),) for a in data["at"]]
    data = data.sort_values(["doc_id", "first"], kind="stable")
    return Scorer(fit_linear(list(zip(data["at"], data["x"], strict=True)), data["posterior"].to_numpy(), seed)), table


def score(docs: DataFrame, scorer: Scorer) -> DataFrame:
    """``doc_id, score, keep`` for each row of ``docs(doc_id, text)``."""
    shared = docs.sparkSession.sparkContext.broadcast(scorer)
    scored = by_row(lambda: lambda t: shared.value.score(t), "double")
    return docs.select("doc_id", scored("text").alias("score")).withColumn("keep", F.col("score") >= KEEP)
