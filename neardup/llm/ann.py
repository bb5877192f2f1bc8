"""Approximate nearest neighbours: an adaptive dimension scan over probed lists.

Nearness is the largest inner product. One more dimension, ``sqrt(M^2 - |x|^2)`` with ``M`` the largest
length of all rows, turns it into the smallest Euclidean distance; a seeded random rotation then spreads
every difference evenly over the dimensions, so that after ``d`` of ``D`` of them the partial distance
estimates the whole. Lists come from k-means on a bounded sample; every row is indexed. On the same sample it
is measured how many of a query's nearest lists hold the ``RECALL`` share of its true neighbours: so many are
probed, few on data with structure and most on noise.

A query's k-th best score in its nearest list bounds the rest. Then it is sent to the lists it probes, and to
no other; a list is dealt to parts of about ``SHARD`` rows, the queries that probe it to blocks of about
``QUERIES``, and each part meets each block in one task. There column blocks are scanned in turn: once a
candidate's partial distance is, at the set confidence, too large for the query's bound, the rest of its
dimensions is not read. Survivors are scored exactly on the original vectors, in double precision and with one
fixed order of summation; a task returns at most ``k`` rows a query.

Defined cases: vectors that are null, empty, zero or hold null or non-finite components take no part, nor
do rows with a null id; vectors of another length than a query's are no candidates of it; ties go to the
smaller id; of repeated rows of one id the best counts; fewer than ``k`` candidates give fewer rows; extra
columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from neardup.llm.cells import fit, sampled, stacked, usable
from neardup.sources.lineage import written

#: Rows a part of a list, queries a block and a chunk of it, columns a block, the test's width.
SHARD, QUERIES, CHUNK, COLUMNS, EPSILON = 16_384, 4096, 64, 16, 2.1
#: Sampled rows and queries that set how many lists are probed, and the share of neighbours wanted there.
SAMPLE, ASKED, RECALL = 20_000, 256, 0.96


def rotation(dim: int, seed: int = 0) -> np.ndarray:
    """A seeded random orthogonal matrix."""
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(dim, dim)))
    return q * np.sign(np.diag(r))


def lifted(x: np.ndarray, most: float) -> np.ndarray:
    """Rows with the added dimension that makes them all ``most`` long."""
    return np.c_[x, np.sqrt(np.maximum(most * most - (x * x).sum(1), 0))]


def exact_scores(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Inner products, equal for equal rows."""
    return (x * q).sum(1)


def survivors(q: np.ndarray, x: np.ndarray, bound: np.ndarray, epsilon: float) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (row of ``q``, row of ``x``) of rotated rows that pass the tests: squared distance at most ``bound``, tried by column blocks."""
    dim = x.shape[1]
    limit = np.where(np.isfinite(bound), bound, np.inf)
    d = min(COLUMNS, dim)
    part = lambda at, to: (q[:, at:to] ** 2).sum(1)[:, None] + (x[:, at:to] ** 2).sum(1)[None, :] - 2 * (q[:, at:to] @ x[:, at:to].T)
    whole = part(0, d)
    while True:
        if d >= dim:
            i, j = np.nonzero(whole <= limit[:, None] * (1 + 1e-9) + 1e-9)
            return i, j
        go = whole * (dim / d) <= (limit * (1 + epsilon / math.sqrt(d)) ** 2)[:, None]
        if go.mean() < 0.2:
            break
        whole = np.where(go, whole + part(d, min(d + COLUMNS, dim)), np.inf)
        d = min(d + COLUMNS, dim)
    i, j = np.nonzero(go)
    partial = whole[i, j]
    while d < dim:  # few are left: pair by pair
        to = min(d + COLUMNS, dim)
        gap = q[i, d:to] - x[j, d:to]
        partial = partial + np.einsum("ij,ij->i", gap, gap)
        d = to
        wide = limit[i] * ((1 + epsilon / math.sqrt(d)) ** 2 * d / dim if d < dim else 1 + 1e-9) + 1e-9
        ok = partial <= wide
        i, j, partial = i[ok], j[ok], partial[ok]
    return i, j


def _answering(turn, most: float, k: int, epsilon: float):
    """The task that answers a block of queries from a part of a list; ``least`` is a query's bound on scores."""

    def answer(asks, data):
        none = pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype({"query_id": "int64", "vec_id": "int64", "score": "float64"})
        if not len(asks) or not len(data):
            return none
        x, ids = stacked(data["vec"]), data["vec_id"].to_numpy()
        q_all, q_ids = stacked(asks["vec"]), asks["vec_id"].to_numpy()
        turned = lifted(x, most) @ turn.value
        bound = most * most + (q_all * q_all).sum(1) - 2 * asks["least"].to_numpy(np.float64)
        out = []
        for s in range(0, len(q_all), CHUNK):
            q = q_all[s : s + CHUNK]
            i, j = survivors(np.c_[q, np.zeros(len(q))] @ turn.value, turned, bound[s : s + CHUNK], epsilon)
            other = q_ids[s + i] != ids[j]
            i, j = i[other], j[other]
            score = exact_scores(x[j], q[i])
            order = np.lexsort((ids[j], -score, i))
            i, j, score = i[order], j[order], score[order]
            place = np.arange(len(i)) - np.searchsorted(i, i)
            top = place < k
            out.append(pd.DataFrame({"query_id": q_ids[s + i[top]], "vec_id": ids[j[top]], "score": score[top]}))
        return pd.concat(out) if out else none

    return answer


def _order(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Lists from the nearest on."""
    return np.argsort(-(x @ c.T), axis=1, kind="stable")


def probes_for(sample: np.ndarray, c: np.ndarray, k: int, recall: float = RECALL, seed: int = 0) -> int:
    """How many of its nearest lists a query must probe to meet the share of its neighbours in the sample."""
    if len(sample) <= 1 or len(c) == 1:
        return len(c)
    home = np.concatenate([(sample[s : s + 2048] @ c.T).argmax(1) for s in range(0, len(sample), 2048)])
    asked = np.random.default_rng(seed).permutation(len(sample))[:ASKED]
    k = min(k, len(sample) - 1)
    need = np.zeros(len(c), np.int64)
    place_of = np.empty((len(asked), len(c)), np.int64)
    np.put_along_axis(place_of, _order(sample[asked], c), np.arange(len(c))[None, :], axis=1)
    for row, a in enumerate(asked):
        s = sample @ sample[a]
        s[a] = -np.inf
        np.add.at(need, place_of[row, home[np.argpartition(-s, k - 1)[:k]]], 1)
    return int(np.searchsorted(np.cumsum(need), recall * need.sum() - 1e-9)) + 1


def search(
    vectors: DataFrame, is_query, k: int = 20, probed: float | None = None, epsilon: float = EPSILON, seed: int = 0,
    shard: int = SHARD, block: int = QUERIES,
) -> DataFrame:
    """``query_id, rank, vec_id, score``: for each row of ``vectors(vec_id, embedding)`` with ``is_query`` its ``k`` nearest others.

    ``probed``: the share of lists a query probes; by default as many as the sample asks for.
    """
    spark = vectors.sparkSession
    rows = written(
        vectors.select("vec_id", F.col("embedding").alias("vec"), is_query.alias("asks"))
        .where(usable() & F.col("vec_id").isNotNull())
        .withColumn("dim", F.size("vec"))
    )
    kind = dict(rows.dtypes)["vec"]
    length = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda a, v: a + v.cast("double") * v.cast("double")))
    dims = rows.groupBy("dim").agg(F.count("*").alias("n"), F.count_if("asks").alias("asked"), F.max(length).alias("most")).collect()
    parts = []
    for r in dims:  # a row for each vector length
        if not r["asked"]:
            continue
        n, dim, most = r["n"], r["dim"], r["most"] * (1 + 1e-12)
        own = rows.where(F.col("dim") == dim)
        c = fit(own.select(F.col("vec_id").alias("id"), "vec"), max(1, min(round(math.sqrt(n) / 4), 1024)), seed)
        if probed is None:
            probes = probes_for(sampled(own.select(F.col("vec_id").alias("id"), "vec"), SAMPLE, seed), c, k, seed=seed)
        else:
            probes = max(1, math.ceil(probed * len(c)))
        centres, turn = spark.sparkContext.broadcast(c), spark.sparkContext.broadcast(rotation(dim + 1, seed))

        def index(batches, centres=centres):
            for pdf in batches:
                if len(pdf):
                    yield pdf.assign(list=(stacked(pdf["vec"]) @ centres.value.T).argmax(1).astype("int32"))

        def route(batches, centres=centres, probes=probes):
            for pdf in batches:
                if len(pdf):
                    yield pdf.assign(lists=list(_order(stacked(pdf["vec"]), centres.value)[:, :probes].astype("int32")))

        indexed = written(own.select("vec_id", "vec").mapInPandas(index, f"vec_id long, vec {kind}, list int"))
        asks = own.where("asks").select("vec_id", "vec").mapInPandas(route, f"vec_id long, vec {kind}, lists array<int>")
        asks = written(asks)
        # Lists are at most 1,024, and so are the rows of these counts.
        splits = indexed.groupBy("list").agg(F.ceil(F.count("*") / shard).cast("int").alias("splits"))
        placed = indexed.join(F.broadcast(splits), "list").withColumn("split", F.pmod(F.xxhash64("vec_id", F.lit(3)), F.col("splits")).cast("int"))
        answer = _answering(turn, most, k, epsilon)
        schema = "query_id long, vec_id long, score double"

        def meet(asked, rows_, placed=placed, answer=answer):
            """Answers of ``asked(vec_id, vec, least, list, split)`` from the rows of their list and part."""
            blocks = asked.groupBy("list", "split").agg(F.ceil(F.count("*") / block).cast("int").alias("blocks"))
            blocks = F.broadcast(blocks) if rows_ else blocks
            at = asked.join(blocks, ["list", "split"]).withColumn("qb", F.pmod(F.xxhash64("vec_id", F.lit(5)), F.col("blocks")).cast("int")).drop("blocks")
            held = placed.join(blocks, ["list", "split"]).select("vec_id", "vec", "list", "split", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("qb"))
            return at.groupBy("list", "split", "qb").cogroup(held.groupBy("list", "split", "qb")).applyInPandas(answer, schema)

        few = splits.agg(F.sum("splits")).first()[0] <= 20_000
        none = F.lit(float("-inf"))
        first = asks.select("vec_id", "vec", none.alias("least"), F.col("lists")[0].alias("list"), F.lit(0).alias("split"))
        near = written(meet(first, few))
        own_rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
        kth = near.withColumn("r", own_rank).where(F.col("r") == k).select(F.col("query_id").alias("vec_id"), F.col("score").alias("least"))
        bounded = asks.join(kth.dropDuplicates(["vec_id"]), "vec_id", "left").withColumn("least", F.coalesce("least", none))
        rest = bounded.select("vec_id", "vec", "least", F.posexplode("lists").alias("place", "list")).join(F.broadcast(splits), "list")
        rest = rest.withColumn("split", F.explode(F.sequence(F.lit(0), F.col("splits") - 1))).where("place > 0 or split > 0")
        parts += [near, meet(rest.select("vec_id", "vec", "least", "list", "split"), few)]
    if not parts:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    found = parts[0]
    for p in parts[1:]:
        found = found.union(p)
    best = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return best.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def nearest_of_every(vectors: DataFrame, modulus: int = 20, k: int = 20, **options) -> DataFrame:
    """``search()`` with every row whose id is divisible by ``modulus`` as a query."""
    return search(vectors, F.coalesce(F.col("vec_id") % modulus == 0, F.lit(False)), k, **options)
