"""An exact join of sets by their similarity, without a list of candidates."""

from __future__ import annotations

import hashlib
from fractions import Fraction

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.functions import text as T
from neardup.sources.lineage import drop_written, written

#: Postings that a task compares, pairs it compares at once, and bits of a sketch.
TASK_ROWS, AT_ONCE, SKETCH = 65_536, 200_000, 512
#: Pairs of a smallest neighbour that one unit decides, and sets a unit.
PART, UNIT_SETS = 100_000, 2048
#: Terms that a task puts in lists, and copies whose ids are broadcast.
POSTINGS, SMALL = 1_000_000, 500_000
#: Sets of the sample that orders terms, and the most terms it orders. They set the order alone, never the result.
SAMPLE, COMMON = 10_000, 200_000


def run_sets(items: DataFrame, size: int = 3) -> DataFrame:
    """``items(item_id, text)`` to ``(item_id, terms)``: hashes of the runs of ``size`` words, all words as one run where there are fewer."""
    w = items.select("item_id", T.words().alias("w"))
    run = lambda i: F.xxhash64(*(F.get("w", i + k) for k in range(size)))
    return w.select("item_id", F.transform(F.sequence(F.lit(0), F.greatest(F.size("w") - size, F.lit(0))), run).alias("terms"))


def _least(na, nb, limit: Fraction, measure: str):
    """The least overlap of similar sets of these sizes, in whole numbers."""
    if measure == "jaccard":
        return -(-(na + nb) * limit.numerator // (limit.numerator + limit.denominator))
    return -(-np.maximum(na, nb) * limit.numerator // limit.denominator)


def _set_of(terms) -> np.ndarray:
    return np.unique(np.asarray(terms, np.int64))


def _common(items: DataFrame, make) -> tuple[np.ndarray, np.ndarray]:
    """Terms frequent in a sample, sorted, and their rank by frequency."""
    parts = max(1, items.count() // SAMPLE)
    some = items.where(F.pmod(F.xxhash64("item_id", F.lit(11)), F.lit(parts)) == 0)
    seen = make(some).select(F.explode(F.array_distinct("terms")).alias("h")).groupBy("h").count()
    top = seen.where("count > 1").orderBy(F.desc("count"), "h").limit(COMMON).toPandas()
    h = top["h"].to_numpy(np.int64)
    order = np.argsort(h)
    return h[order], np.arange(len(h), 0, -1)[order]


def _digest(terms: np.ndarray) -> bytes:
    return hashlib.blake2b(terms.tobytes(), digest_size=16).digest()


def _parity(terms: np.ndarray, bits: int) -> bytes:
    """Parities of the numbers of terms by their last bits: sets differ in as many terms as parities at least."""
    return np.packbits(np.bincount(terms & (bits - 1), minlength=bits).astype(np.uint8) & 1).tobytes()


def _lists(posted: DataFrame, postings: int) -> DataFrame:
    """Lists ``(term, reps, low)`` of two sets or more of ``posted(item_id, prefix)``, which go to tasks of terms as packed columns."""
    tasks = max(1, -(-int(postings) // POSTINGS))

    def deal(batches):
        for pdf in batches:
            pdf = pdf.sort_values("item_id")
            if not len(pdf):
                continue
            h, ids = np.concatenate(list(pdf["prefix"])), np.repeat(pdf["item_id"].to_numpy(np.int64), [len(x) for x in pdf["prefix"]])
            task = h % tasks
            order = np.argsort(task, kind="stable")
            out = []
            for n, at in enumerate(np.split(order, np.searchsorted(task[order], np.arange(1, tasks)))):
                if len(at):
                    steps = np.diff(ids[at]).view(np.uint64)
                    steps = steps.astype(np.min_scalar_type(int(steps.max(initial=0))))
                    out.append((n, int(ids[at[0]]), steps.itemsize, steps.tobytes(), h[at].tobytes()))
            yield pd.DataFrame(out, columns=["task", "id", "size", "steps", "terms"])

    def gather(parts: pd.DataFrame) -> pd.DataFrame:
        h = np.frombuffer(b"".join(parts["terms"]), np.int64)
        unpacked = ((i, np.frombuffer(x, f"u{w}").astype(np.uint64).view(np.int64)) for i, w, x in zip(parts["id"], parts["size"], parts["steps"], strict=True))
        reps = np.concatenate([np.cumsum(np.concatenate([[i], x])) for i, x in unpacked])
        order = np.argsort(h)
        same = np.diff(h[order]) == 0
        order = order[np.concatenate([same, [False]]) | np.concatenate([[False], same])]
        order = order[np.lexsort((reps[order], h[order]))]
        h, reps = h[order], reps[order]
        fresh = np.concatenate([[True], (np.diff(h) != 0) | (np.diff(reps) != 0)])[: len(h)]
        h, reps = h[fresh], reps[fresh]
        terms, start, length = np.unique(h, return_index=True, return_counts=True)
        out = pd.DataFrame({"term": terms, "reps": np.split(reps, start[1:]) if len(h) else [], "low": reps[start]})
        return out[length > 1]

    dealt = posted.select("item_id", "prefix").mapInPandas(deal, "task long, id long, size int, steps binary, terms binary")
    return dealt.groupBy("task").applyInPandas(gather, "term long, reps array<long>, low long")


def _meetings(lists: DataFrame, reps: DataFrame, share: Fraction, measure: str) -> DataFrame:
    """Pairs ``(a, b, na, nb, c)`` of sets ``reps(rep, n, sketch)`` that can be similar and meet ``c`` times in ``lists(term, reps, low)``.

    Sets that share a term share many: lists go by their smallest set ``low`` to a task, or to several if they are long, so a
    pair comes from few tasks, and a task has each of its sets once.
    """
    loads = written(lists.groupBy("low").agg(F.sum(F.size("reps")).alias("rows")))
    tasks = max(1, -(-(loads.agg(F.sum("rows")).first()[0] or 0) // TASK_ROWS))
    parts = F.ceil(F.col("rows") / TASK_ROWS)
    dealt = lists.join(loads, "low").select("reps", F.pmod(F.xxhash64("low", F.pmod(F.xxhash64("term"), parts)), F.lit(tasks)).alias("task"))
    members = dealt.select("task", F.explode("reps").alias("rep")).distinct().join(reps.select("rep", "n", "sketch"), "rep").select(F.col("task").alias("of"), "rep", "n", "sketch")

    def compare(lists: pd.DataFrame, members: pd.DataFrame) -> pd.DataFrame:
        members = members.sort_values("rep")
        rep, n = members["rep"].to_numpy(), members["n"].to_numpy(np.int64)
        sketch = np.frombuffer(b"".join(members["sketch"]), np.uint64).reshape(len(members), -1)
        length = np.array([len(x) for x in lists["reps"]])
        start, ids = np.cumsum(length) - length, np.searchsorted(rep, np.concatenate(list(lists["reps"])))
        keys, times, fresh = np.zeros(0, np.int64), np.zeros(0, np.int64), []

        def count() -> None:
            nonlocal keys, times
            new, c = np.unique(np.concatenate([keys[:0], *fresh]), return_counts=True)
            keys, at = np.unique(np.concatenate([keys, new]), return_inverse=True)
            times = np.bincount(at, np.concatenate([times, c]), len(keys)).astype(np.int64)
            fresh.clear()

        def keep(x: np.ndarray, y: np.ndarray) -> None:
            x, y = ids[x], ids[y]
            fits = np.minimum(n[x], n[y]) * share.denominator >= np.maximum(n[x], n[y]) * share.numerator
            x, y = x[fits], y[fits]
            apart = np.bitwise_count(sketch[x] ^ sketch[y]).sum(1, dtype=np.int64)
            near = apart <= n[x] + n[y] - 2 * _least(n[x], n[y], share, measure)
            fresh.append(x[near] * len(rep) + y[near])
            if sum(map(len, fresh)) > 20 * AT_ONCE:
                count()

        for m in np.unique(length):
            at = start[length == m]
            if m * m > AT_ONCE:  # one list, its rows in slices
                step = max(1, AT_ONCE // int(m))
                for s in at:
                    for i in range(0, int(m), step):
                        x, y = np.meshgrid(np.arange(i, min(i + step, m)), np.arange(i + 1, m), indexing="ij")
                        keep(s + x[x < y], s + y[x < y])
                continue
            x, y = np.triu_indices(int(m), 1)
            step = max(1, AT_ONCE // max(1, len(x)))
            for s in range(0, len(at), step):
                one = at[s : s + step, None]
                keep((one + x).ravel(), (one + y).ravel())
        count()
        a, b = keys // len(rep), keys % len(rep)
        return pd.DataFrame({"a": rep[a], "b": rep[b], "na": n[a], "nb": n[b], "c": times})

    return dealt.groupBy("task").cogroup(members.groupBy("of")).applyInPandas(compare, "a long, b long, na long, nb long, c long")


def _units(pairs: DataFrame) -> DataFrame:
    """``pairs(a, b, na, nb)`` with the ``unit`` that decides them, so that a set goes to few of these.

    Pairs go by the smallest neighbour of their smaller set, as sets alike have the same one; if it has many pairs, to
    parts by that set, so only the larger ones go to several.
    """
    lows = pairs.groupBy("b").agg(F.min("a").alias("low")).select(F.col("b").alias("a"), "low")
    near = written(pairs.join(lows, "a", "left").select("a", "b", "na", "nb", F.coalesce("low", "a").alias("low")))
    parts = near.groupBy("low").agg(F.ceil(F.count("*") / PART).alias("parts"))
    units = max(1, -(-near.select(F.explode(F.array("a", "b")).alias("item")).distinct().count() // UNIT_SETS))
    unit = F.pmod(F.xxhash64("low", F.pmod(F.xxhash64("a", F.lit(3)), F.col("parts"))), F.lit(units))
    return near.join(parts, "low").select("a", "b", "na", "nb", unit.alias("unit"))


def _asked(pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``pairs`` with their units, and the sets ``(item_id, unit)`` that these need."""
    at = written(_units(pairs))
    return at, written(at.select(F.explode(F.array("a", "b")).alias("item_id"), "unit").distinct())


def similar_sets(items: DataFrame, limit: float, measure: str = "jaccard", make=None) -> tuple[DataFrame, DataFrame]:
    """Pairs ``(a, b, overlap, na, nb)`` of different sets of ``items(item_id, terms)``, and ``classes(rep, item_id, n)``.

    Similar are sets of at least ``limit`` in ``jaccard``, or whose overlap is at least that share of the ``larger`` one. Equal
    sets are one class, its smallest item; ``n`` is their size, and sets without terms are in no class. ``make`` gives ``terms``
    of some of ``items``, if they have none yet.

    In one order of terms, frequent ones last, similar sets share a term among the first ``n - ceil(limit * n) + 1`` of each. Lists of
    these are compared where they lie: sizes and parities of the sets drop pairs that cannot be similar, and so does the number
    of such terms that they share. Of pairs left, parities four times as wide as the sets drop more; the others are decided on the sets.
    """
    share = Fraction(limit).limit_denominator(10**6)
    make = make or (lambda rows: rows)
    order = items.sparkSession.sparkContext.broadcast(_common(items, make))

    def profile(batches):
        for pdf in batches:
            out = []
            for item, terms in zip(pdf["item_id"], pdf["terms"], strict=True):
                h = _set_of(terms)
                if len(h):
                    out.append((item, _digest(h), len(h), _parity(h, SKETCH), _parity(h, max(SKETCH, 1 << (4 * len(h) - 1).bit_length()))))
            yield pd.DataFrame(out, columns=["item_id", "digest", "n", "sketch", "wide"])

    def prefix(batches):
        common, rank = order.value
        for pdf in batches:
            out = []
            for item, terms in zip(pdf["item_id"], pdf["terms"], strict=True):
                h = _set_of(terms)
                if not len(h):
                    continue
                at = np.minimum(np.searchsorted(common, h), max(0, len(common) - 1))
                often = common[at] == h if len(common) else np.zeros(len(h), bool)
                late = h[often][np.argsort(rank[at[often]], kind="stable")] if often.any() else h[:0]
                first = len(h) + int(-len(h) * share.numerator // share.denominator) + 1
                out.append((item, _digest(h), np.concatenate([h[~often], late])[:first]))
            yield pd.DataFrame(out, columns=["item_id", "digest", "prefix"])

    # Prefixes are most of the bytes: they are worked out anew, go to the lists of their terms once, and are not written.
    sized = written(make(items).mapInPandas(profile, "item_id long, digest binary, n long, sketch binary, wide binary"))
    reps = written(sized.groupBy("digest", "n", "sketch").agg(F.min("item_id").alias("rep")))
    copies = written(sized.join(reps, (sized["item_id"] == reps["rep"]) & (sized["digest"] == reps["digest"]), "left_anti").select("item_id", "digest"))
    first = F.col("n") + F.ceil(-F.col("n") * share.numerator / share.denominator) + 1
    posted = make(items).mapInPandas(prefix, "item_id long, digest binary, prefix array<long>")
    posted = posted.join(F.broadcast(copies) if copies.count() <= SMALL else copies, ["item_id", "digest"], "left_anti")
    lists = written(_lists(posted, reps.agg(F.sum(first)).first()[0] or 0))
    met = _meetings(lists, reps, share, measure)
    num, den = share.numerator, share.denominator
    rest = lambda c: F.ceil(F.col(c) * num / den) - 1
    up = lambda x, by: F.floor((x + by - 1) / by)
    need = up((F.col("na") + F.col("nb")) * num, num + den) if measure == "jaccard" else up(F.greatest("na", "nb") * num, den)
    counted = met.groupBy("a", "b", "na", "nb").agg(F.sum("c").alias("c"))
    pairs = written(counted.where(F.col("c") >= need - F.greatest(rest("na"), rest("nb")) - 1))
    drop_written(lists)

    at, asked = _asked(pairs)
    held = sized.select("item_id", "wide").join(asked, "item_id").select("item_id", "wide", F.col("unit").alias("of"))

    def thin(pairs: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
        wide = {i: np.frombuffer(x, np.uint64) for i, x in zip(held["item_id"], held["wide"], strict=True)}
        apart = np.zeros(len(pairs), np.int64)
        for n, (a, b) in enumerate(zip(pairs["a"], pairs["b"], strict=True)):
            x, y = sorted((wide[a], wide[b]), key=len)
            apart[n] = np.bitwise_count(x ^ np.bitwise_xor.reduce(y.reshape(-1, len(x)))).sum()
        na, nb = pairs["na"].to_numpy(np.int64), pairs["nb"].to_numpy(np.int64)
        return pairs.loc[apart <= na + nb - 2 * _least(na, nb, share, measure), ["a", "b", "na", "nb"]]

    at, asked = _asked(written(at.groupBy("unit").cogroup(held.groupBy("of")).applyInPandas(thin, "a long, b long, na long, nb long")))
    held = make(items.join(asked.select("item_id").distinct(), "item_id", "left_semi")).join(asked, "item_id").select("item_id", "terms", F.col("unit").alias("of"))

    def decide(pairs: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
        sets = {i: _set_of(t) for i, t in zip(held["item_id"], held["terms"], strict=True)}
        both = [len(np.intersect1d(sets[a], sets[b], assume_unique=True)) for a, b in zip(pairs["a"], pairs["b"], strict=True)]
        out = pairs[["a", "b", "na", "nb"]].assign(overlap=np.array(both, np.int64))
        least = _least(out["na"].to_numpy(np.int64), out["nb"].to_numpy(np.int64), share, measure)
        return out[out["overlap"].to_numpy() >= least]

    similar = written(at.groupBy("unit").cogroup(held.groupBy("of")).applyInPandas(decide, "a long, b long, na long, nb long, overlap long"))
    classes = sized.select("item_id", "digest").join(reps.select("digest", "rep", "n"), "digest").select("rep", "item_id", "n")
    return similar, classes


def expanded(pairs: DataFrame, classes: DataFrame) -> DataFrame:
    """Pairs ``(a, b, overlap, na, nb)`` of all items: those of ``similar_sets`` between the members of both classes, and those within a class."""
    of = lambda c: classes.select(F.col("rep").alias(c), F.col("item_id").alias(f"i{c}"))
    other = pairs.join(of("a"), "a").join(of("b"), "b")
    low = F.col("ia") < F.col("ib")
    size = lambda x, y: F.when(low, F.col(x)).otherwise(F.col(y))
    other = other.select(F.least("ia", "ib").alias("a"), F.greatest("ia", "ib").alias("b"), "overlap", size("na", "nb").alias("na"), size("nb", "na").alias("nb"))
    same = classes.select("rep", "n", F.col("item_id").alias("a")).join(classes.select("rep", F.col("item_id").alias("b")), "rep").where("a < b")
    return other.unionByName(same.select("a", "b", F.col("n").alias("overlap"), F.col("n").alias("na"), F.col("n").alias("nb")))
