"""SimHash near-dedup: byte-position inverted index with count filtering.

A fingerprint is a row of positional bytes. The inverted index lists fingerprints under combinations of
positional bytes, chosen so that every pair with the guaranteed number of matching bytes meets in some list.
Within a list the shared positional bytes of each pair are tallied, pairs that reach the guaranteed minimum
are kept and verified by their differing bits.

* ``near_duplicates`` uses 64 majority bits of word-shingle hashes: two fingerprints that differ in at most
  ``max_bits`` bits agree in at least ``8 - max_bits`` bytes, so no link is missed.
* ``linked_documents`` joins both kinds of links below; the pipeline takes it.
* ``similar_documents`` finds texts by the exact similarity of their distinct word shingles, without
  fingerprints. In one common order of shingles (frequent ones last), two sets of similarity ``t`` share a
  shingle among their first ``n - ceil(t n) + 1``, whatever was edited, so lists of these miss no pair. Sizes
  and parity sketches as wide as the sets drop pairs that cannot reach ``t``; the rest is decided on the sets.
  Each list's least entry is compared first, then only pairs that are still in two components.

Of fingerprints, keys combine more bytes as the number of distinct fingerprints grows, so that lists of unrelated ones stay
short; equal fingerprints are one entry. A list longer than ``BLOCK`` (a large group of near copies) is
compared in blocks, one task a pair of blocks. A task returns no pairs but a forest that spans its links, at
most one edge a fingerprint; components come from the distributed closure.

Defined cases: a null text counts as empty; the empty text has fingerprint zero, linked like any other; rows
with a null id keep their fingerprint and get a null component; repeated rows stay and share their
component; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import math
from fractions import Fraction
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from neardup.llm.batches import by_row
from neardup.llm.blocks import dense_roots, forest
from neardup.operators.closure import components
from neardup.sources.lineage import drop_written, written

#: Rows a block of a long list, rows of short lists a task holds, most fingerprints of a random list.
BLOCK, TASK_ROWS, LIST = 4096, 65_536, 1024
#: Pairs (of two ids and digests) that may be broadcast, and partners of an entry that one task checks.
FEW, PARTNERS = 500_000, 64
#: Bits of a shingle set's sketch, documents of the sample that orders shingles, and the most shingles ordered by it.
SKETCH, SAMPLE, COMMON = 512, 10_000, 100_000


def _majority(h: np.ndarray) -> np.ndarray:
    """Bytes of the bits that are set in over half of the 64-bit hashes."""
    bits = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    whole = len(bits) // 255 * 255  # counts of 255 rows fit a byte, and bytes add fast
    count = bits[:whole].reshape(-1, 255, 64).sum(1, dtype=np.uint8).sum(0, dtype=np.int64) + bits[whole:].sum(0, dtype=np.int64)
    return np.packbits(count * 2 > len(h), bitorder="little")


def _shingle_hashes(words: list[bytes], shingle: int) -> np.ndarray:
    """XXH64 (seed 42) of the word shingles of a text, repeats included; of all of it if it has fewer words."""
    import xxhash

    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    if len(words) <= shingle:
        spans = [(0, len(joined))]
    else:
        spans = zip([0, *(ends[:-shingle] + 1).tolist()], ends[shingle - 1 :].tolist(), strict=True)
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(joined[s:e], 42) for s, e in spans), np.uint64)


def simhash(text: bytes, shingle: int = 3) -> int:
    """Fingerprint of one UTF-8 text, as a signed 64-bit number."""
    words = text.lower().split()  # bytes: A-Z only, and exactly the six ASCII white-space bytes
    return int(_majority(_shingle_hashes(words, shingle)).view(np.int64)[0]) if words else 0


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """``(doc_id, fp)`` with ``fp`` a long, one row per row of ``docs(doc_id, text)``."""
    fp = by_row(lambda: lambda t: simhash(t, shingle), "long", binary=True)
    return docs.select("doc_id", fp(F.col("text").cast("binary")).alias("fp"))


def key_family(n_bytes: int, matches: int, width: int) -> list[tuple[int, ...]]:
    """Combinations of ``width`` byte positions such that any ``matches`` of ``n_bytes`` positions hold one whole.

    Positions are dealt to so few groups that ``matches`` of them put ``width`` into one group; the keys are
    all combinations within the groups.
    """
    groups = max(1, (matches - 1) // (width - 1)) if width > 1 else n_bytes - matches + 1
    if width == 1:
        return [(p,) for p in range(groups)]
    groups = min(groups, n_bytes // width)
    return [c for g in range(groups) for c in combinations(range(g, n_bytes, groups), width)]


def key_width(n: int, matches: int, odds: float) -> int:
    """Bytes a key combines for ``n`` entries, if two unrelated ones agree in a byte with probability ``odds``."""
    width = 2
    while width < min(matches, 5) and n * odds**width > LIST:
        width += 1
    return width


def _match(ia, ib, ca, cb, matches: int, max_bits: int) -> np.ndarray:
    """Whether rows (last axis: 64-bit words) share enough positional bytes and differ in few enough bits."""
    x = ia ^ ib
    tally = (x.view(np.uint8) == 0).sum(-1, dtype=np.uint8)
    ok = tally >= matches
    if ca is not ia:
        ok[ok] = np.bitwise_count(np.broadcast_to(ca, x.shape)[ok] ^ np.broadcast_to(cb, x.shape)[ok]).sum(-1) <= max_bits
    else:
        ok &= np.bitwise_count(x).sum(-1) <= max_bits
    return ok


def _links(ids, index, check, first: np.ndarray, matches: int, max_bits: int):
    """Verified links between rows of one block pair (``first``: rows of the first block; all: one block)."""
    whole = first.all()
    a = np.flatnonzero(first)
    b = a if whole else np.flatnonzero(~first)
    linked = np.zeros((len(a), len(b)), bool)
    step = max(16, 512 // index.shape[1])
    for s in range(0, len(a), step):
        r = a[s : s + step]
        ia = index[r, None]
        ca = ia if check is index else check[r, None]
        linked[s : s + step] = _match(ia, index[None, b], ca, check[None, b], matches, max_bits)
    if whole:
        root = dense_roots(linked)
        keep = root != np.arange(len(a))
        return ids[a[keep]], ids[a[root[keep]]]
    hit, col = np.flatnonzero(linked.any(1)), np.flatnonzero(linked.any(0))
    # First partners of all rows and columns, then more links until none crosses two pieces.
    out_a = [ids[a[hit]], ids[b[col]]]
    out_b = [ids[b[linked[hit].argmax(1)]], ids[a[linked[:, col].argmax(0)]]]
    while True:
        lo, hi = forest(np.concatenate(out_a), np.concatenate(out_b))
        piece = pd.Series(ids).map(pd.Series(hi, lo)).fillna(pd.Series(ids)).to_numpy(ids.dtype)
        cross = linked & (piece[a][:, None] != piece[b][None, :])
        rows = np.flatnonzero(cross.any(1))
        if not len(rows):
            return lo, hi
        out_a, out_b = [lo, ids[a[rows]]], [hi, ids[b[cross[rows].argmax(1)]]]


def _short(keys, ids, index, check, matches: int, max_bits: int):
    """Verified links of many whole lists at once: lists of equal length are compared together."""
    order = np.argsort(keys, kind="stable")
    own = check is index
    ids, index = ids[order], index[order]
    check = index if own else check[order]
    _, start, length = np.unique(keys[order], return_index=True, return_counts=True)
    a, b = [], []
    for n in np.unique(length):
        if n < 2:
            continue
        at = start[length == n]
        if n > 512:
            for s in at:
                part = index[s : s + n]
                lo, hi = _links(ids[s : s + n], part, part if own else check[s : s + n], np.ones(n, bool), matches, max_bits)
                a.append(lo)
                b.append(hi)
            continue
        step = max(1, 400_000 // int(n * n * index.shape[1]))
        for s in range(0, len(at), step):
            rows = at[s : s + step, None] + np.arange(n)
            ia = index[rows][:, :, None]
            ca = ia if own else check[rows][:, :, None]
            ok = _match(ia, index[rows][:, None], ca, check[rows][:, None], matches, max_bits)
            g, i, j = np.nonzero(np.triu(ok, 1))
            a.append(ids[rows[g, i]])
            b.append(ids[rows[g, j]])
    return np.concatenate(a) if a else ids[:0], np.concatenate(b) if b else ids[:0]


def near_edges(reps: DataFrame, matches: int, max_bits: int, odds: float = 1 / 256) -> DataFrame:
    """Edges that span the links between entries of ``reps(rep, idx, chk)``, written once.

    ``idx`` and ``chk`` are fingerprints as bytes: the first is indexed and tallied, the second (null: the
    first) verified.
    """
    n = reps.count()
    n_bytes = (reps.select(F.max(F.length("idx"))).first()[0] or 8) if n else 8
    family = key_family(n_bytes, matches, key_width(n, matches, odds))
    mark = lambda no: F.lit(no.to_bytes(4, "big"))
    keys = [F.xxhash64(F.concat(mark(no), *(F.substring("idx", p + 1, 1) for p in c))) for no, c in enumerate(family)]
    listed = reps.select("rep", "idx", "chk", F.explode(F.array(*keys)).alias("key"))
    long_lists = written(listed.groupBy("key").count().where(F.col("count") > BLOCK))
    tasks = max(1, -(-n * len(family) // TASK_ROWS))
    n_long = long_lists.count()
    if n_long:
        sized = F.broadcast(long_lists) if n_long <= 20_000 else long_lists
        listed = listed.join(sized, "key", "left")
        blocks = F.ceil(F.col("count") / BLOCK).cast("int")
        own = F.pmod(F.xxhash64("rep", F.lit(7)), blocks).cast("int")
        units = F.when(
            F.col("count").isNotNull(),
            F.transform(
                F.sequence(F.lit(0), blocks - 1),
                lambda o: F.struct(F.col("key").alias("unit"), F.least(own, o).alias("i"), F.greatest(own, o).alias("j")),
            ),
        )
    else:
        units, own = F.lit(None), F.lit(0)
    light = F.array(F.struct(F.pmod(F.xxhash64("key"), F.lit(tasks)).alias("unit"), F.lit(-1).alias("i"), F.lit(-1).alias("j")))
    dealt = listed.select("rep", "idx", "chk", "key", own.alias("own"), F.explode(F.coalesce(units, light)).alias("u")).select(
        "rep", "idx", "chk", "key", F.coalesce("own", F.lit(0)).alias("own"), "u.unit", "u.i", "u.j"
    )

    def compare(at: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        ids = rows["rep"].to_numpy()
        index = np.frombuffer(b"".join(rows["idx"]), np.uint64).reshape(len(rows), -1)
        check = index if rows["chk"].isna().any() else np.frombuffer(b"".join(rows["chk"]), np.uint64).reshape(len(rows), -1)
        if at[1] < 0:
            a, b = _short(rows["key"].to_numpy(), ids, index, check, matches, max_bits)
        else:
            a, b = _links(ids, index, check, rows["own"].to_numpy() == at[1], matches, max_bits)
        a, b = forest(a, b) if len(a) else (a, b)
        return pd.DataFrame({"src": b, "dst": a})

    edges = written(dealt.groupBy("unit", "i", "j").applyInPandas(compare, "src long, dst long"))
    drop_written(long_lists)
    return edges


def _with_components(fps: DataFrame, reps: DataFrame, edges: DataFrame, by: list[str]) -> DataFrame:
    """``fps`` with ``component_id``: that of its entry in ``reps``, found by the columns ``by``."""
    found = components(edges).withColumnRenamed("item", "rep")
    linked = reps.join(found, "rep", "left").select(*by, F.coalesce("component", "rep").alias("component_id"))
    known = F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id")
    return fps.join(linked, by, "left").select(*fps.columns, known)


def near_duplicates(docs: DataFrame, max_bits: int = 3, shingle: int = 3) -> DataFrame:
    """One row per row of ``docs(doc_id, text)``: ``doc_id, fp, component_id``.

    ``component_id`` is the smallest ``doc_id`` reachable over links of at most ``max_bits`` differing bits.
    """
    fps = written(fingerprints(docs, shingle))
    reps = written(fps.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("rep")))
    as_bytes = F.unhex(F.lpad(F.hex("fp"), 16, "0"))
    entries = reps.select("rep", as_bytes.alias("idx"), F.lit(None).cast("binary").alias("chk"))
    return _with_components(fps, reps, near_edges(entries, 8 - max_bits, max_bits), ["fp"])


def _distinct_shingles(text: bytes, shingle: int) -> np.ndarray:
    """Sorted hashes of a text's distinct shingles; none of a text without words."""
    words = text.lower().split()
    return np.unique(_shingle_hashes(words, shingle)) if words else np.zeros(0, np.uint64)


def _digest(h: np.ndarray) -> bytes:
    return hashlib.blake2b(h.tobytes(), digest_size=16).digest()


def _profile(h: np.ndarray, common: np.ndarray, rank: np.ndarray, limit: Fraction) -> tuple:
    """``digest, n, sketch, parity, prefix`` of a shingle set.

    The order is: shingles not in ``common`` by hash, then common ones by ``rank``. Sets of similarity
    ``limit`` or more share a shingle among the first ``n - ceil(limit * n) + 1`` of each in any one order.
    ``parity`` holds the parities of about as many buckets as there are shingles, ``sketch`` of ``SKETCH`` buckets:
    sets differ in at least as many shingles as these differ in bits.
    """
    n = len(h)
    often = np.zeros(n, bool)
    if len(common) and n:
        at = np.minimum(np.searchsorted(common, h), len(common) - 1)
        often = common[at] == h
    late = h[often]
    if len(late):
        late = late[np.argsort(rank[at[often]], kind="stable")]
    prefix = np.concatenate([h[~often], late])[: n - math.ceil(limit * n) + 1]
    wide = max(SKETCH, 1 << max(0, n - 1).bit_length())
    parity = np.packbits(np.bincount((h & np.uint64(wide - 1)).astype(np.int64), minlength=wide) & 1)
    return _digest(h), n, _folded(parity.view(np.uint64), SKETCH // 64).tobytes(), parity.tobytes(), prefix.view(np.int64)


def _folded(parity: np.ndarray, words: int) -> np.ndarray:
    """Parities of fewer buckets, from those of a multiple of them."""
    return np.bitwise_xor.reduce(parity.reshape(-1, words), axis=0)


def _least_apart(x: bytes, y: bytes) -> int:
    """Differing bits of two parity sketches, the wider one folded: the sets differ in at least as many shingles."""
    a, b = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
    words = min(len(a), len(b))
    return int(np.bitwise_count(_folded(a, words) ^ _folded(b, words)).sum())


def _possible(na, nb, sa, sb, limit: Fraction) -> np.ndarray:
    """Whether sets of these sizes and sketches (last axis: 64-bit words) may reach the similarity; never false if they do."""
    num, den = limit.numerator, limit.denominator
    fits = np.minimum(na, nb) * den >= np.maximum(na, nb) * num
    return fits & (np.bitwise_count(sa ^ sb).sum(-1, dtype=np.int64) * (den + num) <= (na + nb) * (den - num))


def _sketches(s: pd.Series) -> np.ndarray:
    return np.frombuffer(b"".join(s), np.uint64).reshape(len(s), SKETCH // 64)


def _common_shingles(docs: DataFrame, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles frequent in a sample, sorted, and their rank by frequency. They only set the order, never the result."""
    shingles = by_row(lambda: lambda t: (_distinct_shingles(t, shingle).view(np.int64),), "h array<long>", binary=True)
    parts = max(1, docs.count() // SAMPLE)
    some = docs.where(F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(parts)) == 0)
    seen = some.select(F.explode(shingles(F.col("text").cast("binary"))["h"]).alias("h")).groupBy("h").count()
    top = seen.where("count > 2").orderBy(F.desc("count"), "h").limit(COMMON).collect()
    h = np.array([r["h"] for r in top], np.int64).view(np.uint64)
    order = np.argsort(h)
    return h[order], np.arange(len(h), 0, -1)[order]


def _confirmed(pairs: DataFrame, docs: DataFrame, reps: DataFrame, shingle: int, limit: Fraction) -> DataFrame:
    """The ``pairs(a, b)`` whose shingle sets have the similarity, as edges, written once.

    Pairs go to the texts of ``b``, so the set of ``b`` travels once a pair and that of ``a`` once.
    """
    num, den = limit.numerator, limit.denominator

    def set_of(text: bytes) -> tuple[bytes, np.ndarray]:
        h = _distinct_shingles(text, shingle)
        return _digest(h), h.view(np.int64)

    # Marked so that the check of the digest is not moved below the join, where it would need the set of every text.
    sets = by_row(lambda: set_of, "digest binary, shingles array<long>", binary=True).asNondeterministic()
    # Decided in the JVM: pairs of large sets would fill large batches for Python.
    both = F.size(F.array_intersect("sa", "sb"))
    similar = both * den >= (F.size("sa") + F.size("sb") - both) * num

    digest = lambda c: reps.select(F.col("rep").alias(c), F.col("digest").alias(f"d{c}"))
    # An entry with many partners is met by them in parts of about ``PARTNERS``.
    parts = pairs.groupBy("a").agg(F.ceil(F.count("*") / PARTNERS).cast("int").alias("parts"))
    pairs = written(pairs.join(parts, "a").join(digest("a"), "a").join(digest("b"), "b"))
    few = F.broadcast if pairs.count() <= FEW else lambda x: x

    def held(rows: DataFrame, c: str) -> DataFrame:
        """``rows`` with the set of ``c``; an id may be repeated with another text, whose digest differs."""
        own = docs.join(few(rows), F.col("doc_id") == F.col(c)).select(*rows.columns, sets(F.col("text").cast("binary")).alias("s"))
        return own.where(F.col("s.digest") == F.col(f"d{c}")).withColumn(f"s{c}", F.col("s.shingles")).drop("s")

    right = held(pairs, "b").select("a", "b", "sb", F.pmod(F.xxhash64("b", F.lit(13)), F.col("parts")).cast("int").alias("part"))
    left = held(pairs.select("a", "da", "parts").distinct(), "a").groupBy("a", "parts").agg(F.first("sa").alias("sa"))
    left = left.select("a", "sa", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"))
    edges = written(right.join(left, ["a", "part"]).where(similar).select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct())
    drop_written(pairs)
    return edges


def _open_pairs(lists: DataFrame, limit: Fraction) -> DataFrame:
    """Pairs ``(a, b)`` of ``lists(key, rep, component, n, sketch)`` in one list, of two components, that may be similar; written once.

    A list longer than ``BLOCK`` is compared in blocks, one task a pair of blocks.
    """
    block = BLOCK
    sizes = written(lists.groupBy("key").agg(F.count("*").alias("count"), F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi"))
    rows, listed = sizes.agg(F.sum("count")).first()[0] or 0, lists.join(sizes.select("key", "count"), "key")
    tasks = max(1, -(-rows // TASK_ROWS))
    blocks = F.ceil(F.col("count") / block).cast("int")
    own = F.when(blocks > 1, F.pmod(F.xxhash64("rep", F.lit(7)), blocks)).otherwise(0).cast("int")
    listed = listed.withColumn("own", own)
    units = F.transform(
        F.sequence(F.lit(0), blocks - 1), lambda o: F.struct(F.col("key").alias("unit"), F.least("own", o).alias("i"), F.greatest("own", o).alias("j"))
    )
    light = F.array(F.struct(F.pmod(F.xxhash64("key"), F.lit(tasks)).cast("long").alias("unit"), F.lit(-1).alias("i"), F.lit(-1).alias("j")))
    dealt = listed.select("key", "rep", "component", "n", "sketch", "own", F.explode(F.when(blocks > 1, units).otherwise(light)).alias("u")).select(
        "key", "rep", "component", "n", "sketch", "own", "u.*"
    )

    def compare(at: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("key", kind="stable")
        key, own = rows["key"].to_numpy(), rows["own"].to_numpy()
        ids, component, n, sketch = rows["rep"].to_numpy(), rows["component"].to_numpy(), rows["n"].to_numpy(np.int64), _sketches(rows["sketch"])
        a, b = [ids[:0]], [ids[:0]]
        i = np.arange(len(ids))
        for shift in range(1, len(ids)):
            i = i[i + shift < len(ids)]
            i = i[key[i] == key[i + shift]]
            if not len(i):
                break
            x = i[component[i] != component[i + shift]]
            if at[1] != at[2]:  # rows of one block meet in its own task
                x = x[own[x] != own[x + shift]]
            x = x[_possible(n[x], n[x + shift], sketch[x], sketch[x + shift], limit)]
            a.append(np.minimum(ids[x], ids[x + shift]))
            b.append(np.maximum(ids[x], ids[x + shift]))
        return pd.DataFrame({"a": np.concatenate(a), "b": np.concatenate(b)}).drop_duplicates()

    pairs = written(dealt.groupBy("unit", "i", "j").applyInPandas(compare, "a long, b long").where("a < b").distinct())
    drop_written(sizes)
    return pairs


def similar_documents(docs: DataFrame, similarity: float = 0.8, shingle: int = 5) -> DataFrame:
    """``doc_id, component_id`` for each row of ``docs(doc_id, text)``: linked are texts of at least that similarity, exactly."""
    limit = Fraction(similarity).limit_denominator(10**6)
    order = docs.sparkSession.sparkContext.broadcast(_common_shingles(docs, shingle))
    profile = by_row(
        lambda: lambda t: _profile(_distinct_shingles(t, shingle), *order.value, limit), "digest binary, n int, sketch binary, parity binary, prefix array<long>", binary=True
    )
    fps = docs.select("doc_id", profile(F.col("text").cast("binary")).alias("p"))
    fps = written(fps.select("doc_id", "p.*"))
    firsts = (F.first(c).alias(c) for c in ("n", "sketch", "parity", "prefix"))
    reps = written(fps.where("doc_id is not null").groupBy("digest").agg(F.min("doc_id").alias("rep"), *firsts))
    same = Window.partitionBy("key")
    lists = reps.select("rep", F.explode("prefix").alias("key"))
    lists = written(lists.withColumn("least", F.min("rep").over(same)).withColumn("most", F.max("rep").over(same)).where("least < most").drop("most"))

    @F.pandas_udf("boolean")
    def possible(na: pd.Series, nb: pd.Series, sa: pd.Series, sb: pd.Series) -> pd.Series:
        return pd.Series(_possible(na.to_numpy(np.int64), nb.to_numpy(np.int64), _sketches(sa), _sketches(sb), limit))

    @F.pandas_udf("int")
    def apart(na: pd.Series, nb: pd.Series, pa: pd.Series, pb: pd.Series) -> pd.Series:
        least = np.array([_least_apart(x, y) for x, y in zip(pa, pb, strict=True)], np.int64)
        far = least * (limit.denominator + limit.numerator) > (na + nb).to_numpy(np.int64) * (limit.denominator - limit.numerator)
        return pd.Series(least, dtype="Int32").mask(far)

    def sides(pairs: DataFrame, *kept: str) -> DataFrame:
        for c in "ab":
            pairs = pairs.join(reps.select(F.col("rep").alias(c), *(F.col(k).alias(f"{k}_{c}") for k in kept)), c)
        return pairs

    def likely(pairs: DataFrame) -> DataFrame:
        """``pairs`` with ``apart``, the least number of shingles they differ in, where that allows the similarity."""
        return sides(pairs, "n", "parity").select("a", "b", apart("n_a", "n_b", "parity_a", "parity_b").alias("apart")).where("apart is not null")

    # Each entry against the nearest by parities of its lists' least ones first: that joins most copies with one
    # exact check an entry, so that few pairs of two components remain.
    stars = lists.where("least < rep").select(F.col("least").alias("a"), F.col("rep").alias("b")).distinct()
    stars = sides(stars, "n", "sketch").where(possible("n_a", "n_b", "sketch_a", "sketch_b")).select("a", "b")
    stars = written(likely(stars).groupBy("b").agg(F.min(F.struct("apart", "a"))["a"].alias("a")).select("a", "b"))
    edges = _confirmed(stars, docs, reps, shingle, limit)
    found = components(edges).withColumnRenamed("item", "rep")
    open_lists = lists.select("key", "rep").join(found, "rep", "left").withColumn("component", F.coalesce("component", "rep"))
    open_pairs = _open_pairs(open_lists.join(reps.select("rep", "n", "sketch"), "rep"), limit)
    rest = written(likely(open_pairs).select("a", "b"))
    edges = edges.union(_confirmed(rest, docs, reps, shingle, limit))
    for done in (lists, stars, open_pairs, rest):
        drop_written(done)
    return _with_components(fps.select("doc_id", "digest"), reps, edges, ["digest"]).select("doc_id", "component_id")


def deduplicate(docs: DataFrame, similarity: float = 0.8, shingle: int = 5) -> DataFrame:
    """``docs`` with the smallest-id document of each group of similar texts; columns unchanged.

    Rows that repeat a kept id stay, and so do rows without an id: nothing names them, so nothing stands for them.
    """
    return _kept(docs, similar_documents(docs.select("doc_id", "text"), similarity, shingle))


def linked_documents(docs: DataFrame, max_bits: int = 3, similarity: float = 0.8, shingle: int = 5) -> DataFrame:
    """``doc_id, component_id`` over both kinds of links: fingerprints of at most ``max_bits`` differing bits, found by the
    index of their bytes, and texts of at least the exact ``similarity``, which fingerprints may tell apart.
    """
    by_bits = written(near_duplicates(docs, max_bits).select("doc_id", "component_id"))
    by_sets = written(similar_documents(docs, similarity, shingle))
    edges = by_bits.union(by_sets).where("doc_id <> component_id").select(F.col("component_id").alias("src"), F.col("doc_id").alias("dst"))
    found = components(edges).withColumnRenamed("component", "least")
    return by_sets.join(found, F.col("doc_id") == F.col("item"), "left").select("doc_id", F.coalesce("least", "component_id").alias("component_id"))


def drop_linked(docs: DataFrame, max_bits: int = 3, similarity: float = 0.8, shingle: int = 5) -> DataFrame:
    """``deduplicate`` over the components of ``linked_documents``."""
    return _kept(docs, linked_documents(docs.select("doc_id", "text"), max_bits, similarity, shingle))


def _kept(docs: DataFrame, found: DataFrame) -> DataFrame:
    keep = found.where("doc_id is null or doc_id = component_id").select(F.col("doc_id").alias("__kept")).distinct()
    return docs.join(keep, F.col("doc_id").eqNullSafe(F.col("__kept")), "left_semi")


def hex_fingerprint(fp: str = "fp"):
    """The fingerprint as 16 lower-case hex digits."""
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
