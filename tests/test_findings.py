"""Cases of the second review."""

import numpy as np
from pyspark.sql import functions as F

from neardup.config import DEFAULT
from neardup.operators import search
from neardup.operators import terms as terms_


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_near_pairs_keep_the_layout_of_the_sql(spark):
    """Beyond 4,096 items as below: pairs that share a term of the default layout, no others."""
    draw = np.random.default_rng(7)
    base = draw.integers(0, 2, (2500, 256))
    near = base.copy()
    for r in near:
        r[draw.choice(256, 58, replace=False)] ^= 1
    packed = [np.packbits(x, bitorder="little").view("<u4").astype(int).tolist() for x in np.vstack([base, near])]
    words = spark.createDataFrame([(i, w) for i, w in enumerate(packed)], "item_id long, words array<long>").cache()
    cands = search.self_search(terms_.group_bits(words, 256, DEFAULT.width, "permuted", DEFAULT.repeats, DEFAULT.seed)).cache()
    assert rows(search.pairs_in_lists(words).drop("distance")) == rows(cands)
    want = search.with_distance(cands, words).where("distance <= 64").select("a", "b", "overlap", "distance")
    assert rows(search.near_pairs(words)) == rows(want) and want.count() > 1000


def test_medians_are_exact(spark):
    from neardup.operators import signatures

    draw = np.random.default_rng(3)
    x = np.round(draw.normal(size=(30_001, 3)), 6)
    x[:, 2] = draw.integers(0, 2, len(x))  # ties alone
    df = spark.createDataFrame([(i, v) for i, v in enumerate(x.tolist())], "item_id long, vec array<double>")
    assert signatures.medians(df, 3) == np.sort(x, axis=0)[15_000].tolist()
    even = df.where("item_id < 30000")
    assert signatures.medians(even, 3) == np.sort(x[:30_000], axis=0)[14_999].tolist() == signatures.medians(even, 3, 0.0)
    assert signatures.medians(df.limit(0), 3) == [0.0, 0.0, 0.0]


def test_recursive_components(spark):
    from neardup.plans import surrounding as R

    path = [(i, i + 1) for i in range(150)]  # far more hops than a level, and than one round
    zigzag = [(200 + (i * 37) % 90, 200 + ((i + 1) * 37) % 90) for i in range(89)]
    clique = [(i, j) for i in range(400, 440) for j in range(i + 1, 440)]  # paths without number
    edges = spark.createDataFrame(path + zigzag + clique, "src long, dst long")
    want = {**{i: 0 for i in range(151)}, **{200 + i: 200 for i in range(90)}, **{i: 400 for i in range(400, 440)}}
    assert dict(rows(R.recursive_components(edges))) == want
    assert R.recursive_components(edges.limit(0)).count() == 0


def test_all_links(spark, monkeypatch):
    """Counts and components of all pairs, copies included, over several blocks; no row a pair."""
    draw = np.random.default_rng(8)
    base = draw.normal(size=(60, 16))
    x = np.vstack([base, base[:30] + 0.1 * draw.normal(size=(30, 16)), base[:10], np.zeros((2, 16))])
    unit = x / np.maximum(np.linalg.norm(x, axis=1), 1e-9)[:, None]
    bits = (x > 0).astype(int)
    near = {"cosine": unit @ unit.T >= 0.93, "hamming": (bits[:, None] != bits[None]).sum(2) <= 2}
    df = spark.createDataFrame([(i, v, [int(b @ (1 << np.arange(16))), 0]) for i, (v, b) in enumerate(zip(x.tolist(), bits, strict=True))] + [(200, None, None)], "item_id long, vec array<double>, words array<long>")
    for block in (8192, 16):
        monkeypatch.setattr(search, "BLOCK", block)
        for measure, limit in (("cosine", 0.93), ("hamming", 2)):
            linked = near[measure] & ~np.eye(len(x), dtype=bool)
            root = np.arange(len(x))
            for _ in range(len(x)):
                root = np.array([min([root[i], *root[linked[i]]]) for i in range(len(x))])
            want = [(i, int(linked[i].sum()), int(root[i])) for i in range(len(x))] + [(200, 0, 200)]
            assert rows(search.all_links(df, measure, limit)) == want


def drawn_sets(spark):
    """Word sets with near and exact copies, and empty ones."""
    draw = np.random.default_rng(12)
    sets = [sorted(set(draw.integers(0, 60, 14).tolist())) for _ in range(60)]
    sets += [sorted({*s[2:], 60 + n % 7}) for n, s in enumerate(sets[:30])] + sets[:10] + [[], []]
    names = [[f"w{x}" for x in s] for s in sets]
    return spark.createDataFrame(list(enumerate(names)), "item_id long, terms array<string>").cache(), [set(s) for s in names]


def test_library_minhash_as_a_search(spark, monkeypatch):
    """The rows of the library's own join, for the items that ask."""
    from pyspark.ml.feature import HashingTF, MinHashLSH

    from neardup.operators import legacy

    df, _ = drawn_sets(spark)
    data = HashingTF(inputCol="terms", outputCol="features", numFeatures=1 << 18, binary=True).transform(df.where(F.size("terms") > 0))
    model = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=8, seed=0).fit(data)
    joined = model.approxSimilarityJoin(data.where("item_id % 3 = 0"), data, 0.5, distCol="distance").select("datasetA.item_id", F.col("datasetB.item_id").alias("other"), F.round("distance", 9))
    want = rows(joined.where("item_id <> other"))
    for block in (8192, 16):
        monkeypatch.setattr(search, "BLOCK", block)
        got = legacy.library_minhash(df, "item_id % 3 = 0", 0.5)
        assert rows(got.withColumn("distance", F.round("distance", 9))) == want and len(want) > 20


def test_library_projection_as_a_join(spark, monkeypatch):
    """Counts and components of the rows of the library's own join."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    from neardup.operators import closure, legacy

    draw = np.random.default_rng(13)
    base = draw.normal(size=(50, 8)) * 0.5
    x = np.vstack([base, base[:30] + 0.2 * draw.normal(size=(30, 8)), base[:8], np.zeros((2, 8))])
    df = spark.createDataFrame([*enumerate(x.tolist()), (500, None)], "item_id long, vec array<double>")
    data = df.where("vec is not null").select("item_id", array_to_vector("vec").alias("features"))
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=0.5, numHashTables=8, seed=0).fit(data)
    pairs = model.approxSimilarityJoin(data, data, 0.9, distCol="distance").select(F.col("datasetA.item_id").alias("src"), F.col("datasetB.item_id").alias("dst")).where("src <> dst").cache()
    n, low = dict(rows(pairs.groupBy("src").count())), dict(rows(closure.components(pairs)))
    assert 60 < sum(n.values()) < len(x) * (len(x) - 1) / 2
    want = [(i, n.get(i, 0), low.get(i, i)) for i in [*range(len(x)), 500]]
    for block in (8192, 16):
        monkeypatch.setattr(search, "BLOCK", block)
        assert rows(legacy.library_projection(df, 0.9)) == want


def test_similar_sets(spark, monkeypatch):
    """All pairs by brute force, by both measures, with copies, null and empty texts, and long lists in slices."""
    from neardup.operators import sets

    draw = np.random.default_rng(14)
    texts = [" ".join(f"w{x}" for x in draw.integers(0, 6, n)) for n in draw.integers(1, 30, 80)]
    texts += [t + " w1 w2 w3" for t in texts[:40]] + [" ".join(t.split()[: len(t.split()) * 2 // 3]) for t in texts[:40]] + texts[:12] + ["", None, "", "w1", "w1 w2"]
    df = spark.createDataFrame(list(enumerate(texts)), "item_id long, text string")
    of = [{" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))} for w in ((t or "").split() for t in texts)]
    for at_once, part, common in ((200_000, 512, 200_000), (16, 2, 5)):
        for name, value in (("AT_ONCE", at_once), ("PART", part), ("COMMON", common)):
            monkeypatch.setattr(sets, name, value)
        for measure, limit in (("jaccard", 0.5), ("larger", 0.6), ("jaccard", 0.8)):
            want = []
            for a, x in enumerate(of):
                for b in range(a + 1, len(of)):
                    n, total = len(x & of[b]), len(x | of[b]) if measure == "jaccard" else max(len(x), len(of[b]))
                    if n >= limit * total - 1e-9:
                        want.append((a, b, n))
            got = sets.expanded(*sets.similar_sets(df, limit, measure, sets.run_sets))
            assert rows(got.select("a", "b", "overlap")) == want and len(want) > 40


def test_set_search_gives_word_similarity(spark, monkeypatch):
    """Overlap and sizes of every pair that shares a key, against brute force."""
    df, of = drawn_sets(spark)
    keyed = df.select("item_id", F.array(F.col("item_id") % 7, F.col("item_id") % 5 + 10).cast("array<long>").alias("keys"), F.transform("terms", lambda w: F.xxhash64(w)).alias("terms"))
    want = [(a, b, len(of[a] & of[b]), len(of[a]), len(of[b])) for a in range(0, len(of), 4) for b in range(len(of)) if a != b and (a % 7 == b % 7 or a % 5 == b % 5)]
    for block in (8192, 16):
        monkeypatch.setattr(search, "BLOCK", block)
        assert rows(search.set_search(keyed, "item_id % 4 = 0")) == want
    assert search.set_search(keyed.limit(0), "item_id % 4 = 0").count() == 0


def test_global_links_count_the_candidates(spark, sf, monkeypatch):
    """As many links as there are pairs, and their components, copies and many tasks included."""
    from neardup.operators import closure, legacy
    from neardup.sources.tables import text_items

    items = text_items(spark, sf).select("item_id", "text")
    items = items.union(items.where("item_id < 9").select(F.col("item_id") + 1000, "text")).cache()
    pairs = legacy.global_candidates(items).cache()
    n = dict(rows(pairs.select(F.explode(F.array("a", "b")).alias("i")).groupBy("i").count()))
    low = dict(rows(closure.components(pairs.select(F.col("a").alias("src"), F.col("b").alias("dst")))))
    want = sorted((i, n.get(i, 0), low.get(i, i)) for (i,) in items.select("item_id").collect())
    for task_rows in (131_072, 64):
        monkeypatch.setattr(legacy, "TASK_ROWS", task_rows)
        assert rows(legacy.global_links(items)) == want
    assert 0 < pairs.count() and len({c for _, _, c in want}) > 1


def test_expansion_is_a_search(spark, sf):
    """The queries of every hundredth vector meet every head that shares a term with them; no others are listed."""
    from neardup.operators import augment
    from neardup.plans import QUERIES, core

    _, mapping, cands = core.drift_parts(spark, sf)
    every = augment.expand(cands, mapping, 2).cache()
    got = rows(QUERIES["m13_expand"](spark, sf))
    assert got == [r for r in rows(every) if (r[0] - 2_000_000) // 10 % 100 == 0] and 0 < len(got) < every.count() / 20


def test_accepted_pairs_need_no_list_of_candidates(spark, sf):
    """Pairs judged where postings meet: the same accepted heads and hard positives as from all candidates, of which few are kept."""
    from neardup.operators import augment, training
    from neardup.plans import core

    _, _, scored = core.drift_scored(spark, sf)
    scored, near = scored.cache(), core.drift_near(spark, sf).cache()
    taken, want = augment.accept(near, core.LIMIT), augment.accept(scored, core.LIMIT)
    assert rows(taken) == rows(want) and want.count() > 300
    hard = rows(training.adversarial_pairs(scored, want, core.LIMIT))
    assert rows(training.adversarial_pairs(near, taken, core.LIMIT)) == hard and len(hard) > 300
    assert near.count() < scored.count() / 10


def test_gold_pairs_are_drawn_without_a_list_of_candidates(spark, sf, monkeypatch):
    """the first candidates and others by their hash, as many as asked, and none of them by the driver."""
    from neardup.sources import fixtures as X

    draw = np.random.default_rng(21)
    df = spark.createDataFrame([(int(a), int(b), int(h) << 12) for a, b, h in draw.integers(0, 90, (700, 3))], "a long, b long, h long").cache()
    every = sorted(((r.h, r.a, r.b) for r in df.collect()))
    for n in (0, 333, 900):
        assert sorted((r.h, r.a, r.b) for r in X.first_by(df, n, "h").collect()) == every[:n]

    words = X.document_words(spark, sf).cache()
    cands = search.pairs_in_lists(words).select("a", "b").cache()
    true = cands.where("(a + b) % 9 = 0").cache()
    want = sorted((r.h, r.a, r.b) for r in cands.where("(a + b) % 9 <> 0").withColumn("h", X.h32("n", F.col("a"), F.col("b"))).collect())
    assert len(want) > 100
    for n in (60, len(want) + 5):
        assert sorted((r.h, r.a, r.b) for r in X.drawn_candidates(words, true, n).collect()) == want[:n]
    some = words.select(F.col("item_id").alias("a")).join(words.where("item_id < 9").select(F.col("item_id").alias("b")), F.col("a") < F.col("b"))
    assert rows(X.without_shared_term(some, words)) == rows(some.join(cands, ["a", "b"], "left_anti"))
    monkeypatch.setattr(X, "shingle_pairs", lambda items: true)
    assert "TakeOrdered" not in X.gold(spark, sf)._jdf.queryExecution().toString()


def test_pairs_of_sets_come_from_few_tasks(spark, monkeypatch):
    """near copies share hundreds of terms, and one task or the parts of one counts them; before, as many as there are."""
    from fractions import Fraction

    from neardup.operators import sets

    monkeypatch.setattr(sets, "TASK_ROWS", 64)
    lists = spark.createDataFrame([(1000 * p + t, [2 * p, 2 * p + 1], 2 * p) for p in range(30) for t in range(150)] + [(-1, list(range(60)), 0)], "term long, reps array<long>, low long")
    reps = spark.createDataFrame([(i, 300, bytes(64)) for i in range(60)], "rep long, n long, sketch binary")
    met = sets._meetings(lists, reps, Fraction(1, 2), "jaccard").cache()
    times = dict(((a, b), c) for a, b, c in rows(met.groupBy("a", "b").agg(F.sum("c"))))
    assert times == {(a, b): 151 if a % 2 == 0 and b == a + 1 else 1 for a in range(60) for b in range(a + 1, 60)}
    assert met.groupBy("a", "b").count().agg(F.max("count")).first()[0] <= 7


def test_sharing_is_what_brute_force_says():
    """Few rows and many, with large classes of equal ones, and in small batches."""
    draw = np.random.default_rng(21)
    for n, values in ((0, 30), (1, 30), (40, 30), (400, 30), (400, 200)):
        value = draw.integers(0, values, (n, 5)).astype(np.uint16)
        value[: n // 5] = value[:1]
        for least in (1, 2):
            x, y = np.triu_indices(n, 1)
            near = (value[x] == value[y]).sum(1) >= least
            want = sorted(zip(x[near].tolist(), y[near].tolist(), strict=True))
            for at_once in (500_000, 100):
                got = [p for a, b in search.sharing(value, least, at_once) for p in zip(a.tolist(), b.tolist(), strict=True)]
                assert sorted(got) == want


def passages(spark):
    """Texts with passages that few and many of them hold at different places, copies, and texts without a run."""
    draw = np.random.default_rng(22)
    text = lambda n: [f"w{v}" for v in draw.integers(0, 3000, n)]
    common, some, base = text(12), text(9), text(40)
    corpus = [text(int(draw.integers(0, 12))) + common + text(int(draw.integers(5, 40))) for _ in range(330)]
    corpus += [text(30) + some + text(n) + some for n in range(24)] + [base[:n] + text(2) + base[n:] for n in range(0, 40, 4)]
    corpus += [base] * 20 + [[], [], ["w1"], ["w1", "w2"], ["w1", "w2"]]
    rows_ = [(7 * i, " ".join(t)) for i, t in enumerate(corpus)] + [(5001, None)]
    return spark.createDataFrame(rows_, "item_id long, text string").repartition(3).cache()


def test_votes_of_candidates_that_are_not_listed(spark, monkeypatch):
    """As the join of the listed candidates has them, over several tasks of runs."""
    from neardup.operators import legacy, signatures
    from neardup.plans.baselines import candidates

    items = passages(spark)
    words = signatures.text_bits(items).cache()
    pairs = candidates(words)
    assert search.rule_of(pairs) is not None
    want = rows(legacy.offset_votes(spark.createDataFrame(pairs.collect(), pairs.schema), legacy.keypoints(items)))
    points = legacy.keypoints(items, "lists")
    plan = legacy.offset_votes(pairs, points)._jdf.queryExecution().optimizedPlan().toString()
    assert len(want) > 500 and "overlap" not in plan  # the candidates' own table is not in it
    for postings, small in ((1_000_000, 500_000), (3000, 0)):
        monkeypatch.setattr(legacy, "POSTINGS", postings)
        monkeypatch.setattr(legacy, "SMALL", small)
        assert rows(legacy.offset_votes(pairs, points)) == want
    twice = items.union(items.where("item_id = 7").withColumn("text", F.lit("other words than before")))
    pairs = candidates(words)
    assert rows(legacy.offset_votes(pairs, legacy.keypoints(twice, "lists"))) == rows(legacy.offset_votes(spark.createDataFrame(pairs.collect(), pairs.schema), legacy.keypoints(twice)))


def test_sets_that_differ_are_not_sent_to_each_other(spark, monkeypatch):
    """large sets that only share their rarest terms are told apart by parities; before, each came whole to every such pair."""
    from neardup.operators import sets

    draw = np.random.default_rng(23)
    own = [draw.integers(1, 1 << 60, 3000).tolist() for _ in range(12)]
    some = draw.integers(1, 1 << 60, 1200).tolist()
    terms = [x[:1800] + some for x in own] + [own[0][:1700] + some + [5]]
    df = spark.createDataFrame(list(enumerate(terms)), "item_id long, terms array<long>").repartition(3).cache()
    monkeypatch.setattr(sets, "COMMON", 1)  # so that shared terms come first too
    asked, units = [], sets._units
    monkeypatch.setattr(sets, "_units", lambda pairs: asked.append(pairs.count()) or units(pairs))
    pairs, _ = sets.similar_sets(df, 0.6, "larger")
    assert rows(pairs.select("a", "b", "overlap")) == [(0, 12, 2900)]
    assert asked[0] > 1 == asked[1]  # sets are read for the last ones alone


def test_lists_of_terms_are_packed(spark, monkeypatch):
    """as grouping rows gives them, over several tasks, with ids that are far apart and rows that come twice."""
    from neardup.operators import sets

    draw = np.random.default_rng(24)
    ids = [int(i) for i in draw.integers(-(1 << 50), 1 << 50, 60)] + [*range(60)]
    posted = [(i, sorted({int(t) for t in draw.integers(-40, 400, 30)})) for i in ids]
    df = spark.createDataFrame([*posted, posted[0], (7 << 40, [])], "item_id long, prefix array<long>").repartition(3).cache()
    want = {}
    for i, ts in posted:
        for t in ts:
            want.setdefault(t, []).append(i)
    want = sorted((t, sorted(x), min(x)) for t, x in want.items() if len(x) > 1)
    for size in (1_000_000, 500):
        monkeypatch.setattr(sets, "POSTINGS", size)
        assert sorted((r.term, list(r.reps), r.low) for r in sets._lists(df, 3600).collect()) == want
