"""The experiment workloads on the given tables, and the applications."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from neardup.functions import text as T
from neardup.operators import apps, augment, closure, heads, incremental, legacy, metrics, postings, scorers, search, signatures, training
from neardup.operators import terms as terms_
from neardup.plans import baselines as B
from neardup.plans import core as C
from neardup.plans import measures as M
from neardup.plans import sql as S
from neardup.plans.registry import QUERIES, SQL, query
from neardup.sources import fixtures as X
from neardup.sources.lineage import written
from neardup.sources.sinks import Snapshots, scratch
from neardup.sources.tables import table, text_items
from neardup.streaming import stream


def same_as(name: str, other: str):
    """A workload that is another query under its own name."""
    query(name, SQL.get(other))(QUERIES[other])


@query(
    "w01_new_vs_heads",
    S.with_(S.DOCS, S.DAYS, "hs as (select distinct m.head_id from map m join days d on d.item_id = m.head_id where d.day < (select max(day) from days))")
    + "select q.item_id as query_id, h.head_id as index_id, count(*) as overlap from days q join terms x on x.item_id = q.item_id join terms y on y.term = x.term join hs h on h.head_id = y.item_id where q.day = (select max(day) from days) group by all",
)
def _(spark, sf):
    words = C.doc_words(spark, sf)
    days = X.arrivals(spark, sf)
    last = days.agg(F.max("day")).first()[0]
    t = terms_.search_terms(words)
    old = search.head_index(t, C.doc_mapping(spark, sf)).join(days.where(F.col("day") < last), "item_id", "left_semi")
    return search.batch_search(t.join(days.where(F.col("day") == last), "item_id", "left_semi"), old, None)


same_as("w02_search_vec", "v04_self_search")


@query("w02_search_text", S.with_(S.SEARCH) + "select a, b, overlap from cand")
def search_text(spark, sf):
    return search.pairs_in_lists(C.doc_words(spark, sf)).drop("distance")


@query("w03_index_bytes", f"with {B.BAGS}, terms as (select item_id, term from bags), {C.GAPS} select postings, postings * 8 as raw_bytes, coded_bytes from bytes")
def index_bytes(spark, sf):
    lists = postings.build(B.bags(spark, sf))
    return postings.storage_report(postings.encode(lists, "varbyte")).select("postings", "raw_bytes", "coded_bytes")


same_as("w04_augment", "s07_recall_lift")


@query("w05_gold", S.with_(S.GOLD) + "select a, b, cast(truth as bigint) as truth, array_to_string(votes, ',') as votes, cast(label as bigint) as label, split from gold")
def _(spark, sf):
    g = X.gold(spark, sf)
    return g.select("a", "b", F.col("truth").cast("long").alias("truth"), C.joined("votes").alias("votes"), F.col("label").cast("long").alias("label"), "split")


def codebook(words, size: int = 64):
    """Word sets as visual words: each word by one of ``size`` entries of a small vocabulary, as quantised descriptors are."""
    return words.select("item_id", F.array_distinct(F.transform("terms", lambda w: F.pmod(F.xxhash64(w), F.lit(size)))).alias("terms"))


def gold_with_variants(spark, sf):
    """The gold pairs and modified copies: each with its origin (positive) and with other documents (negative).

    Pairs are ``(a, b, label, split)``; origins are split by hash. Also the texts of all items, and the side of each copy.
    """
    items = text_items(spark, sf).select("item_id", "text")
    v = written(X.text_variants(spark, sf))
    side = F.when(X.h32("s", F.col("origin_id")) % 2 == 0, "train").otherwise("test")
    near = v.select(F.col("origin_id").alias("a"), F.col("item_id").alias("b"), F.lit(1).alias("label"), side.alias("split"))
    n = max(1, items.count())
    far = v.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(6)))).select(
        ((F.col("origin_id") + F.col("k") * 11) % n).alias("a"), F.col("item_id").alias("b"), F.lit(0).alias("label"), side.alias("split")
    )
    gold = X.gold(spark, sf).select("a", "b", "label", "split")
    texts = written(items.unionByName(v.select("item_id", "text")))
    return written(gold.unionByName(near).unionByName(far)), texts, written(v.select("item_id", side.alias("split")))


def training_sets(spark, sf, gold, texts, words, sides):
    """The two training sets, neither with a judged label.

    ``base``: a share of the bootstrap labels of the documents' candidates, and random others as negatives. ``hard``: all
    of these, and adversarial positives: among documents and the modified copies of the training side, queries that
    the earlier generation takes through a member near the head though it refuses the head itself.
    """
    held = gold.where("split <> 'train'").select("a", "b")
    docs_ = words.where("item_id < 1000000")
    boot = C.bootstrap(spark, sf, docs_).join(held, ["a", "b"], "left_anti")
    n = max(1, docs_.count())
    other = docs_.select(F.col("item_id").alias("x"), ((F.col("item_id") * 104729 + 71) % n).alias("y")).where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
    boot = written(boot.unionByName(other.distinct().join(held, ["a", "b"], "left_anti").withColumn("label", F.lit(0))).groupBy("a", "b").agg(F.max("label").alias("label")))
    own = written(words.join(sides.where("split <> 'train'"), "item_id", "left_anti"))
    mapping = written(incremental.rebuild(own))
    cands = search.batch_search(terms_.search_terms(own), terms_.search_terms(search.head_index(own, mapping)), None)
    pairs = written(augment.expand(cands, mapping, 2))
    scored = written(legacy.VoteScorer().score(pairs, texts, "query_id", "member_id"))
    hard = training.adversarial_pairs(scored, augment.accept(scored, 0.6), 0.6).join(held, ["a", "b"], "left_anti")
    return {"base_deep": training.make_set("base", boot, share=0.3), "hard_deep": training.make_set("hard", boot, hard)}


def classifier_scores(spark, sf, epochs=24):
    """Scores of the test half by each generation: ``name, a, b, label, score``."""
    gold, texts, sides = gold_with_variants(spark, sf)
    test = gold.where("split = 'test'").select("a", "b", "label")
    words = written(signatures.text_bits(texts))
    points = written(legacy.keypoints(texts))
    plain = X.gold(spark, sf).where("split = 'train'").select("a", "b", "label")
    asked = test.select("a", "b").union(plain.select("a", "b")).distinct()
    features = written(legacy.pair_features(legacy.align(asked, points), legacy.global_descriptor(texts)))
    tree = legacy.TreeScorer().fit(features, plain)
    sets_of_words = written(texts.select("item_id", F.array_distinct(T.words()).alias("terms")))
    rows = {
        "words": scorers.WordJaccard().score(test, sets_of_words),
        "words_of_1024": scorers.WordJaccard().score(test, codebook(sets_of_words, 1024)),
        "words_of_64": scorers.WordJaccard().score(test, codebook(sets_of_words, 64)),
        "tree": tree.score_features(test, features),
        "distance": scorers.HammingScorer().score(test, words),
    }
    for name, pairs in training_sets(spark, sf, gold, texts, words, sides).items():
        weights, _ = training.fit_mlp(written(pairs), words, epochs=epochs, local_steps=4)
        rows[name] = scorers.MlpScorer(weights).score(test, words)
    out = None
    for name, r in rows.items():
        one = r.select(F.lit(name).alias("name"), "a", "b", "label", "score")
        out = one if out is None else out.unionByName(one)
    return written(out)


@query("w06_auc")
def auc(spark, sf):
    """Areas of every classifier: exact words as they are, and by codebooks that stand for quantised descriptors."""
    s = classifier_scores(spark, sf)
    out = None
    for name in ("words", "words_of_1024", "words_of_64", "tree", "distance", "base_deep", "hard_deep"):
        one = s.where(F.col("name") == name)
        row = metrics.pr_auc(one).crossJoin(metrics.roc_auc(one)).select(F.lit(name).alias("name"), "pr_auc", "roc_auc")
        out = row if out is None else out.unionByName(row)
    return out


@query("b07_base_deep")
def _(spark, sf):
    """The network trained on a share of the earlier generation's labels only, over all candidates."""
    words = C.doc_words(spark, sf)
    cands = written(B.candidates(words))
    base = written(training.make_set("base", C.bootstrap(spark, sf, words, cands), share=0.3))
    weights, _ = training.fit_mlp(base, words, hidden=(128, 64, 32), epochs=8, local_steps=2)
    return scorers.MlpScorer(weights).score(cands, words)


same_as("w07_clusters", "s09_cluster_stats")

_PARTS = """ps as (select p_partkey as item_id, list_distinct(string_split(p_name, ' ') || [p_brand, p_type, cast(p_size as varchar)]) as t from part),
pr as (select item_id, unnest(t) as term from ps),
pn as (select item_id, len(t) as n from ps),
pc as (select x.item_id as a, y.item_id as b, count(*) as c from pr x join pr y on x.term = y.term and x.item_id < y.item_id group by all),
pe as (select a, b from pc join pn p on p.item_id = a join pn q on q.item_id = b where c = p.n and c = q.n)"""


@query("w07_parts", S.with_(_PARTS, S.components("pe", "pcomp")) + "select count(*) as items, count(distinct component) as clusters from pcomp")
def _(spark, sf):
    sets = table(spark, sf, "part").select(F.col("p_partkey").alias("item_id"), F.array_distinct(F.concat(F.split("p_name", " "), F.array("p_brand", "p_type", F.col("p_size").cast("string")))).alias("terms"))
    # Equal attribute sets: collapsed by their sorted terms, so a popular set is one aggregate and no pairs.
    keyed = sets.select("item_id", F.array_sort("terms").alias("words"))
    first = keyed.groupBy("words").agg(F.min("item_id").alias("dst"))
    edges = keyed.join(first, "words").select(F.col("item_id").alias("src"), "dst")
    return closure.components(edges).agg(F.count("*").alias("items"), F.count_distinct("component").alias("clusters"))


_CONV = "select conv_id * 100 + turn as item_id, text from conversations"


@query("w07_conversations", S.with_(S.signatures(_CONV), S.search_terms(), S.cands(), S.near_items(), S.components()) + "select count(*) as items, count(distinct component) as clusters from comp")
def _(spark, sf):
    c = table(spark, sf, "conversations").select((F.col("conv_id") * 100 + F.col("turn")).alias("item_id"), "text")
    return C.components_of(written(signatures.text_bits(c))).agg(F.count("*").alias("items"), F.count_distinct("component").alias("clusters"))


_PAGE = "select page_id as item_id, regexp_replace(html, '<[^>]*>', ' ', 'g') as text from pages"


@query("w07_pages", S.with_(S.signatures(_PAGE), S.search_terms(), S.cands(), S.near_items(), S.components()) + "select count(*) as items, count(distinct component) as clusters from comp")
def _(spark, sf):
    p = table(spark, sf, "pages").select(F.col("page_id").alias("item_id"), F.regexp_replace("html", "<[^>]*>", " ").alias("text"))
    return C.components_of(written(signatures.text_bits(p))).agg(F.count("*").alias("items"), F.count_distinct("component").alias("clusters"))


same_as("w08_sizes", "s10_size_distribution")
same_as("w09_trend", "s11_trend")
same_as("w10_one_day", "m23_apply_batch")


@query("w10_thirty_days")
def thirty_days(spark, sf):
    """Thirty daily batches one after another, against one clustering of everything."""
    words = C.doc_words(spark, sf)
    mapping, _ = incremental.run_days(words, X.arrivals(spark, sf).select("item_id", "day"))
    return metrics.pairwise(mapping, C.doc_mapping(spark, sf)).crossJoin(metrics.cluster_stats(mapping))


same_as("w11_generations", "b12_generation_ratios")
same_as("w12_lsh_recall", "s04_candidate_recall")


@query("w13_copies", S.with_(M.COPIES) + "select original_id, item_id from copies")
def copies(spark, sf):
    return M.copies(spark, sf)


@query("w13_passages")
def _(spark, sf):
    originals = table(spark, sf, "benchmark").select("item_id", "text")
    return apps.edited_copies(originals, X.text_items(spark, sf).select("item_id", "text"))


FEED = """first as (select r.*, m.head_id, row_number() over (partition by r.request, m.head_id order by r.rank, r.item_id) as n from {} r join map m using (item_id))
select request, rank, item_id, head_id, row_number() over (partition by request order by rank, item_id) as place from first where n = 1"""
SEARCHED = """wd as (select distinct item_id, unnest(t) as word from tok),
k as (select word from wd group by word order by count(*) desc, word limit 50),
hits as (select wd.word as request, wd.item_id from wd join k using (word)),
iw as (select item_id, cast(sum(cast(round(weight * 100) as bigint)) as bigint) as w from bookmarks group by item_id),
searched as (select request, item_id, row_number() over (partition by request order by coalesce(w, 0) desc, item_id) as rank from hits left join iw using (item_id))"""


def searched(spark, sf):
    """Results of the fifty most frequent words as requests, ranked by engagement."""
    d = written(text_items(spark, sf).select("item_id", F.explode(F.array_distinct(T.words())).alias("request")))
    words = d.groupBy("request").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "request").limit(50)
    hits = d.join(F.broadcast(words.select("request")), "request")
    weight = X.bookmarks(spark, sf).groupBy("item_id").agg(F.sum(F.round(F.col("weight") * 100).cast("long")).alias("weight"))
    rank = F.row_number().over(Window.partitionBy("request").orderBy(F.desc(F.coalesce("weight", F.lit(0))), "item_id"))
    return hits.join(weight, "item_id", "left").select("request", "item_id", rank.cast("long").alias("rank"))


@query("w14_search_feed", S.with_(S.DOCS, S.BOOKMARKS, SEARCHED)[:-1] + ",\n" + FEED.format("searched"))
def _(spark, sf):
    return apps.feed(searched(spark, sf), C.doc_mapping(spark, sf)).withColumn("place", F.col("place").cast("long"))


@query("w14_home_feed", S.with_(S.DOCS, S.BOOKMARKS, B.RANKED)[:-1] + ",\n" + FEED.format("ranked"))
def home_feed(spark, sf):
    return apps.feed(B.ranked(spark, sf), C.doc_mapping(spark, sf)).withColumn("place", F.col("place").cast("long"))


same_as("p01_dedupe_ranked", "w14_home_feed")


@query("w15_metadata", S.with_(S.DOCS, S.BOOKMARKS) + "select m.head_id, count(*) as bookmarks, count(distinct user_id) as users, round(sum(weight), 4) as weight, array_to_string(list_sort(list(distinct board)), ',') as boards from bookmarks b join map m using (item_id) group by m.head_id")
def _(spark, sf):
    return apps.aggregate_metadata(X.bookmarks(spark, sf), C.doc_mapping(spark, sf))


@query(
    "w15_keywords",
    S.with_(S.DOCS)
    + "select head_id, word, items, place from (select *, row_number() over (partition by head_id order by items desc, word) as place from (select m.head_id, w as word, count(distinct t.item_id) as items from (select item_id, unnest(list_distinct(t)) as w from tok) t join map m using (item_id) where length(w) >= 4 group by all)) where place <= 5",
)
def _(spark, sf):
    return apps.cluster_keywords(text_items(spark, sf), C.doc_mapping(spark, sf)).withColumn("place", F.col("place").cast("long"))


same_as("p02_aggregate_metadata", "w15_metadata")
same_as("w16_graph", "s16_graph_shrink")


@query("p03_condense_graph", S.with_(S.DOCS, S.BOOKMARKS, M.GRAPH) + 'select l as "left", item, weight from cond')
def _(spark, sf):
    return apps.condense_graph(M.user_items(spark, sf), C.doc_mapping(spark, sf))


_CP = S.with_(_PARTS, S.components("pe", "pcomp"), "edges as (select o_custkey as l, l_partkey as item, count(*) as weight from orders join lineitem on l_orderkey = o_orderkey group by all)",
              "cond as (select l, coalesce(component, item) as item, sum(weight) as weight from edges left join pcomp on pcomp.item = edges.item group by all)") + M.SHRINK


@query("w16_customer_parts", _CP.replace("coalesce(component, item) as item", "coalesce(pcomp.component, edges.item) as item"))
def _(spark, sf):
    sets = table(spark, sf, "part").select(F.col("p_partkey").alias("item_id"), F.array_sort(F.array_distinct(F.concat(F.split("p_name", " "), F.array("p_brand", "p_type", F.col("p_size").cast("string"))))).alias("words"))
    mapping = sets.withColumn("head_id", F.min("item_id").over(Window.partitionBy("words")))
    o, li = table(spark, sf, "orders"), table(spark, sf, "lineitem")
    edges = li.join(o, li.l_orderkey == o.o_orderkey).groupBy(F.col("o_custkey").alias("left"), F.col("l_partkey").alias("item")).agg(F.count("*").alias("weight"))
    return metrics.graph_shrink(edges, apps.condense_graph(edges, mapping))


@query(
    "w17_canonical",
    S.with_(S.DOCS, S.BOOKMARKS, "iw as (select item_id, cast(sum(cast(round(weight * 100) as bigint)) as bigint) as w from bookmarks group by item_id)")
    + "select context, m.head_id, arg_min(m.item_id, ((case when d.lang <> context then 1 else 0 end), -coalesce(w, 0), m.item_id)) as item_id from map m join documents d on d.doc_id = m.item_id left join iw on iw.item_id = m.item_id, (values ('en'), ('fr'), ('de'), ('es')) v(context) group by context, m.head_id",
)
def canonical(spark, sf):
    weight = X.bookmarks(spark, sf).groupBy("item_id").agg(F.sum(F.round(F.col("weight") * 100).cast("long")).alias("weight"))
    items = text_items(spark, sf).select("item_id", "lang").join(weight, "item_id", "left").withColumn("weight", F.coalesce("weight", F.lit(0)))
    contexts = spark.createDataFrame([("en",), ("fr",), ("de",), ("es",)], "context string")
    return apps.canonical(C.doc_mapping(spark, sf), items, contexts)


same_as("p04_canonical", "w17_canonical")
same_as("p05_copies_of", "w13_copies")
same_as("p07_lift", "s17_lift")
same_as("w18_lift", "s17_lift")


@query("w17_user_locale", S.with_(S.LOCALE) + "select user_id, nation, region, lang from locale")
def _(spark, sf):
    return X.user_locale(spark, sf)


@query(
    "p06_pool_labels",
    S.with_(S.DOCS, "lb as (select l.doc_id as item_id, l.quality, m.head_id from labels l join map m on m.item_id = l.doc_id)")
    + "select item_id, cast(case when avg(quality) over (partition by head_id) >= 0.5 then 1 else 0 end as bigint) as pooled from lb",
)
def _(spark, sf):
    labels = table(spark, sf, "labels").select(F.col("doc_id").alias("item_id"), F.col("quality").alias("label"))
    return apps.pool_labels(labels, C.doc_mapping(spark, sf)).withColumn("pooled", F.col("pooled").cast("long"))


@query(
    "w19_disagree",
    S.with_(C.GOLD_BITS) + "select a, b, cast(label as bigint) as label, cast(distance as bigint) as distance from scored where (distance <= 64) <> (label = 1) or list_sum(votes) not in (0, 5)",
)
def _(spark, sf):
    g = C.gold_scored(spark, sf)
    votes = F.aggregate("votes", F.lit(0), lambda s, v: s + v)
    odd = ((F.col("distance") <= 64) != (F.col("label") == 1)) | ~votes.isin(0, 5)
    return g.where(odd).select("a", "b", F.col("label").cast("long").alias("label"), F.col("distance").cast("long").alias("distance"))


@query("w20_bow", f"with {B.BAGS}, p as (select x.item_id as a, y.item_id as b, count(*) as overlap from bags x join bags y on x.term = y.term and x.item_id < y.item_id group by all) select overlap, count(*) as pairs from p group by overlap")
def bow(spark, sf):
    from neardup.operators import legacy

    return legacy.bow_search(B.bags(spark, sf), 1).groupBy("overlap").agg(F.count("*").alias("pairs"))


same_as("w21_chain", "v10_morph_chain_4")
same_as("w22_kinds", "v13_modification_kinds")
same_as("w23_widths", "v01_width_sweep")


@query("w24_stream_of_batches", S.with_(S.SEARCH) + "select item_id from sig")
def stream_batches(spark, sf):
    """The items of a mapping kept by a stream of one file a day, in order of arrival."""
    return daily_stream(spark, sf).select("item_id")


def daily_stream(spark, sf, days=None):
    """The mapping after a stream of documents, one file a day of ``days(item_id, day)`` (by default the day of arrival).

    It equals the same batches applied one by one.
    """
    days = days if days is not None else X.arrivals(spark, sf).select("item_id", "day")
    items = written(C.doc_words(spark, sf).join(days, "item_id"))
    path = scratch(spark)
    for d in [r["day"] for r in items.select("day").distinct().orderBy("day").collect()]:  # a row a day
        items.where(F.col("day") == d).select("item_id", "words").coalesce(1).write.mode("append").parquet(path)
    store, bits = Snapshots(spark, scratch(spark)), Snapshots(spark, scratch(spark))
    stream.run_available(stream.files(spark, path, "item_id long, words array<long>"), stream.batch_writer(store, bits))
    return store.read()


@query("m12_heads_by_day", S.with_(S.DOCS, S.BOOKMARKS, S.DAYS, C.HEADS) + "select day, count(*) as clusters, count(*) filter (where head_id <> cluster) as by_engagement from heads join days on days.item_id = head_id group by day")
def _(spark, sf):
    """How many clusters are headed by an item of each day, and how many heads are not the one that cut the cluster."""
    days = X.arrivals(spark, sf).select(F.col("item_id").alias("head_id"), F.col("day").cast("long").alias("day"))
    found = C.doc_heads(spark, sf, C.doc_mapping(spark, sf)).join(days, "head_id")
    return found.groupBy("day").agg(F.count("*").alias("clusters"), F.count_if(F.col("head_id") != F.col("cluster")).alias("by_engagement"))
