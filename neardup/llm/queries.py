"""Queries over the operators of this folder: each applies one to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.llm import ann, chat, embed_dedup, mixing, pieces, pii, quality, simhash, toxicity, url_templates
from neardup.sources.tables import table


def op1_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed_dedup.near_duplicates(table(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label"))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    plan = mixing.plan(table(spark, sf_dir, "documents").select("doc_id", "source", "text"))
    return plan.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("times")).alias("taken"), "source", "times")


def op9_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(pii.find(table(spark, sf_dir, "documents").select("doc_id", "text")))


def op10_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.nearest_of_every(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))


def op2_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode(table(spark, sf_dir, "documents").select("doc_id", "text"), pieces.load())


def op3_url_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    return url_templates.judge(pages, url_templates.labels_by_document(pages, table(spark, sf_dir, "labels")))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = toxicity.score(docs, toxicity.learn(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", toxicity.held_out().alias("held_out"), "score", "predicted", "evidence")


def op5_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.format_turns(table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text"))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scorer, _ = quality.fit(docs)
    return quality.score(docs, scorer)


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", simhash.hex_fingerprint().alias("fingerprint"), "component_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (
        op1_embedding_dedup,
        op2_sentencepiece,
        op3_url_templates,
        op4_toxicity,
        op5_chat,
        op6_quality,
        op7_simhash,
        op8_mixing,
        op9_pii,
        op10_ann,
    )
    return {f.__name__: f for f in own}


#: All pairs of equal label; links and what they reach. Only for small tables.
_OP1 = """with recursive v as (select row_number() over () as n, vec_id, label, embedding::double[] as e from embeddings
  where label is not null and vec_id is not null and len(embedding) > 0 and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0),
links as (select x.n as a, y.n as b from v x join v y on x.label = y.label and x.n <> y.n and len(x.e) = len(y.e) and list_cosine_similarity(x.e, y.e) >= 0.93),
reach as (select n as a, n as b from v union select r.a, l.b from reach r join links l on l.a = r.b),
comp as (select r.a as n, min(v.vec_id) as component_id from reach r join v on v.n = r.b group by r.a),
many as (select a as n, count(*) as k from links group by a)
select v.vec_id, coalesce(k, 0) as n_links, component_id, v.vec_id = component_id as kept from v join comp using (n) left join many using (n)
union all select e.vec_id, 0, e.vec_id, true from embeddings e where e.vec_id is null or not exists (select 1 from v where v.vec_id = e.vec_id)"""


def oracle_sql() -> dict[str, str]:
    return {"op1_embedding_dedup": _OP1}
