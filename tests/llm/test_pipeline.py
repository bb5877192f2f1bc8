"""The corpus pipeline's stages."""

import corpus_pipeline
import numpy as np
import pytest
from pyspark.sql import functions as F

from tests.llm.conftest import ODD


def test_stages_in_order():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "simhash", "pii", "mixing", "sentencepiece"]


def test_run(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    n = [docs.count()]
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf)
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == docs.columns
        out.write.parquet(str(tmp_path / str(k)))
        docs = spark.read.parquet(str(tmp_path / str(k)))
        n.append(docs.count())
    assert n[0] > n[1] > n[2] == n[3] and docs.where("not round_trip").count() == 0
    whole = corpus_pipeline.run(spark, sf)
    assert whole.count() == n[-1]
    assert whole.agg(F.sum("n_pieces")).first() == docs.agg(F.sum("n_pieces")).first()


@pytest.mark.parametrize("name, stage", corpus_pipeline.STAGES)
def test_odd_rows(spark, sf, docs_of, name, stage):
    docs = docs_of(ODD).select("doc_id", "text", "lang", "source", "n_chars")
    assert stage(spark, docs, sf).count() >= 0
    assert stage(spark, docs.limit(0), sf).count() == 0


def test_near_duplicates_go(spark, sf, docs_of):
    draw = np.random.default_rng(0)
    words = [f"w{i}" for i in range(300)]
    text = list(draw.choice(words, 200))
    near = [*text[:100], "other", *text[101:]]
    pairs = [(1, " ".join(text)), (2, " ".join(near)), (3, " ".join(text)), (4, " ".join(draw.choice(words, 200)))]
    stage = dict(corpus_pipeline.STAGES)["simhash"]
    assert sorted(r["doc_id"] for r in stage(spark, docs_of(pairs), sf).collect()) == [1, 4]


def test_fingerprints_link_in_the_stage(spark, sf, docs_of):
    """Texts alike in what they repeat: equal fingerprints, though most distinct shingles differ."""
    from neardup.llm import simhash

    text = {i: " ".join(["one two three four five six seven"] * 60 + [f"{i}w{j}" for j in range(12)]) for i in (1, 2)}
    near = " ".join([f"x{j}" for j in range(80)])
    chain = [(3, near), (4, near + " y"), (5, near)]
    assert (simhash.simhash(text[1].encode()) ^ simhash.simhash(text[2].encode())).bit_count() <= 3
    docs = docs_of([*text.items(), *chain, (None, near)])
    stage = dict(corpus_pipeline.STAGES)["simhash"]
    assert sorted(r["doc_id"] or 0 for r in stage(spark, docs, sf).collect()) == [0, 1, 3]
    assert sorted(r["doc_id"] or 0 for r in simhash.deduplicate(docs).collect()) == [0, 1, 2, 3]
