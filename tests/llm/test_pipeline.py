"""The pipeline's stages one by one and as a whole."""

from collections import Counter

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from twigmine.llm import mixing, near, quality, queries


@pytest.fixture(scope="module")
def sf01():
    return "/root/testdata/sf0.001"


def test_stages(spark, sf01):
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    seen = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf01)
        assert out.columns == docs.columns and dict(out.dtypes) == dict(docs.dtypes)
        rows = out.collect()
        seen[name] = (docs.collect(), rows)
        docs = spark.createDataFrame(rows, docs.schema)
    before, after = seen["quality"]
    model = queries.quality_model(spark.read.parquet(f"{sf01}/documents.parquet"), spark.read.parquet(f"{sf01}/labels.parquet"))
    import pyarrow as pa

    scores = quality.scores(pa.array([r.text for r in before], pa.string()), model["w"], model["bias"])
    assert sorted(r.doc_id for r in after) == sorted(r.doc_id for r, s in zip(before, scores, strict=True) if s >= quality.THRESHOLD)
    before, after = seen["exact_dedup"]
    best = {}
    for r in before:
        k = (r.text or "").translate({c: c + 32 for c in range(65, 91)})
        best[k] = max(best.get(k, -1), r.doc_id)
    assert sorted(r.doc_id for r in after) == sorted(best.values())
    before, after = seen["near_dedup"]
    classes = {r.doc_id: r.class_id for r in near.near_duplicates(spark.createDataFrame(before)).collect()}
    assert sorted(r.doc_id for r in after) == sorted(set(classes.values()))
    before, after = seen["mixture"]
    copies = {r.doc_id: r.copies for r in mixing.mix_sources(spark.createDataFrame(before), **queries.MIXTURE).collect()}
    assert Counter(r.doc_id for r in after) == Counter({i: c for i, c in copies.items() if c})


def test_whole(spark, sf01):
    out = corpus_pipeline.run(spark, sf01)
    assert out.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
    assert 0 < out.count() and out.filter(F.col("ids_sha256").isNull()).count() == 0


def test_empty_and_odd_rows(spark, sf01):
    kind = spark.read.parquet(f"{sf01}/documents.parquet").schema
    odd = spark.createDataFrame([(None, None, None, None, None), (1, "", "en", "a", 0), (2, None, None, None, None), (3, "x " * 50_000, "en", "a", 1), (3, "x " * 50_000, "en", "a", 1)], kind)
    for docs in (spark.createDataFrame([], kind), odd):
        for _, stage in corpus_pipeline.STAGES:
            stage(spark, docs, sf01).count()
