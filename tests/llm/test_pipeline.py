"""The pipeline's stages against brute-force versions of each on its own input."""

import importlib.util
import re

import pytest
from pyspark.sql import functions as F

if importlib.util.find_spec("corpus_pipeline") is None:
    pytest.skip("no pipeline here", allow_module_level=True)

import corpus_pipeline
from layermul.llm import ngram_join
from layermul.llm.scratch import materialize

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, before = docs.columns, docs
    for name, stage in corpus_pipeline.STAGES:
        after = materialize(stage(spark, before, SF), "test-stage")
        if name != "sharding":
            assert after.columns == columns
        if name == "quality":
            labels = spark.read.parquet(f"{SF}/labels.parquet")
            good = before.join(labels.where("quality = 1"), "doc_id", "left_semi")
            assert after.join(good, "doc_id", "left_semi").count() >= 0.95 * good.count()
        if name == "near_duplicates":
            groups = ngram_join.ngram_components(before).groupBy("component_id").agg(F.min("doc_id").alias("doc_id"))
            assert sorted(r[0] for r in groups.select("doc_id").collect()) == sorted(r["doc_id"] for r in after.collect())
        if name == "decontamination":
            items = [r["text"] for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
            words = lambda t: re.findall(r"[a-z0-9\x80-\U0010ffff]+", t.lower())
            grams = lambda w: {tuple(w[i : i + 5]) for i in range(len(w) - 4)}
            sets = [grams(words(t)) for t in items]
            clean = [r["doc_id"] for r in before.collect() if not any(100 * len(s & grams(words(r["text"]))) >= 80 * len(s) for s in sets)]
            assert sorted(clean) == sorted(r["doc_id"] for r in after.collect())
        if name == "mixing":
            assert after.select("doc_id").distinct().join(before, "doc_id", "left_anti").isEmpty() and after.groupBy("doc_id").count().where("count > 3").isEmpty()
        if name == "sharding":
            assert sorted(r["doc_id"] for r in after.collect()) == sorted(r["doc_id"] for r in before.collect())
        before = after
    assert after.count() > 0


def test_repeated_rows_and_nulls(spark):
    schema = spark.read.parquet(f"{SF}/documents.parquet").schema
    text = " ".join(f"word{k}" for k in range(30))
    rows = [(1, text, "en", "a", 1), (1, text, "en", "a", 1), (2, text, None, None, None), (3, None, "en", "a", 0), (None, text, "en", "b", 1)]
    docs = spark.createDataFrame(rows, schema)
    kept = corpus_pipeline.drop_near_duplicates(spark, docs, SF)
    assert sorted(str(r["doc_id"]) for r in kept.collect()) == ["1", "3", "None"]
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.limit(0), SF).count() == 0
        stage(spark, docs, SF).count()
