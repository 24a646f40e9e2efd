"""Corpus pipeline: quality, near duplicates, contamination, mixture, shards.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes each stage's rows as
Parquet in the shared folder and reads them back as the next one's docs. All stages but the last
return docs' own columns.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from layermul.llm.decontaminate import without_items
from layermul.llm.mixing import mixed_documents
from layermul.llm.ngram_join import ngram_components
from layermul.llm.quality import QualityConfig, train, with_score
from layermul.llm.scratch import broadcast_if_small, counted, discard, materialize, table
from layermul.llm.sharding import shard_of_rows, sharded


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts."""
    config = QualityConfig()
    model = train(docs, table(spark, sf_dir, "labels"), config)
    score = "_score" + "_" * sum(c.startswith("_score") for c in docs.columns)
    return with_score(docs, model, score).where(F.col(score) >= config.accept).drop(score)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: the one with the smallest doc_id. Of rows that
    share this doc_id the one that is least as JSON stays, and rows without doc_id all stay."""
    found = ngram_components(docs.select("doc_id", "text"))
    gone, n_gone = counted(found.where("component_id <> doc_id").select("doc_id").distinct(), "groups-gone")
    again, n_again = counted(found.where("component_id = doc_id").groupBy("doc_id").count().where("count > 1").select("doc_id"), "groups-again")
    discard(found)
    kept = docs.join(broadcast_if_small(gone, n_gone), "doc_id", "left_anti").select(*docs.columns)
    if n_again == 0:
        return kept
    twice = broadcast_if_small(again, n_again)
    row = F.struct(*docs.columns)
    one = kept.join(twice, "doc_id", "left_semi").groupBy("doc_id").agg(F.min_by(row, F.to_json(row)).alias("_kept")).select("_kept.*")
    return kept.join(twice, "doc_id", "left_anti").select(*docs.columns).unionByName(one.select(*docs.columns))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that contain no benchmark item."""
    return without_items(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mixture takes them."""
    return mixed_documents(docs)


def write_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each row lies after sharding: docs' columns but text, and shard, shard_bytes, tier, version."""
    return shard_of_rows(sharded(docs), docs.schema, [c for c in docs.columns if c != "text"])


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality", keep_quality),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("mixing", mix_sources),
    ("sharding", write_shards),
]

#: The classifier and the shards' sizes have no SQL form; tests hold run() against brute force.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"stage-{name}")
        if before is not None:
            discard(before)
        before = docs
    return docs
