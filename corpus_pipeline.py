"""A corpus pipeline: quality filter, exact dedup, near dedup, packing. Each stage's rows are written and read again for the next.

The same executors run all stages, so what one leaves in their native memory is there in the next: each stage bounds the session's Arrow batches.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from svengine.llm import common, dedup, neardup, packing, quality


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier, trained on all labels, doesn't reject."""
    common.bounded_batches(spark)
    model = quality.train(docs, common.table(spark, sf_dir, "labels"))
    return quality.score(docs, model, ("__score", "__predicted")).where("__predicted = 1").select(*docs.columns)


def _without(docs: DataFrame, dropped: DataFrame) -> DataFrame:
    return docs.join(dedup._small(common.written(dropped, "pipeline-dropped")), docs["doc_id"] == F.col("__id"), "left_anti").select(*docs.columns)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, the document with the largest doc_id."""
    common.bounded_batches(spark)
    return _without(docs, dedup.exact_dedup(docs).where("not kept").select(F.col("doc_id").alias("__id")))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each near-duplicate class, the document with the least doc_id."""
    common.bounded_batches(spark)
    return _without(docs, neardup.classes(docs).where("doc_id <> class_id").select(F.col("doc_id").alias("__id")))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    common.bounded_batches(spark)
    return packing.pack(docs)


STAGES = [("quality", keep_good), ("exact dedup", drop_copies), ("near dedup", drop_near_copies), ("packing", pack)]

#: Models and sketches can't be written in SQL; tests/llm holds the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = common.written(stage(spark, docs, sf_dir), f"pipeline-{name.replace(' ', '-')}")
    return STAGES[-1][1](spark, docs, sf_dir)
