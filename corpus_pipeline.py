"""From raw documents to packed training sequences.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; its result is written as Parquet and
read again as the next one's ``docs``. Tables that a stage keeps in the shared folder are deleted
when the next stage begins, as the stage's result is written by then.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from beamrank.llm.common import release_scratch, scratch_path, scratch_scope
from beamrank.llm.exact_dedup import exact_dedup
from beamrank.llm.mixing import mix
from beamrank.llm.near_dedup import near_dedup
from beamrank.llm.packing import pack_documents
from beamrank.llm.quality import keep_good


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier predicts good."""
    with scratch_scope("pipeline-quality"):
        return keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, the one with the largest identifier."""
    release_scratch(spark, "pipeline-quality")
    with scratch_scope("pipeline-exact"):
        return exact_dedup(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near-duplicates, the one with the least identifier."""
    release_scratch(spark, "pipeline-exact")
    with scratch_scope("pipeline-near"):
        return near_dedup(docs)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated, or left out, to bring each source to its target."""
    release_scratch(spark, "pipeline-near")
    with scratch_scope("pipeline-mixture"):
        return mix(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document lies in the training sequences."""
    release_scratch(spark, "pipeline-mixture")
    with scratch_scope("pipeline-pack"):
        return pack_documents(docs)


STAGES = [("quality", quality), ("exact", exact), ("near", near), ("mixture", mixture), ("pack", pack)]

#: Trees and signatures are beyond SQL; tests hold the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        path = scratch_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
