"""Reading and writing tables in several formats."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession, name: str) -> str:
    """A fresh folder that all executors share; a temporary one only on a single machine."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        local = tempfile.mkdtemp(prefix="beamrank-")
        atexit.register(shutil.rmtree, local, ignore_errors=True)
        root = "file://" + local
    return f"{root.rstrip('/')}/beamrank-{spark.sparkContext.applicationId}/{name}-{uuid.uuid4().hex[:12]}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df`` written in the shared folder and read again: it is not computed twice, and its lineage ends."""
    path = shared_folder(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small(df: DataFrame, name: str, limit: int = 100_000) -> DataFrame:
    """``df``, stored, with the hint of a broadcast only if it has no more than ``limit`` rows."""
    kept = stored(df, name)
    return F.broadcast(kept) if kept.limit(limit + 1).count() <= limit else kept


def csv_round_trip(df: DataFrame) -> DataFrame:
    path = shared_folder(df.sparkSession, "csv")
    df.write.option("header", True).csv(path)
    return df.sparkSession.read.schema(df.schema).option("header", True).csv(path)


def json_round_trip(df: DataFrame) -> DataFrame:
    path = shared_folder(df.sparkSession, "json")
    df.write.json(path)
    return df.sparkSession.read.schema(df.schema).json(path)


def write_beams(df: DataFrame, path: str, *by: str) -> None:
    """Beams in Parquet, partitioned by origin, split or the like, ordered by beam within files."""
    df.sortWithinPartitions("beam_id", "pos").write.partitionBy(*by).parquet(path)


def save_bucketed(df: DataFrame, name: str, buckets: int) -> None:
    """Beams as a table bucketed by beam: later aggregates and joins by beam need no exchange."""
    df.write.bucketBy(buckets, "beam_id").sortBy("beam_id", "pos").mode("overwrite").saveAsTable(name)
