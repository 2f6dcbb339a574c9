"""Helpers shared by the corpus operators: durable tables, checked broadcasts, components."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of a table of narrow rows (ids and digests) that may be sent to every executor.
BROADCAST_ROWS = 250_000

_scope: ContextVar[str] = ContextVar("scope", default="all")

_local_root: dict[str, str] = {}


def scratch_root(spark: SparkSession) -> str:
    """The folder that all executors share, from ``spark.checkpoint.dir``.

    Only a single-machine session without that setting gets a temporary folder.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    app = spark.sparkContext.applicationId
    if not root:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        if app not in _local_root:
            _local_root[app] = tempfile.mkdtemp(prefix="beamrank-")
            atexit.register(shutil.rmtree, _local_root[app], ignore_errors=True)
        root = "file://" + _local_root[app]
    return f"{root.rstrip('/')}/beamrank-{app}"


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{scratch_root(spark)}/{_scope.get()}/{name}-{uuid.uuid4().hex[:12]}"


@contextmanager
def scratch_scope(name: str) -> Iterator[None]:
    """Durable tables that are made inside lie in a folder that ``release_scratch`` can delete."""
    token = _scope.set(name)
    try:
        yield
    finally:
        _scope.reset(token)


def release_scratch(spark: SparkSession, scope: str) -> None:
    """Delete the durable tables of a scope, once what was made of them is written."""
    root = spark._jvm.org.apache.hadoop.fs.Path(f"{scratch_root(spark)}/{scope}")
    root.getFileSystem(spark._jsc.hadoopConfiguration()).delete(root, True)


def durable(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: the lineage ends there, and a
    lost executor costs only the tasks that it was running."""
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bounded_broadcast(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Hint a broadcast only if the counted ``rows`` are within ``limit``; else the join shuffles."""
    return F.broadcast(df) if rows <= limit else df


def text_or_empty(name: str = "text"):
    return F.coalesce(F.col(name), F.lit(""))


def connected_components(vertices: DataFrame, edges: DataFrame, name: str = "cc") -> DataFrame:
    """Smallest vertex reachable over undirected ``edges (a, b)`` for each of ``vertices (v)``.

    Edges are contracted in rounds: every root takes the smallest of its neighbours and itself, and
    edges are then redrawn between the new roots. Aggregates combine on the map side, so that a hub
    is no hot key; each round is written to the shared folder. Returns ``(v, root)``; vertices
    without edges are their own root.
    """
    links = durable(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), name + "-edges")
    touched = links.select(F.col("a").alias("v")).union(links.select(F.col("b").alias("v"))).distinct()
    labels = touched.select("v", F.col("v").alias("root"))
    while not links.isEmpty():
        both = links.union(links.select(F.col("b"), F.col("a"))).toDF("r", "n")
        hook = durable(both.groupBy("r").agg(F.least("r", F.min("n")).alias("p")), name + "-hook")
        # one pointer jump, so that chains of hooks halve
        up = hook.toDF("p", "pp")
        hook = durable(hook.join(up, "p").select("r", F.col("pp").alias("p")), name + "-jump")
        labels = durable(
            labels.join(hook, labels["root"] == hook["r"], "left").select("v", F.coalesce("p", "root").alias("root")), name + "-labels"
        )
        at, bt = hook.toDF("a", "pa"), hook.toDF("b", "pb")
        links = durable(
            links.join(at, "a").join(bt, "b").where("pa <> pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct(),
            name + "-edges",
        )
    return vertices.join(labels, "v", "left").select("v", F.coalesce("root", "v").alias("root"))
