"""Shared scratch space: where loops cut their lineage.

A cluster names one folder that every executor sees in ``spark.checkpoint.dir``; that setting is read
from the session.  Only on a single machine (master ``local[...]``) a temporary folder takes its place.
"""

from __future__ import annotations

import atexit
import gc
import re
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

_OWN: list[str] = []


def scratch_root(spark: SparkSession) -> str:
    """The shared folder of the session, or one of our own where a single machine names none."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", master := spark.conf.get("spark.master", "")):
        raise RuntimeError(f"set spark.checkpoint.dir to a folder that all executors share: master is {master}")
    if not _OWN:
        _OWN.append(tempfile.mkdtemp(prefix="flowrings-"))
        atexit.register(shutil.rmtree, _OWN[0], ignore_errors=True)
    return _OWN[0]


def scratch_path(spark: SparkSession, label: str) -> str:
    return f"{scratch_root(spark)}/flowrings/{label}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to the shared scratch folder and return a scan of it.

    The result has no lineage beyond the files, survives the loss of executors, and claims no
    partitioning, so a later join on a hot key can be split by adaptive execution.
    """
    spark = df.sparkSession
    path = scratch_path(spark, label)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def materialize_observed(df: DataFrame, label: str, **measures: Column) -> tuple[DataFrame, dict]:
    """``materialize`` and aggregates over the rows written, from the same job.

    The rows are counted where they are written, in the job's last stage, whose tasks count once however
    often they were tried.
    """
    seen = Observation()
    out = materialize(df.observe(seen, *(c.alias(n) for n, c in measures.items())), label)
    return out, seen.get


def release(*frames: DataFrame | None) -> None:
    """Delete the files of materialised frames that nothing will read any more."""
    for df in frames:
        if path := getattr(df, "scratch_path", None):
            _delete(df.sparkSession, path)


def release_shuffles(spark: SparkSession) -> None:
    """Let Spark remove the shuffle files of finished steps now: it does so once their frames are collected as garbage."""
    gc.collect()
    spark._jvm.System.gc()


def release_heaps(spark: SparkSession) -> None:
    """Collect garbage in the executors' JVMs, one task a core.

    A JVM keeps the heap that its busiest step needed until a full collection; beside the Python workers of a
    later step it then counts against the executor's memory.  Where an executor gets no task, only its heap stays as it is.
    """
    slots = max(1, spark.sparkContext.defaultParallelism)
    spark.range(0, slots, 1, slots).select(F.expr("reflect('java.lang.System', 'gc')")).collect()


def drop_scratch(spark: SparkSession) -> None:
    """Delete everything this engine has left in the scratch folder of the session."""
    _delete(spark, f"{scratch_root(spark)}/flowrings")


def _delete(spark: SparkSession, where: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(where)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
