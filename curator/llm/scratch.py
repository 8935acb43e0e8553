"""Shared scratch space: tables and files that outlive an executor.

Lineage is cut by writing a Parquet table below ``spark.checkpoint.dir`` (the folder that the
cluster shares between driver and executors) and reading it back.  Only where that setting is
absent and driver and executors are one process, as in unit tests, a folder of this driver is used.
"""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Spark then removes a query's shuffle files when the query ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_own: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder as a URI without a trailing slash."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="curator-scratch-"))
        atexit.register(shutil.rmtree, _own[0], ignore_errors=True)
    return f"file://{_own[0]}"


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/curator-{label}-{uuid.uuid4().hex}"


def stored(df: DataFrame, label: str) -> DataFrame:
    """``df`` written once and read back: its lineage ends at files all executors can reach, and the shuffle files behind it go as soon as it is written."""
    path = fresh_path(df.sparkSession, label)
    conf, old = df.sparkSession.conf, df.sparkSession.conf.get(CLEANUP, "false")
    conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        conf.set(CLEANUP, old)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._curator_path = path
    return out


def discard(df: DataFrame) -> None:
    """Remove the files behind a table made by ``stored`` that nothing reads any more."""
    path = getattr(df, "_curator_path", None)
    if path:
        jvm = df.sparkSession._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(target, True)


def free_shuffles(df: DataFrame) -> None:
    """Let Spark remove the shuffle files of queries that have ended now: it does so when the driver collects its garbage, which may be long after."""
    gc.collect()  # what Python no longer uses may still hold plans in the driver's JVM
    df.sparkSession._jvm.System.gc()
