"""Stage checkpoints: tables written once to the folder that a cluster shares, and read back.

Lineage ends there, so a lost executor costs the tasks it held and nothing before them, and no branch of a plan computes the stage again.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Spark then removes a query's shuffle files when the query ends.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_own: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; where it is unset and driver and executors are one process, a folder of this driver."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="curator-stages-"))
        atexit.register(shutil.rmtree, _own[0], ignore_errors=True)
    return f"file://{_own[0]}"


def stage(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table of the shared folder; the shuffle files behind it go as soon as it is written."""
    path = f"{shared_folder(df.sparkSession)}/stage-{name}-{uuid.uuid4().hex}"
    conf, old = df.sparkSession.conf, df.sparkSession.conf.get(CLEANUP, "false")
    conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        conf.set(CLEANUP, old)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._stage_path = path
    return out


def unstage(df: DataFrame) -> None:
    """Remove the files of a table made by ``stage`` that nothing reads any more."""
    jvm = df.sparkSession._jvm
    target = jvm.org.apache.hadoop.fs.Path(df._stage_path)
    target.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(target, True)
