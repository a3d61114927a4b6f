"""Tables written to the shared folder: the lineage cuts of the operators.

The folder is ``spark.checkpoint.dir`` of the session.  Where that is unset
(local tests) a temporary folder stands in; on a cluster it must be set,
because drivers and executors share no local disk.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_LOCAL: list[str] = []


def shared_root(spark: SparkSession) -> str:
    """The application's own folder below the shared one."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        if not _LOCAL:
            _LOCAL.append(tempfile.mkdtemp(prefix="overlapix-"))
        root = f"file://{_LOCAL[0]}"
    return f"{root.rstrip('/')}/overlapix-{spark.sparkContext.applicationId}"


def new_path(spark: SparkSession, label: str) -> str:
    return f"{shared_root(spark)}/{label}-{uuid.uuid4().hex[:12]}"


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` once and return the reader of what was written."""
    spark = df.sparkSession
    path = new_path(spark, label)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._overlapix_path = path
    return out


def discard(df: DataFrame) -> None:
    """Delete a table that :func:`materialise` wrote and no later plan reads."""
    path = getattr(df, "_overlapix_path", None)
    if path:
        remove_path(df.sparkSession, path)


def remove_path(spark: SparkSession, path: str) -> None:
    jvm = spark._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
