"""Shared scratch space: where lineage is cut and intermediate tables live.

Everything goes under the folder that the session names in
``spark.checkpoint.dir``, which every executor and the driver can reach, so a
lost executor never takes an intermediate result with it. Only a local-mode
session without that setting gets a temporary folder of its own.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The shared scratch folder of this session."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    root = tempfile.mkdtemp(prefix="motifjoin-")
    spark.sparkContext.setCheckpointDir(root)
    return root


def new_path(spark: SparkSession, name: str) -> str:
    """A path under the shared folder that nobody else uses."""
    return f"{shared_root(spark)}/motifjoin-{name}-{uuid.uuid4().hex[:12]}"


def open_folder(spark: SparkSession, path: str | None = None) -> str | None:
    """The shared folder, or a path in it, as tasks open it themselves; none where only Spark reads it."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path or shared_root(spark))
    fs = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return where.toUri().getPath() if fs.getUri().getScheme() == "file" else None


def materialize(df: DataFrame, name: str = "step", compression: str = "snappy") -> DataFrame:
    """Write ``df`` to the shared folder and read it back: a reliable cut of its lineage."""
    path = new_path(df.sparkSession, name)
    df.write.mode("overwrite").option("compression", compression).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop_stored(df: DataFrame) -> None:
    """Delete a table that ``materialize`` stored and nothing reads any more."""
    if files := df.inputFiles():
        drop_path(df.sparkSession, files[0].rpartition("/")[0])


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a scratch path on whatever filesystem holds it."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
