"""Tables written in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession, name: str) -> str:
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        root = tempfile.mkdtemp(prefix="svengine-")
        spark.sparkContext.setCheckpointDir(root)
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str = "state", path: str | None = None, by: str | None = None) -> DataFrame:
    """df written as Parquet (by: partitioned by that column) and read again: lineage and plan are cut, and lost executors cost nothing but their running tasks."""
    path = path or shared_folder(df.sparkSession, name)
    (df.write.partitionBy(by) if by else df.write).mode("overwrite").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.shared_path = path
    return out


def _file(spark: SparkSession, path: str):
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark._jsc.hadoopConfiguration()), target


def drop(df: DataFrame) -> None:
    """Delete what written() made, once nothing reads it any more."""
    fs, target = _file(df.sparkSession, df.shared_path)
    fs.delete(target, True)


def complete(spark: SparkSession, path: str) -> bool:
    """Whether a table was written whole at path."""
    fs, target = _file(spark, f"{path}/_SUCCESS")
    return fs.exists(target)
