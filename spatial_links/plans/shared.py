"""The folder that driver and executors share, for files that a query writes and reads again."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; where it is unset, a folder of our own in local mode and an error on a cluster."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="checkpoint-"))
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame) -> DataFrame:
    """df as a table in the shared folder: lineage and plan are cut, and a lost executor costs no recomputation."""
    spark = df.sparkSession
    path = new_path(spark, "table")
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def settled(df: DataFrame) -> DataFrame:
    """A small result, `written` at once; the JVM is then asked to collect the plan, on which Spark deletes its shuffle files."""
    out = written(df)
    gc.collect()
    df.sparkSession._jvm.System.gc()
    return out


def dropped(df: DataFrame) -> None:
    """Deletes the files of a `written` table, once nothing reads it any more."""
    spark = df.sparkSession
    top = shared_dir(spark).split(":", 1)[-1].lstrip("/")
    for parent in {f.rpartition("/")[0] for f in df.inputFiles()}:
        if top in parent:
            path = spark._jvm.org.apache.hadoop.fs.Path(parent)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
