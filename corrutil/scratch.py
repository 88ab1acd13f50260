"""Tables written to the folder that driver and executors share.

Intermediate results that several branches read, or that must survive a lost
executor, are written as Parquet under ``spark.checkpoint.dir``.
"""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder. Where none is set, a temporary one, in local mode alone: executors share no other."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if base:
        return base.rstrip("/")
    base = getattr(spark.sparkContext, "_corrutil_scratch", None)
    if base is None:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir is not set: driver and executors need a folder that they share")
        base = "file://" + tempfile.mkdtemp(prefix="corrutil-")
        spark.sparkContext._corrutil_scratch = base
    return base


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once and read back: cuts lineage, and no branch computes it again."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def delete_tables(*frames: DataFrame) -> None:
    """Deletes scratch tables that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_scratch_path", None)
        if path:
            delete(df.sparkSession, path)


def discard(*frames: DataFrame) -> None:
    """``delete_tables``, and lets Spark free old shuffle files."""
    delete_tables(*frames)
    release(frames[0].sparkSession if frames else SparkSession.getActiveSession())


def release(spark: SparkSession) -> None:
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
