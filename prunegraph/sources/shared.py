"""Tables written between steps, in the folder that all executors share."""

from __future__ import annotations

import gc
import os
import uuid

from pyspark import SparkContext
from pyspark.sql import DataFrame, SparkSession

LOCAL_DEFAULT = "/tmp/checkpoints/prunegraph-graphs"


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; a local folder only where none is configured (tests)."""
    return spark.conf.get("spark.checkpoint.dir", None) or os.environ.get("SPARK_CHECKPOINT_DIR") or LOCAL_DEFAULT


def written(df: DataFrame, name: str = "step") -> DataFrame:
    """``df`` as a written table: plans that read it start there, and a lost executor costs a re-read."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back._written_path = path
    return back


def removed(*frames: DataFrame) -> None:
    """Delete tables of ``written`` that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_written_path", None)
        if path:
            where = df.sparkSession.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(where, True)


def forgotten() -> None:
    """Let Spark delete the shuffle files of plans that nothing holds any more.

    Its cleaner learns of them only when the driver collects garbage."""
    gc.collect()
    SparkContext._active_spark_context._jvm.System.gc()
