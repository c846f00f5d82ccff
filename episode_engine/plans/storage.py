"""Intermediates that cut lineage, in the folder that all executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_place(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or the folder given to setCheckpointDir; a temporary one in local mode only."""
    place = spark.conf.get("spark.checkpoint.dir", None) or getattr(spark, "_episode_dir", None)
    if not place:
        set_ = spark.sparkContext._jsc.sc().getCheckpointDir()
        if set_.isDefined():
            place = set_.get()
        elif spark.sparkContext.master.startswith("local") and not spark.sparkContext.master.startswith("local-cluster"):
            place = tempfile.mkdtemp(prefix="episodes-")
            atexit.register(shutil.rmtree, place, ignore_errors=True)
        else:
            raise RuntimeError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
        spark._episode_dir = place
    return place.rstrip("/")


def written(df: DataFrame, name: str) -> DataFrame:
    """df as Parquet in the shared folder, read again."""
    spark = df.sparkSession
    path = f"{shared_place(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_path = path
    return out


def discard(*frames: DataFrame) -> None:
    """Delete written() frames that nothing reads any more."""
    for df in frames:
        if path := getattr(df, "_written_path", None):
            place = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(place, True)
