"""Work folders that driver and executors share, and tables that cut lineage."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession, kind: str = "work") -> str:
    """A new folder under spark.checkpoint.dir, which driver and executors share, gone with the application; where a local session (tests) sets none, a local one."""
    top = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not top:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        top = "file://" + os.path.join(tempfile.gettempdir(), "shapebalance-work")
    root = f"{top.rstrip('/')}/{kind}-{uuid.uuid4().hex}"
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(root)
    fs = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    fs.mkdirs(path)
    fs.deleteOnExit(path)
    return root


def written(df: DataFrame) -> DataFrame:
    """df written as Parquet to a work folder and read back: what follows neither recomputes it nor loses it with an executor."""
    path = f"{shared_root(df.sparkSession, 'cut')}/table"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
