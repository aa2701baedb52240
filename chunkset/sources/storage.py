"""Where intermediate tables go, and how small a table must be to be broadcast."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BROADCAST_BYTES = 8 << 20


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir if set; else, on one machine, a folder of our own, and on a cluster one in the warehouse."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    master = spark.sparkContext.master
    if master.startswith("local") and "cluster" not in master:
        base = tempfile.mkdtemp(prefix="chunkset-")
        atexit.register(shutil.rmtree, base, True)
        spark.conf.set("spark.checkpoint.dir", base)
        return base
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_work"


def saved(df: DataFrame, tag: str) -> DataFrame:
    """Cuts the lineage: writes df as Parquet to the shared folder and reads it again. The files go when the application ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(at)
    return spark.read.schema(df.schema).parquet(path)


def small_side(df: DataFrame, most: int = BROADCAST_BYTES) -> DataFrame:
    """Marks df for broadcast if Spark's own estimate of its size, which never runs it, is small; beyond that the join shuffles, unless the
    sizes that it finds then speak for a broadcast."""
    return F.broadcast(df) if int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()) <= most else df
