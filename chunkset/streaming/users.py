"""Streams of events as sets of users: windows of built-in bitmaps, sessions, and containers kept up to date."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import BinaryType, StructField, StructType

from chunkset.functions import containers as C
from chunkset.sources.storage import shared_dir

HALF = 32768


def stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """Events as a file stream; ts as a timestamp, as watermarks need one (the session's zone should be UTC)."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger)
    # a file source lists a directory; the one file is picked by its name
    rows = source.option("pathGlobFilter", "events.parquet").parquet(sf_dir) if not _is_dir(spark, path) else source.parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def _is_dir(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def run_to_end(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the query over all that is there now and gives what it wrote."""
    spark = df.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{base}/out")

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{base}/out/{number}")

    q = df.writeStream.foreachBatch(keep).option("checkpointLocation", f"{base}/state").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{base}/out/*")


def window_halves(events: DataFrame, length: str, slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """(window, half, bits): users of each window as built-in bitmaps of 32,768 users, 4 kB of state each."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    rows = events.withWatermark("ts", delay).groupBy(w, F.expr(f"user_id div {HALF}").alias("half"))
    return rows.agg(F.bitmap_construct_agg(F.col("user_id") % HALF).alias("bits")).select(F.col("window.start").alias("start"), "half", "bits")


def window_users(halves: DataFrame) -> DataFrame:
    return halves.groupBy("start").agg(F.sum(F.bitmap_count("bits")).alias("users"))


def sessions(events: DataFrame, gap: str = "6 hours", delay: str = "1 day") -> DataFrame:
    rows = events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("s"), "user_id")
    return rows.agg(F.count(F.lit(1)).alias("events")).select("user_id", F.col("s.start").alias("start"), "events")


class Maintain(StatefulProcessor):
    """Keeps the container of a (set, key) up to date as ids arrive, in any order; emits its count after each batch.

    The state is the kind as one byte, then the payload.
    """

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.box = handle.getValueState("box", StructType([StructField("payload", BinaryType())]))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        lows = np.unique(np.concatenate([r["low"].to_numpy() for r in rows]))
        new = C.from_values(lows)
        if self.box.exists():
            old = bytes(self.box.get()[0])
            new = C.union(C.from_payload(old[0], old[1:]), new)
        self.box.update((bytes([new.kind]) + new.payload,))
        yield pd.DataFrame({"set_id": [key[0]], "key": [key[1]], "card": [new.card]})

    def close(self) -> None:
        pass


def maintained(events: DataFrame, set_col: str, id_col: str) -> DataFrame:
    """(set_id, key, card) after each batch, from containers held as state (at most 8 kB each)."""
    rows = events.select(F.col(set_col).cast("string").alias("set_id"), F.shiftright(F.col(id_col), 16).cast("int").alias("key"), F.col(id_col).bitwiseAND(C.CHUNK - 1).cast("int").alias("low"))
    return rows.groupBy("set_id", "key").transformWithStateInPandas(Maintain(), "set_id string, key int, card int", "Update", "none")


def merge_batches(batches: DataFrame, path: str) -> None:
    """A sink that ORs each batch's containers into a table of files; a batch that comes again changes nothing."""
    from chunkset.operators.build import build

    def keep(batch: DataFrame, number: int) -> None:
        build(batch.select("set_id", "id")).write.mode("overwrite").parquet(f"{path}/batch={number}")

    q = batches.writeStream.foreachBatch(keep).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
    q.awaitTermination()
