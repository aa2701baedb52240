"""What the data-preparation operators share: storage, hot-group blocks, connected components."""

from __future__ import annotations

import atexit
import ctypes
import gc
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import suppress
from functools import wraps
from sys import getsizeof

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space that separates words wherever a contract speaks of words.
WORD_GAP = r"[\x20\x09-\x0D]+"


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A folder that the driver and all executors see: spark.checkpoint.dir if set, else one of our own."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if spark.sparkContext.master.startswith("local") and "cluster" not in spark.sparkContext.master:
        base = tempfile.mkdtemp(prefix="chunkset-")  # one machine: its folder is shared by definition
        atexit.register(shutil.rmtree, base, True)
        spark.conf.set("spark.checkpoint.dir", base)
        return base
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_work"


def saved(df: DataFrame, tag: str) -> DataFrame:
    """Cuts the lineage: writes df as Parquet to the shared folder and reads it again. The files go when the application ends, or by discard()."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    goes_at_exit(spark, path)
    out = spark.read.schema(df.schema).parquet(path)
    out.saved_at = path
    return out


def _file_system(spark: SparkSession, path: str):
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()), at


def goes_at_exit(spark: SparkSession, path: str) -> None:
    fs, at = _file_system(spark, path)
    fs.deleteOnExit(at)


def discard(*tables: DataFrame) -> None:
    """Deletes the files of saved tables that nothing will read again."""
    for t in tables:
        fs, at = _file_system(t.sparkSession, t.saved_at)
        fs.delete(at, True)


def bounded_text(col: str = "text"):
    """A text as bytes; a null text is the empty text."""
    return F.coalesce(F.col(col).cast("binary"), F.lit(b"")).alias(col)


PART_BYTES, ENTRY_BYTES, BATCH_KEY = 4 << 20, 100, "spark.sql.execution.arrow.maxBytesPerBatch"


def small_batches(df: DataFrame) -> DataFrame:
    """df, from whose session on Arrow batches hold PART_BYTES at most: executors keep several of them, and Spark's default is sixteen times as much."""
    spark = df.sparkSession
    now = spark.conf.get(BATCH_KEY, None)
    if now and not 0 < spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(now) <= PART_BYTES:
        spark.conf.set(BATCH_KEY, f"{PART_BYTES}b")
    return df



def raw(x: pa.Scalar) -> bytes:
    return x.as_buffer().to_pybytes() if x.is_valid else b""


def parts(batches: Iterator[pa.RecordBatch], column: int, most: int = PART_BYTES) -> Iterator[pa.RecordBatch]:
    """The batches in parts whose binary column holds about so many bytes, one row at least: what is made of a part, and sent back, stays small."""
    for batch in batches:
        ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
        at = 0
        while at < len(ends):
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, "right")))
            yield batch.slice(at, to - at)
            at = to
        del batch
        pa.default_memory_pool().release_unused()


class Memo:
    """A cache of two generations, each of so many bytes: what was asked for since the last turn survives the next."""

    def __init__(self, most_bytes: int, make: Callable):
        self.most, self.room, self.make, self.young, self.old = most_bytes, most_bytes, make, {}, {}

    def clear(self) -> None:
        self.young, self.old, self.room = {}, {}, self.most

    def find(self, key, make: Callable | None = None):
        """For keys that self.young lacks; make, if given, instead of the cache's own."""
        value = self.old.get(key)
        if value is None:
            value = (make or self.make)(key)
        if self.room <= 0:
            self.young, self.old, self.room = {}, self.young, self.most
        self.young[key] = value
        self.room -= ENTRY_BYTES + getsizeof(key) + getsizeof(value)
        return value


def sorted_runs(batches: Iterator[pa.RecordBatch], keys: list[str], at_least: int = 65536) -> Iterator[pa.Table]:
    """Regroups Arrow batches, sorted by keys, into tables that never cut a group of equal keys."""
    held: list[pa.RecordBatch] = []
    rows = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        rows += batch.num_rows
        if rows < at_least:
            continue
        table = pa.Table.from_batches(held).combine_chunks()
        last = np.ones(table.num_rows, bool)
        for key in keys:
            col = table.column(key).to_numpy(zero_copy_only=False)
            last &= col == col[-1]
        differs = np.flatnonzero(~last)
        cut = int(differs[-1]) + 1 if len(differs) else 0
        if cut:
            yield table.slice(0, cut)
        rest = table.slice(cut)
        held, rows = rest.to_batches(), rest.num_rows
    if rows:
        yield pa.Table.from_batches(held).combine_chunks()


def tidy(run: Callable) -> Callable:
    """run, whose worker gives what it no longer needs back to the system at its end: workers are kept, and executors hold several."""

    @wraps(run)
    def tidied(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        gc.collect()
        pa.default_memory_pool().release_unused()
        with suppress(OSError, AttributeError):  # where the C library has no such call
            ctypes.CDLL(None).malloc_trim(0)

    return tidied


def run_starts(*cols: np.ndarray) -> np.ndarray:
    """Where groups of equal keys begin, with the length at the end."""
    n = len(cols[0])
    new = np.zeros(n, bool)
    new[:1] = True
    for c in cols:
        new[1:] |= c[1:] != c[:-1]
    return np.append(np.flatnonzero(new), n)


def into_blocks(df: DataFrame, bucket: list[str], unit: str, block_rows: int, sizes: DataFrame | None = None) -> DataFrame:
    """Splits the rows of each bucket into blocks of about block_rows, and sends each row to every pair of blocks that holds its own.

    Adds block (the row's own), lo and hi: a task that gets the rows of one (bucket, lo, hi) sees
    block lo against block hi. All pairs of rows of a bucket meet exactly once (within a block: at lo = hi),
    and no task gets more than about two blocks, however large the bucket is.
    """
    sizes = sizes if sizes is not None else df.groupBy(*bucket).agg(F.count(F.lit(1)).alias("bucket_rows"))
    large = sizes.filter(F.col("bucket_rows") > block_rows).select(*bucket, F.ceil(F.col("bucket_rows") / block_rows).cast("int").alias("blocks"))
    placed = df.join(large, bucket, "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    placed = placed.withColumn("block", F.pmod(F.xxhash64(unit), F.col("blocks")).cast("int"))
    other = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    return other.withColumns({"lo": F.least("block", "other"), "hi": F.greatest("block", "other")}).drop("other", "blocks")


def local_components(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes of the links (u, v) and the smallest node that each reaches by them."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, label[a], low)
        np.minimum.at(new, label[b], low)
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        while True:
            jumped = new[new]
            if (jumped == new).all():
                break
            new = jumped
        if (new == label).all():
            return nodes, nodes[label]
        label = new


def star_links(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """As few links as keep the components: each node to the smallest it reaches."""
    if not len(u):
        return u, v
    nodes, low = local_components(u, v)
    keep = nodes != low
    return nodes[keep], low[keep]


def components(links: DataFrame, u: str = "u", v: str = "v") -> DataFrame:
    """(node, component): the smallest node that each node of the links reaches. Nodes without links aren't listed.

    Links are first shrunk to spanning stars inside each partition; then rounds of star contraction alternate
    (each node's larger neighbours move to its smallest one, then its smaller ones do), each round written to the
    shared folder, until nothing changes. Only aggregates that combine first and joins that Spark can split touch a hot node: the smallest
    neighbours are written before the join, as a join right after an aggregate by the same key would bring a node's links to one task.
    """

    def shrink(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        rows = 0
        for b in batches:
            held.append((b.column(0).to_numpy(), b.column(1).to_numpy()))
            rows += b.num_rows
            if rows > 400_000:
                held = [star_links(*(np.concatenate(x) for x in zip(*held, strict=True)))]
                rows = len(held[0][0])
                if rows > 200_000:
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in held[0]], ["u", "v"])
                    held, rows = [], 0
        if held:
            a, b = star_links(*(np.concatenate(x) for x in zip(*held, strict=True)))
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["u", "v"])

    pairs = links.select(F.col(u).cast("long").alias("u"), F.col(v).cast("long").alias("v")).filter("u <> v")
    stars = saved(pairs.mapInArrow(shrink, "u long, v long").distinct(), "links")
    seen = None
    while True:
        # larger neighbours to the smallest neighbour
        both = stars.select("u", "v").union(stars.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = saved(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")), "links")
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = saved(large, "links")
        discard(stars, least)
        # smaller neighbours, and the node itself, to the smallest
        least = saved(large.groupBy("u").agg(F.min("v").alias("m")), "links")
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v")
        stars = saved(small.union(least.select("u", F.col("m").alias("v"))).distinct(), "links")
        discard(large, least)
        now = stars.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        if now == seen:
            break
        seen = now
    ends = stars.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return ends.union(stars.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
