"""Sources and sinks: tables, id lists, generated sets, id spaces, and the container dataset on disk."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chunkset.sources.storage import saved, small_side

EPOCH = "2024-01-01 00:00:00"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_ids(spark: SparkSession, path: str, fmt: str) -> DataFrame:
    """(set_id, id) from csv, json or text (a line: set_id, a blank, id)."""
    if fmt == "text":
        parts = F.split("value", " ")
        return spark.read.text(path).select(parts[0].alias("set_id"), parts[1].cast("long").alias("id"))
    return getattr(spark.read.schema("set_id string, id long"), fmt)(path)


def range_set(spark: SparkSession, start: int, stop: int, step: int = 1, set_id: str = "range") -> DataFrame:
    return spark.range(start, stop, step).select(F.lit(set_id).alias("set_id"), "id")


def example_set(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three chunks: spread multiples of 62, a short run, every other value. 33,868 line items, one for each member, fill them; the next fill the next three."""
    j = F.col("id") % 33_868
    at = F.when(j < 1000, j * 62).when(j < 1100, (1 << 16) + j - 1000).otherwise((2 << 16) + (j - 1100) * 2)
    return row_numbers(spark, sf_dir, "lineitem", "l_orderkey").select(F.lit("example").alias("set_id"), (F.expr("id div 33868") * (3 << 16) + at).alias("id"))


def to_id_sets(df: DataFrame, id_col: Column, attributes: dict[str, Column]) -> DataFrame:
    """(set_id, id): a set for each value of each attribute, named attribute=value. A null value is in no set. One scan."""
    named = F.array(*[F.concat(F.lit(f"{name}="), value.cast("string")) for name, value in attributes.items()])
    return df.select(F.explode(named).alias("set_id"), id_col.cast("long").alias("id")).filter("set_id is not null and id is not null")


def dense_row_ids(df: DataFrame, order: list[str], name: str = "id") -> DataFrame:
    """Adds 0, 1, 2, ... in the order of the columns, which must be unique together; no task sorts more than its range.

    Rows are range-partitioned and sorted once and kept; each partition's count gives the others' offsets.
    """
    kept = saved(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()), "row-ids")
    part = F.shiftright("_at", 33)
    counts = kept.groupBy(part.alias("_part")).agg(F.count(F.lit(1)).alias("_n"))
    offsets = counts.select("_part", F.coalesce(F.sum("_n").over(W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_offset"))
    rows = kept.withColumn("_part", part).join(small_side(offsets), "_part")
    return rows.withColumn(name, F.col("_offset") + F.col("_at").bitwiseAND((1 << 33) - 1)).drop("_at", "_part", "_offset")


def row_numbers(spark: SparkSession, sf_dir: str, name: str, key: str) -> DataFrame:
    """(id): 0, 1, 2, ..., one for each row of the table, whatever its key; which of equal keys comes first changes nothing."""
    return dense_row_ids(read_table(spark, sf_dir, name).select(key), [key]).select("id")


def seconds(ts: Column) -> Column:
    """Whole seconds since the epoch of the events, without any time zone."""
    return F.timestamp_diff("SECOND", F.lit(EPOCH).cast("timestamp_ntz"), ts)


def milliseconds(ts: Column) -> Column:
    return F.timestamp_diff("MILLISECOND", F.lit(EPOCH).cast("timestamp_ntz"), ts)


def lineitem_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets over orderkey * 8 + linenumber."""
    t = read_table(spark, sf_dir, "lineitem")
    return to_id_sets(t, F.col("l_orderkey") * 8 + F.col("l_linenumber"), lineitem_attributes())


def lineitem_attributes() -> dict[str, Column]:
    return {
        "flag": F.col("l_returnflag"),
        "status": F.col("l_linestatus"),
        "qty": F.col("l_quantity").cast("int"),
        "disc": F.round(F.col("l_discount") * 100).cast("int"),
        "tax": F.round(F.col("l_tax") * 100).cast("int"),
        "year": F.year("l_shipdate"),
        "part": F.col("l_partkey"),
    }


def lineitem_rows(spark: SparkSession, sf_dir: str, stretch: int = 1) -> DataFrame:
    """Sets over dense row numbers, times stretch."""
    t = read_table(spark, sf_dir, "lineitem")
    rows = dense_row_ids(t, ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"])
    return to_id_sets(rows, F.col("id") * stretch, lineitem_attributes() | {"supp": F.col("l_suppkey"), "day": F.to_date("l_shipdate")})


def order_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = read_table(spark, sf_dir, "orders")
    return to_id_sets(t, F.col("o_orderkey"), {"ostatus": F.col("o_orderstatus"), "oprio": F.col("o_orderpriority")})


def event_sets(spark: SparkSession, sf_dir: str, space: str = "ev") -> DataFrame:
    """space: ev (event_id), ev_sec or ev_ms."""
    t = read_table(spark, sf_dir, "events")
    ident = {"ev": F.col("event_id"), "ev_sec": seconds(F.col("ts")), "ev_ms": milliseconds(F.col("ts"))}[space]
    return to_id_sets(t, ident, {"day": F.to_date("ts"), "type": F.col("event_type"), "user": F.col("user_id"), "hour": F.hour("ts")})


def terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Posting lists: the documents that hold each blank-separated lower-case word."""
    t = read_table(spark, sf_dir, "documents")
    return t.select(F.explode(F.array_distinct(F.split(F.lower("text"), " "))).alias("set_id"), F.col("doc_id").alias("id")).filter("set_id <> ''")


DRAWS = 100_000


def draw_parts(spark: SparkSession, sf_dir: str) -> tuple[int, int]:
    """Into how many parts the orders fall for draws, and how many of them each has."""
    n = read_table(spark, sf_dir, "orders").agg(F.count("o_orderkey")).first()[0]
    parts = max(1, -(-n // DRAWS))
    return parts, max(1, n // parts)


def synthetic(spark: SparkSession, sf_dir: str, exponents: tuple[int, ...], dist: str = "uniform", seeds: tuple[int, ...] = (42,)) -> DataFrame:
    """Sets dist-exponent-seed-part: each order of a part draws a number below its orders * 2^exponent, uniform or squared, from its key by integer
    arithmetic alone; repeats fall together. Parts have at most DRAWS orders where keys are dense."""
    parts, draws = draw_parts(spark, sf_dir)
    big, prime = 1 << 31, (1 << 31) - 1
    a = F.pmod(F.pmod(F.col("i"), F.lit(big)) * 1103515245 + F.col("seed") * 12345, F.lit(big))
    b = F.pmod(a.bitwiseXOR(F.shiftright(a, 15)) * 48271, F.lit(prime))
    y = F.pmod(b.bitwiseXOR(F.shiftright(b, 13)) * 69621, F.lit(prime))
    each = lambda values: F.explode(F.array(*map(F.lit, values)))
    keys = read_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("i")).filter("i is not null")
    drawn = keys.select("i", each(seeds).alias("seed")).select("seed", F.expr(f"i % {parts}").alias("part"), y.alias("y"))
    most = f"({draws} * shiftleft(1L, e))"
    ident = F.expr(f"(y * {most}) div {prime}") if dist == "uniform" else F.expr(f"(((y * y) div {big}) * {most}) div {big}")
    return drawn.select("*", each(exponents).alias("e")).select(F.format_string(f"{dist}-%d-%d-%d", "e", "seed", "part").alias("set_id"), ident.alias("id"))


# -- the container dataset ------------------------------------------------------------------------------------------


def write_index(containers: DataFrame, path: str, files_per_attribute: int = 8) -> None:
    """Parquet by attribute (the part of set_id before =), clustered by key so that row groups skip on it."""
    named = containers.withColumn("attr", F.substring_index("set_id", "=", 1))
    named.repartition(files_per_attribute, "attr", "key").sortWithinPartitions("attr", "key", "set_id").write.partitionBy("attr").parquet(path)


def read_index(spark: SparkSession, path: str, attribute: str | None = None) -> DataFrame:
    df = spark.read.parquet(path)
    return (df.filter(F.col("attr") == attribute) if attribute else df).drop("attr")


def write_bucketed(containers: DataFrame, table: str, buckets: int = 8) -> DataFrame:
    """A table bucketed and sorted by key: joins on the key need no shuffle."""
    containers.write.bucketBy(buckets, "key").sortBy("key").mode("overwrite").saveAsTable(table)
    return containers.sparkSession.table(table)
