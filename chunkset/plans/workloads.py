"""The experiments' set-ups over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chunkset.sources import tables

#: Attributes of each stand-in for a real data set, and the id space that its rows get.
REAL = {
    1: ("part", "supp", "day", "qty", "disc", "tax", "flag", "status"),
    2: ("ostatus", "oprio"),
    3: ("day", "hour"),
    4: ("qty", "disc", "tax", "year"),
    5: ("user",),
}


def real_sets(spark: SparkSession, sf_dir: str, which: int) -> DataFrame:
    """(set_id, id) of the stand-in, which may repeat: dense line items, orders, events in time order, line-item slots, users by millisecond."""
    rows = {
        1: lambda: tables.lineitem_rows(spark, sf_dir),
        2: lambda: tables.order_sets(spark, sf_dir),
        3: lambda: tables.event_sets(spark, sf_dir),
        4: lambda: tables.lineitem_slots(spark, sf_dir),
        5: lambda: tables.event_sets(spark, sf_dir, "ev_ms"),
    }[which]()
    return rows.filter(F.substring_index("set_id", "=", 1).isin(*REAL[which]))


def set_names(spark: SparkSession, sf_dir: str, which: int) -> DataFrame:
    """The distinct names of real_sets, without its ids."""
    if which in (1, 4):
        t = tables.read_table(spark, sf_dir, "lineitem")
        named = tables.to_id_sets(t, F.lit(0), tables.lineitem_attributes() | {"supp": F.col("l_suppkey"), "day": F.to_date("l_shipdate")})
        return named.filter(F.substring_index("set_id", "=", 1).isin(*REAL[which])).select("set_id").distinct()
    return real_sets(spark, sf_dir, which).select("set_id").distinct()


def sample_pairs(ids: DataFrame, pairs: int = 100, seed: int = 42) -> DataFrame:
    """(pair_id, left_set, right_set) of the sets that ids names: attributes drawn with replacement, then one of each one's sets, by a hash that SQL can repeat."""
    sets = ids.select("set_id").distinct().withColumn("attr", F.substring_index("set_id", "=", 1))
    by_attr = sets.withColumn("v", F.row_number().over(W.partitionBy("attr").orderBy("set_id")) - 1).withColumn("n", F.count(F.lit(1)).over(W.partitionBy("attr")))
    names = sorted(r["attr"] for r in sets.select("attr").distinct().collect())  # columns of a table: a handful
    a = F.element_at(F.create_map(*[F.lit(x) for i, n in enumerate(names) for x in (n, i)]), F.col("attr")) if names else F.lit(0)
    known = by_attr.withColumn("a", a)
    big = 1 << 31
    spark = ids.sparkSession
    h = F.pmod((F.col("id") + 1) * 1103515245 + seed * 12345, F.lit(big))
    h = F.pmod(h.bitwiseXOR(F.shiftright(h, 13)) * 48271, F.lit(big - 1))
    draws = spark.range(2 * pairs).select(F.col("id").alias("i"), h.alias("h"))
    drawn = draws.select("i", F.expr(f"cast(h % {max(1, len(names))} as int)").alias("a"), F.expr("h div 97").alias("k"))
    chosen = drawn.join(known, "a").filter("v = k % n").select("i", "set_id")
    return chosen.groupBy(F.expr("i div 2").cast("int").alias("pair_id")).agg(F.max(F.when(F.expr("i % 2 = 0"), F.col("set_id"))).alias("left_set"), F.max(F.when(F.expr("i % 2 = 1"), F.col("set_id"))).alias("right_set"))


def of_pairs(ids: DataFrame, pairs: DataFrame) -> DataFrame:
    """The ids of the sets that the pairs name."""
    named = pairs.select(F.col("left_set").alias("set_id")).union(pairs.select("right_set")).distinct()
    return ids.join(F.broadcast(named), "set_id")  # two names a pair
