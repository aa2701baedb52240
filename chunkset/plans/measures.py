"""Sizes and counts by which the schemes are compared. The hybrid's containers cost OVERHEAD bytes each besides their payload."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chunkset.operators import baselines
from chunkset.operators.build import payload_bytes

OVERHEAD = 4
SCHEMES = ("hybrid", "posfill", "fillrun", "plain")


def hybrid_counts(ids: DataFrame) -> DataFrame:
    """(set_id, key, card, last_word) of the containers that the ids would make, without making them. Ids that repeat count once."""
    words = baselines.plain_words(ids)
    return words.groupBy("set_id", F.shiftright("widx", 10).alias("key")).agg(F.sum(F.bit_count("word")).cast("long").alias("card"), F.max("widx").alias("last_word"))


def sizes(ids: DataFrame, overhead: int = OVERHEAD) -> DataFrame:
    """(set_id, card, hybrid, posfill, fillrun, plain): bits of each encoding of each set, from one list of words and one of runs."""
    words = hybrid_counts(ids).groupBy("set_id").agg(F.sum("card").alias("card"), (F.sum(payload_bytes() + overhead) * 8).alias("hybrid"), ((F.max("last_word") + 1) * 64).alias("plain"))
    runs = baselines.both_word_counts(ids).select("set_id", (F.col("posfill") * 32).alias("posfill"), (F.col("fillrun") * 32).alias("fillrun"))
    return words.join(runs, "set_id").select("set_id", "card", *SCHEMES)


def bits_per_id(sized: DataFrame) -> DataFrame:
    return sized.select("set_id", "card", *[F.round(F.col(s) / F.col("card"), 6).alias(s) for s in SCHEMES])


def expansion(sized: DataFrame) -> DataFrame:
    """(scheme, of_sums, mean_of_ratios): how much larger each scheme is than the hybrid."""
    long = sized.select("hybrid", F.explode(F.array(*[F.struct(F.lit(s).alias("scheme"), F.col(s).alias("bits")) for s in SCHEMES[1:]])).alias("x")).select("hybrid", "x.scheme", "x.bits")
    return long.groupBy("scheme").agg(F.round(F.sum("bits") / F.sum("hybrid"), 6).alias("of_sums"), F.round(F.avg(F.col("bits") / F.col("hybrid")), 6).alias("mean_of_ratios"))


def profile(ids: DataFrame, n: int, overhead: int = OVERHEAD) -> DataFrame:
    """One row: rows, sets, mean density, hybrid bits per id over all sets."""
    h = hybrid_counts(ids).groupBy("set_id").agg(F.sum("card").alias("card"), (F.sum(payload_bytes() + overhead) * 8).alias("bits"))
    return h.agg(F.lit(n).cast("long").alias("n_rows"), F.count(F.lit(1)).alias("sets"), F.round(F.avg(F.col("card") / n), 8).alias("density"), F.round(F.sum("bits") / F.sum("card"), 6).alias("bits_per_item"))


def bounds(ids: DataFrame) -> DataFrame:
    """(set_id, key, card, problem) where a container needs over 16 bits an id or 8 kB; none, if the bounds hold."""
    c = hybrid_counts(ids)
    return c.filter((payload_bytes() * 8 > F.col("card") * 16) | (payload_bytes() > 8192)).select("set_id", F.col("key").cast("long").alias("key"), "card")
