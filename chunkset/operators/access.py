"""Membership, change, and counting on container tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chunkset.functions import containers as C
from chunkset.operators import pairwise
from chunkset.operators.build import build, kernel, split_id
from chunkset.sources.storage import small_side


def contains_many(containers: DataFrame, probes: DataFrame) -> DataFrame:
    """(set_id, id) of the probes (id) that each set holds: one join on the key, then all probes of a container at once."""
    key, low = split_id(F.col("id"))
    keyed = probes.select("id", key.alias("key"), low.alias("low")).distinct()
    grouped = keyed.groupBy("key").agg(F.collect_list("low").alias("lows"))  # at most a chunk of them

    def test(r: dict):
        box = C.from_payload(r["kind"], r["payload"])
        lows = np.array(r["lows"], np.int64)
        if box.kind == C.BITMAP:
            hit = (box.data[lows >> 6] >> (lows & 63).astype(np.uint64)) & np.uint64(1) == 1
        else:
            hit = np.isin(lows, box.data)
        for x in lows[hit].tolist():
            yield r["set_id"], (r["key"] << 16) + x

    return kernel(containers.select("set_id", "key", "kind", "payload").join(small_side(grouped), "key"), "set_id string, id long", test)


def contains(containers: DataFrame, set_id: str, x: int) -> bool:
    row = containers.filter((F.col("set_id") == set_id) & (F.col("key") == x >> 16)).select("kind", "payload").first()
    return bool(row) and C.contains(C.from_payload(row["kind"], bytes(row["payload"])), x & 65535)


def add_many(containers: DataFrame, ids: DataFrame) -> DataFrame:
    """The sets with ids added, as a union with what the ids build."""
    return pairwise.same_sets(containers, build(ids), "or")


def remove_many(containers: DataFrame, ids: DataFrame) -> DataFrame:
    return pairwise.same_sets(containers, build(ids), "andnot")


def cardinality(containers: DataFrame) -> DataFrame:
    """From the counters alone: payloads aren't read."""
    return containers.groupBy("set_id").agg(F.sum("card").alias("card"))


def _before(containers: DataFrame) -> DataFrame:
    w = W.partitionBy("set_id").orderBy("key").rowsBetween(W.unboundedPreceding, -1)
    return containers.select("set_id", "key", "card", F.coalesce(F.sum("card").over(w), F.lit(0)).alias("before"))


def rank(containers: DataFrame, queries: DataFrame) -> DataFrame:
    """(set_id, id, rank) for queries (set_id, id): members at most id. Counters give the chunks below, one container the rest.

    A query falls between two keys of its set; each counter row covers the keys up to the next one. The keys that are asked for find
    theirs by a sort-merge over both (a union and a last-value window), not by a range join; queries then join by key, so that a set
    that many ask about fills no window.
    """
    key, low = split_id(F.col("id"))
    asked = queries.select("set_id", F.col("id").alias("q"), key.alias("key"), low.alias("low"))
    q = asked.select("set_id", "key").distinct().select("set_id", "key", F.lit(1).alias("side"), F.lit(None).cast("int").alias("card"), F.lit(None).cast("long").alias("before"))
    c = _before(containers).select("set_id", "key", F.lit(0).alias("side"), "card", "before")
    w = W.partitionBy("set_id").orderBy("key", "side").rowsBetween(W.unboundedPreceding, 0)
    last = c.union(q).select("set_id", "key", "side", *[F.last(F.when(F.col("side") == 0, F.col(x)), ignorenulls=True).over(w).alias(f"last_{x}") for x in ("key", "card", "before")]).filter("side = 1").drop("side")
    hit = asked.join(last, ["set_id", "key"]).join(containers.select("set_id", "key", "kind", "payload"), ["set_id", "key"], "left")

    def count(r: dict):
        if r["last_key"] is None:
            n = 0
        elif r["payload"] is None:
            n = r["last_before"] + r["last_card"]
        else:
            n = r["last_before"] + C.rank(C.from_payload(r["kind"], r["payload"]), r["low"])
        yield r["set_id"], r["q"], n

    return kernel(hit.select("set_id", "q", "low", "last_key", "last_card", "last_before", "kind", "payload"), "set_id string, id long, rank long", count)


def select(containers: DataFrame, queries: DataFrame) -> DataFrame:
    """(set_id, j, id) for queries (set_id, j): the member with j below it, null if there is none."""
    c = _before(containers).select("set_id", F.lit(None).cast("long").alias("j"), F.col("before").alias("at"), F.lit(0).alias("side"), "key", "card", "before")
    q = queries.select("set_id", "j", F.col("j").alias("at"), F.lit(1).alias("side"), F.lit(None).cast("int").alias("key"), F.lit(None).cast("int").alias("card"), F.lit(None).cast("long").alias("before"))
    w = W.partitionBy("set_id").orderBy("at", "side").rowsBetween(W.unboundedPreceding, 0)
    found = c.union(q).select("set_id", "j", *[F.last(F.when(F.col("side") == 0, F.col(x)), ignorenulls=True).over(w).alias(x) for x in ("key", "card", "before")]).filter("j is not null")
    hit = found.join(containers.select("set_id", "key", "kind", "payload"), ["set_id", "key"], "left")

    def pick(r: dict):
        at = None if r["payload"] is None or not 0 <= r["j"] - r["before"] else C.select(C.from_payload(r["kind"], r["payload"]), r["j"] - r["before"])
        yield r["set_id"], r["j"], None if at is None else (r["key"] << 16) + at

    return kernel(hit.select("set_id", "j", "key", "before", "kind", "payload"), "set_id string, j long, id long", pick)


def range_count(containers: DataFrame, queries: DataFrame) -> DataFrame:
    """(set_id, low, high, members) for queries (set_id, low, high): members in [low, high)."""
    ends = queries.select("set_id", (F.col("low") - 1).alias("id")).union(queries.select("set_id", (F.col("high") - 1).alias("id"))).filter("id >= 0").distinct()
    ranks = rank(containers, ends)
    low, high = ranks.select("set_id", (F.col("id") + 1).alias("low"), F.col("rank").alias("r0")), ranks.select("set_id", (F.col("id") + 1).alias("high"), F.col("rank").alias("r1"))
    return queries.join(low, ["set_id", "low"], "left").join(high, ["set_id", "high"]).select("set_id", "low", "high", (F.col("r1") - F.coalesce("r0", F.lit(0))).alias("members"))


def min_max(containers: DataFrame) -> DataFrame:
    """(set_id, least, most): only the first and the last container of a set are opened."""
    ends = containers.groupBy("set_id").agg(F.min_by(F.struct("key", "kind", "payload"), "key").alias("a"), F.max_by(F.struct("key", "kind", "payload"), "key").alias("b"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for r in b.to_pylist():
                values = [C.plain_values(C.from_payload(r[s]["kind"], r[s]["payload"])) for s in "ab"]
                out.append((r["set_id"], (r["a"]["key"] << 16) + int(values[0][0]), (r["b"]["key"] << 16) + int(values[1][-1])))
            yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], t) for i, t in enumerate((pa.string(), pa.int64(), pa.int64()))], ["set_id", "least", "most"])

    return ends.mapInArrow(run, "set_id string, least long, most long")


def first_members(containers: DataFrame, k: int) -> DataFrame:
    """(set_id, id): the k smallest members; containers beyond the one in which the count passes k aren't opened."""
    from chunkset.operators.build import to_ids

    near = _before(containers).filter(F.col("before") < k).select("set_id", "key")
    ids = to_ids(containers.join(near, ["set_id", "key"], "left_semi"))
    order = F.row_number().over(W.partitionBy("set_id").orderBy("id"))
    return ids.withColumn("n", order).filter(F.col("n") <= k).select("set_id", "id")
