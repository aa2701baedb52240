"""The schemes compared with: plain bitsets and the two run-length codecs, as tables of words and of runs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chunkset.functions import runs as R
from chunkset.operators.build import kernel
from chunkset.sources.storage import small_side

# -- plain bitset --------------------------------------------------------------------------------------------------


def plain_words(ids: DataFrame) -> DataFrame:
    """(set_id, widx, word); words of zeros aren't stored, but count in plain_sizes."""
    return ids.groupBy("set_id", F.shiftright("id", 6).alias("widx")).agg(F.expr("bit_or(shiftleft(1L, cast(id & 63 as int)))").alias("word"))


def plain_sizes(ids: DataFrame) -> DataFrame:
    """(set_id, words): up to the last one that isn't zero."""
    return ids.groupBy("set_id").agg((F.shiftright(F.max("id"), 6) + 1).alias("words"))


def plain_pairs(ids: DataFrame, pairs: DataFrame, op: str) -> DataFrame:
    """(pair_id, widx, word) of the result, zeros dropped."""
    w = plain_words(ids)
    side = lambda c: w.join(small_side(pairs.select("pair_id", F.col(c).alias("set_id"))), "set_id").select("pair_id", "widx", F.col("word").alias(c))
    both = side("left_set").join(side("right_set"), ["pair_id", "widx"], "inner" if op == "and" else "full_outer")
    a, b = F.coalesce("left_set", F.lit(0)), F.coalesce("right_set", F.lit(0))
    return both.select("pair_id", "widx", (a.bitwiseAND(b) if op == "and" else a.bitwiseOR(b)).alias("word")).filter("word <> 0")


def doubled_capacity(ids: DataFrame) -> DataFrame:
    """(set_id, words): capacity after the ids have come in ascending order, doubled whenever it doesn't do. A set streams through its task
    in order; nothing of it is held but the capacity."""
    needs = plain_words(ids).select("set_id", (F.col("widx") + 1).alias("need"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name, words = None, 1
        for b in batches:
            if not b.num_rows:
                continue
            names, need = b.column(0).dictionary_encode(), b.column(1).to_numpy()
            cuts = np.append(np.flatnonzero(np.diff(names.indices.to_numpy(), prepend=-1)), len(need))
            for x, y in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                if b.column(0)[x].as_py() != name:
                    if name is not None:
                        yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([words])], ["set_id", "words"])
                    name, words = b.column(0)[x].as_py(), 1
                while (x := x + int(np.searchsorted(need[x:y], words, side="right"))) < y:
                    words = max(2 * words, int(need[x]))
        if name is not None:
            yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([words])], ["set_id", "words"])

    return needs.repartition("set_id").sortWithinPartitions("set_id", "need").mapInArrow(run, "set_id string, words long")


# -- runs as rows --------------------------------------------------------------------------------------------------


def groups(ids: DataFrame) -> DataFrame:
    """(set_id, g, bits): groups of 31 bits that aren't zero."""
    return ids.groupBy("set_id", F.expr("id div 31").alias("g")).agg(F.expr("bit_or(shiftleft(1L, cast(id % 31 as int)))").alias("bits"))


def islands(ids: DataFrame) -> DataFrame:
    """(set_id, first_group, length, bits, after, next_group, next_bits): runs that aren't zero, with the end of the one before and the start of the next.

    Islands of all-ones groups have a constant difference of group and row number.
    """
    g = groups(ids).withColumn("n", F.row_number().over(W.partitionBy("set_id", "bits").orderBy("g")))
    island = F.when(F.col("bits") == R.ONES, F.col("g") - F.col("n")).otherwise(-1 - F.col("g"))
    ones = g.withColumn("island", island).groupBy("set_id", "bits", "island").agg(F.min("g").alias("first_group"), F.count(F.lit(1)).alias("length")).drop("island")
    w = W.partitionBy("set_id").orderBy("first_group")
    return ones.withColumns({"after": F.coalesce(F.lag(F.col("first_group") + F.col("length")).over(w), F.lit(0)), "next_group": F.lead("first_group").over(w), "next_bits": F.lead("bits").over(w)})


def run_rows(ids: DataFrame) -> DataFrame:
    """(set_id, first_group, length, bits): runs of the set in order, zero runs included, trailing zeros not. Gaps are where the run
    before doesn't end at the next one's start; both come from one pass."""
    one = lambda first, length, bits: F.struct(first.cast("long").alias("first_group"), length.cast("long").alias("length"), bits.cast("long").alias("bits"))
    both = F.array(one(F.col("after"), F.col("first_group") - F.col("after"), F.lit(0)), one(F.col("first_group"), F.col("length"), F.col("bits")))
    return islands(ids).select("set_id", F.explode(both).alias("r")).select("set_id", "r.*").filter("length > 0")


def both_word_counts(ids: DataFrame) -> DataFrame:
    """(set_id, fillrun, posfill): words of the encoded streams, from one list of runs. Position-fill: a literal that differs from the next
    fill in one bit costs nothing."""
    gap = F.col("first_group") - F.col("after")
    cost = lambda length, codec: F.ceil(length / F.lit(R.FILL_MOST[codec]))
    literal = F.col("bits") != R.ONES
    follows = F.when(F.col("next_group") > F.col("first_group") + F.col("length"), F.lit(0)).when(F.col("next_bits") == R.ONES, F.lit(R.ONES))
    folded = F.coalesce(literal & (F.bit_count(F.col("bits").bitwiseXOR(follows.cast("long"))) == 1), F.lit(False))
    per_run = lambda codec: cost(gap, codec) + F.when(literal, 1).otherwise(cost(F.col("length"), codec))
    return islands(ids).groupBy("set_id").agg(F.sum(per_run("fillrun")).cast("long").alias("fillrun"), F.sum(per_run("posfill") - folded.cast("int")).cast("long").alias("posfill"))


def word_counts(ids: DataFrame, codec: str) -> DataFrame:
    """(set_id, words) of the encoded stream."""
    return both_word_counts(ids).select("set_id", F.col(codec).alias("words"))


def run_ids(runs: DataFrame) -> DataFrame:
    """(set_id, id): decodes run rows."""
    rows = runs.filter("bits <> 0").select("set_id", "bits", F.explode(F.sequence(F.col("first_group"), F.col("first_group") + F.col("length") - 1)).alias("g"))
    return rows.select("set_id", "g", "bits", F.explode(F.sequence(F.lit(0), F.lit(30))).alias("b")).filter("shiftright(bits, b) & 1 = 1").select("set_id", (F.col("g") * 31 + F.col("b")).alias("id"))


def run_pairs(ids: DataFrame, pairs: DataFrame, op: str, slab_groups: int = 1 << 7) -> DataFrame:
    """(pair_id, first_group, length, bits): overlapping pieces of two run lists, met slab by slab of the group axis.

    Slabs make the overlap join an equi-join on (pair, slab) and keep a long run list from being one task's work; a run is
    cut at slab ends, which changes no bits. A slab holds at most slab_groups runs of each side.
    """
    r = run_rows(ids).filter("bits <> 0")
    first, last = F.expr(f"first_group div {slab_groups}"), F.expr(f"(first_group + length - 1) div {slab_groups}")
    cut = r.withColumn("slab", F.explode(F.sequence(first, last)))
    cut = cut.withColumns({"a": F.greatest("first_group", F.col("slab") * slab_groups), "b": F.least(F.col("first_group") + F.col("length"), (F.col("slab") + 1) * slab_groups)}).select("set_id", "slab", "a", "b", "bits")
    side = lambda c, s: cut.join(small_side(pairs.select("pair_id", F.col(c).alias("set_id"))), "set_id").select("pair_id", "slab", *[F.col(x).alias(f"{x}{s}") for x in ("a", "b", "bits")])
    x, y = side("left_set", 1), side("right_set", 2)
    if op == "and":
        met = x.join(y, ["pair_id", "slab"]).filter("a1 < b2 and a2 < b1")
        start = F.greatest("a1", "a2")
        return met.select("pair_id", start.alias("first_group"), (F.least("b1", "b2") - start).alias("length"), F.col("bits1").bitwiseAND(F.col("bits2")).alias("bits")).filter("bits <> 0")
    # union: cut both at all ends of the slab, then OR what covers each piece
    either = x.toDF("pair_id", "slab", "a", "b", "bits").union(y.toDF("pair_id", "slab", "a", "b", "bits"))
    ends = either.select("pair_id", "slab", F.explode(F.array("a", "b")).alias("p")).distinct()
    w = W.partitionBy("pair_id", "slab").orderBy("p")
    pieces = ends.withColumn("q", F.lead("p").over(w)).filter("q is not null")
    covered = pieces.join(either, ["pair_id", "slab"]).filter("a <= p and q <= b")
    return covered.groupBy("pair_id", "slab", "p", "q").agg(F.bit_or("bits").alias("bits")).select("pair_id", F.col("p").alias("first_group"), (F.col("q") - F.col("p")).alias("length"), "bits")


# -- streams of words, by the codecs themselves ----------------------------------------------------------------------


def encode_streams(ids: DataFrame, codec: str) -> DataFrame:
    """(set_id, words, stream): one stream a set, made in one task; for sets that fit one (the comparison's)."""

    def run(table: pa.Table) -> pa.Table:
        stream = R.encode(table.column("id").to_numpy(), codec)
        return pa.table({"set_id": table.column("set_id").slice(0, 1), "words": pa.array([len(stream)], pa.int64()), "stream": pa.array([stream.tobytes()], pa.binary())})

    return ids.select("set_id", "id").groupBy("set_id").applyInArrow(run, "set_id string, words long, stream binary")


def decode_streams(streams: DataFrame, codec: str) -> DataFrame:
    def ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, stream in enumerate(b.column("stream")):
                found = R.decode(np.frombuffer(stream.as_buffer(), np.uint32), codec)
                for a in range(0, len(found), 1 << 16):
                    part = pa.array(found[a : a + (1 << 16)])
                    yield pa.RecordBatch.from_arrays([b.column("set_id").take(pa.array(np.full(len(part), i))), part], ["set_id", "id"])

    return streams.select("set_id", "stream").mapInArrow(ids, "set_id string, id long")


def stream_pairs(streams: DataFrame, pairs: DataFrame, codec: str, op: str) -> DataFrame:
    """(pair_id, words_read, words, stream) by two cursors over the words of both streams."""
    side = lambda c: streams.join(small_side(pairs.select("pair_id", F.col(c).alias("set_id"))), "set_id").select("pair_id", F.col("stream").alias(c))

    def work(r: dict):
        out, read = R.combine(np.frombuffer(r["left_set"], np.uint32), np.frombuffer(r["right_set"], np.uint32), codec, op)
        yield r["pair_id"], read, len(out), out.tobytes()

    return kernel(side("left_set").join(side("right_set"), "pair_id"), "pair_id int, words_read long, words long, stream binary", work)


# -- plain Spark, as the reference ---------------------------------------------------------------------------------


def reference_pairs(ids: DataFrame, pairs: DataFrame, op: str) -> DataFrame:
    """(pair_id, id) by hash joins and distinct on the ids themselves."""
    side = lambda c: ids.join(small_side(pairs.select("pair_id", F.col(c).alias("set_id"))), "set_id").select("pair_id", "id").distinct()
    a, b = side("left_set"), side("right_set")
    return {"and": a.intersect, "or": lambda x: a.union(x).distinct(), "andnot": a.subtract}[op](b)


def bits_per_id(words: Column, card: Column, word_bits: int = 32) -> Column:
    return F.round(words * word_bits / card, 6)
