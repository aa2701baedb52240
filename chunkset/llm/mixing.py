"""Mixing sources to target weights, by balanced sampling with the cube method.

A source's target over its size is the mean number of copies of each of its documents: the whole part is taken of
every document, the fraction is an inclusion probability. The flight phase moves these probabilities along the null
space of two constraints, the number of documents and the number of tokens, until at most a dozen of a block are
left undecided; what the blocks leave flies again in fewer blocks, until one block a source is left. Its last
dozen are landed, on the outcome with the smallest error in tokens.

Hot sources are dealt over blocks by a hash of the document. All choices follow from hashes: reruns agree. Null
text and text without words: size 0 (sampled as the others, with nothing to take). A null source is a source of
its own, the last one. Rows that repeat a doc_id are units of their own. Rows that agree in id, source and text can't be told
apart: they are counted, and become units by number, so that no group of them meets in one task. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chunkset.llm.common import WORD_GAP, read, run_starts, saved, small_batches, sorted_runs, tidy

WEIGHTS, SHARE, MOST = (3, 1, 2), 1.5, 2.0
BLOCK_ROWS, HELD, BROADCAST_SOURCES, AT_ONCE = 256, 10, 10_000, 10_000
EPS = 1e-9


def words(text: str = "text") -> Column:
    parts = F.split(F.coalesce(F.col(text), F.lit("")), WORD_GAP)
    empty = F.when(F.element_at(parts, 1) == "", 1).otherwise(0) + F.when((F.size(parts) > 1) & (F.element_at(parts, -1) == ""), 1).otherwise(0)
    return (F.size(parts) - empty).cast("long")


def source_targets(sizes: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """(source, source_size, target, source_no): targets by weight, none above most times its source's size.

    Resharing what is above by weight until nothing is has a closed form: with sources in the order of cap over weight,
    a prefix gets its cap and all others the same amount per weight. One row a source goes through the windows.
    """
    totals = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = W.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int"))
    w = totals.withColumn("weight", weight.cast("double")).withColumn("source_no", F.row_number().over(order).cast("long"))
    w = w.withColumn("cap", F.col("source_size") * F.lit(float(most)))
    by_cap = W.orderBy(F.col("cap") / F.col("weight"), "source_no")
    before, after = by_cap.rowsBetween(W.unboundedPreceding, -1), by_cap.rowsBetween(0, W.unboundedFollowing)
    whole = W.orderBy(F.lit(1)).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    w = w.withColumn("level", (F.sum("source_size").over(whole) * F.lit(share) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after))
    w = w.withColumn("free", F.col("level") * F.col("weight") <= F.col("cap"))
    level = F.first(F.when(F.col("free"), F.col("level")), ignorenulls=True).over(by_cap.rowsBetween(W.unboundedPreceding, W.unboundedFollowing))
    return w.withColumn("target", F.least(F.col("cap"), F.coalesce(level * F.col("weight"), F.col("cap")))).select("source", "source_size", "target", "source_no")


def fly(p: np.ndarray, size: np.ndarray, u: np.ndarray, land: bool) -> np.ndarray:
    """Moves the probabilities p of one block, keeping sum(p) and sum(p * size).

    HELD units stay out of the flight and at most two of the others stay fractional; if land, these together get the
    outcome that is nearest in tokens.
    """
    p = p.tolist()
    z = size.tolist()
    free = sorted((i for i, x in enumerate(p) if EPS < x < 1 - EPS), key=lambda i: (z[i], i))
    held = free[:: max(1, len(free) // HELD)][-HELD:]  # of every size, so that what remains can make up any sum
    free = [i for i in free if i not in set(held)]  # the largest fly first
    active: list[int] = []
    draws = iter(u.tolist() * 2)
    while True:
        while len(active) < 3 and free:
            active.append(free.pop())
        if len(active) < 3:
            break
        a, b, c = active
        va, vb, vc = z[c] - z[b], z[a] - z[c], z[b] - z[a]
        if not (va or vb or vc):
            va, vb, vc = 1, -1, 0
        up = down = float("inf")
        for i, v in ((a, va), (b, vb), (c, vc)):
            if v > 0:
                up, down = min(up, (1 - p[i]) / v), min(down, p[i] / v)
            elif v < 0:
                up, down = min(up, p[i] / -v), min(down, (1 - p[i]) / -v)
        step = up if next(draws, 0.5) * (up + down) < down else -down
        for i, v in ((a, va), (b, vb), (c, vc)):
            x = p[i] + step * v
            p[i] = 0.0 if x < EPS else 1.0 if x > 1 - EPS else x
        active = [i for i in active if 0 < p[i] < 1]
    if land and (last := active + held):
        z_last, p_last = np.array([z[i] for i in last], float), np.array([p[i] for i in last])
        outcomes = np.arange(1 << len(last))[:, None] >> np.arange(len(last)) & 1
        error = np.abs(outcomes @ z_last - p_last @ z_last) + 1e-6 * np.abs(outcomes.sum(1) - p_last.sum())
        for i, x in zip(last, outcomes[int(error.argmin())].tolist(), strict=True):
            p[i] = float(x)
    return np.array(p)


def flight(units: DataFrame, land: bool) -> DataFrame:
    """Units (source_no, block, unit, row_key, doc_id, size, base, p) with p moved, block by block."""
    kept = ["source_no", "unit", "row_key", "doc_id", "size", "base"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in sorted_runs(batches, ["source_no", "block"]):
            source, block, p, size, u = (t.column(c).to_numpy() for c in ("source_no", "block", "p", "size", "u"))
            new = np.empty(len(p))
            cuts = run_starts(source, block)
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                new[a:b] = fly(p[a:b], size[a:b], u[a:b], land)
            yield from t.select(kept).append_column("p", pa.array(new)).to_batches()

    keyed = units.withColumn("u", F.pmod(F.xxhash64("unit", F.lit(7)), F.lit(1 << 30)) / F.lit(float(1 << 30)))
    dealt = keyed.repartition("source_no", "block").sortWithinPartitions("source_no", "block", "unit", "size")
    return dealt.select(*kept, "block", "p", "u").mapInArrow(tidy(run), "source_no long, unit long, row_key struct<a:bigint,b:bigint>, doc_id long, size long, base long, p double")


def in_blocks(units: DataFrame, level: int, counts: DataFrame) -> DataFrame:
    blocks = F.greatest(F.lit(1), F.ceil(F.col("units") / F.lit(BLOCK_ROWS)))
    few = counts.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    dealt = units.join(F.broadcast(counts) if few else counts, "source_no")
    return dealt.withColumn("block", F.pmod(F.xxhash64("unit", F.lit(level)), blocks).cast("long")).drop("units")


def row_key() -> Column:
    """128 bits of a row's doc_id, source and text."""
    row = ["doc_id", "source", "text"]
    nulls = [F.col(c).isNull() for c in row]
    return F.struct(F.xxhash64(*row, *nulls).alias("a"), F.xxhash64(F.lit(1), *nulls, *reversed(row)).alias("b"))


def numbered(rows: DataFrame, count: str) -> DataFrame:
    """Each row as often as its count says, with its number; large counts are first cut into pieces that go to different tasks."""
    pieces = rows.withColumn("piece", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col(count) - 1) / AT_ONCE))))
    large = pieces.filter(F.col(count) > AT_ONCE).repartition("row_key", "piece")
    first = F.col("piece") * AT_ONCE
    number = F.explode(F.sequence(first, F.least(first + AT_ONCE, F.col(count)) - 1))
    return pieces.filter(F.col(count) <= AT_ONCE).unionByName(large).withColumn("number", number).drop("piece", count)


def mix(docs: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """(doc_id, size, source_size, target, copies, taken, row_key) for each row of (doc_id, source, text)."""
    sizes = small_batches(docs).select(F.col("doc_id").cast("long").alias("doc_id"), "source", words().alias("size"), row_key().alias("row_key"))
    sizes = saved(sizes.groupBy("row_key", "doc_id", "source", "size").agg(F.count(F.lit(1)).alias("alike")), "sizes")
    targets = saved(source_targets(sizes.select("source", (F.col("size") * F.col("alike")).alias("size")), weights, share, most), "targets")
    few = targets.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    t = targets.withColumnRenamed("source", "of")
    units = sizes.join(F.broadcast(t) if few else t, F.col("source").eqNullSafe(F.col("of")))
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    whole = F.floor(ratio + F.lit(EPS))
    units = units.select("source_no", "row_key", "doc_id", "size", "alike", whole.cast("long").alias("base"), F.greatest(F.lit(0.0), ratio - whole).alias("p"))
    units = numbered(units, "alike").withColumn("unit", F.xxhash64("row_key", "number")).drop("number")
    fractional = (F.col("p") > EPS) & (F.col("p") < 1 - EPS)
    decided = [units.filter(~fractional)]
    left, level = units.filter(fractional), 0
    while True:
        counts = saved(left.groupBy("source_no").agg(F.count(F.lit(1)).alias("units")), "unit-counts")
        most_units = counts.agg(F.max("units")).first()[0] or 0
        land = most_units <= BLOCK_ROWS
        flown = saved(flight(in_blocks(left, level, counts), land), "flight")
        decided.append(flown if land else flown.filter(~fractional))
        if land:
            break
        left, level = flown.filter(fractional), level + 1
    rows = decided[0]
    for d in decided[1:]:
        rows = rows.unionByName(d)
    copies = (F.col("base") + F.round("p")).cast("long")
    t = targets.select("source_no", "source_size", "target")
    return rows.join(F.broadcast(t) if few else t, "source_no").select("doc_id", "size", "source_size", "target", copies.alias("copies"), (F.col("size") * copies).alias("taken"), "row_key")


def mixed_rows(docs: DataFrame) -> DataFrame:
    """The mix itself: every row of docs as often as it is taken, with docs' columns.

    Of rows that can't be told apart each comes as often as the least taken of them, and one stands for what the others are taken beyond that.
    """
    picks = mix(docs.select("doc_id", "source", "text")).groupBy("row_key").agg(F.min("copies").alias("least"), F.sum("copies").alias("total"), F.count(F.lit(1)).alias("alike"))
    picks = saved(picks.select("row_key", "least", (F.col("total") - F.col("least") * F.col("alike")).alias("extra")), "picks")
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), row_key().alias("row_key"))
    out = keyed.join(picks.filter("least > 0").select("row_key", "least"), "row_key").select("row", F.explode(F.sequence(F.lit(1).cast("long"), F.col("least")))).select("row")
    beyond = picks.filter("extra > 0").select("row_key", "extra")
    if not beyond.isEmpty():
        one = keyed.join(beyond, "row_key").groupBy("row_key").agg(F.first("row").alias("row"), F.first("extra").alias("extra"))
        out = out.unionByName(numbered(one, "extra").select("row"))
    return out.select("row.*")


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(read(spark, sf_dir, "documents").select("doc_id", "source", "text")).drop("row_key")
