"""Sets of ids to containers and back.

IdSets: (set_id string, id long). Containers: (set_id string, key int or long, kind tinyint, card int, payload binary), one row for each
chunk that a set touches. Ids are unsigned 32-bit unless universe_bits is 64.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from chunkset.functions import containers as C

SCHEMA = "set_id string, key int, kind tinyint, card int, payload binary"


def schema(universe_bits: int = 32) -> str:
    return SCHEMA if universe_bits == 32 else SCHEMA.replace("key int", "key long")


def split_id(ident: Column, universe_bits: int = 32) -> tuple[Column, Column]:
    key = F.shiftright(ident, 16)
    return (key.cast("int") if universe_bits == 32 else key), ident.bitwiseAND(C.CHUNK - 1).cast("int")


def checked(ids: DataFrame, universe_bits: int = 32) -> DataFrame:
    """Raises, when run, on an id outside the universe."""
    bad = (F.col("id") < 0) if universe_bits == 64 else ((F.col("id") < 0) | (F.col("id") >= 1 << 32))
    return ids.withColumn("id", F.when(bad, F.raise_error(F.concat(F.lit("id outside the universe: "), F.col("id").cast("string"))).cast("long")).otherwise(F.col("id")))


def words(ids: DataFrame, universe_bits: int = 32) -> DataFrame:
    """(set_id, key, widx, word): 64 ids a row, by a hash aggregate that combines before the shuffle."""
    key, low = split_id(F.col("id"), universe_bits)
    rows = checked(ids, universe_bits).select("set_id", key.alias("key"), F.shiftright(low, 6).cast("smallint").alias("widx"), F.expr("shiftleft(1L, cast(id & 63 as int))").alias("bit"))
    return rows.groupBy("set_id", "key", "widx").agg(F.bit_or("bit").alias("word"))


def build(ids: DataFrame, universe_bits: int = 32) -> DataFrame:
    """Words of each chunk meet in one task, at most 1,024 of them, and are packed as the kind that their count asks for."""
    rows = words(ids, universe_bits).repartition("set_id", "key").sortWithinPartitions("set_id", "key", "widx")
    return rows.mapInArrow(pack_words, schema(universe_bits))


def build_kernel(ids: DataFrame, universe_bits: int = 32) -> DataFrame:
    """The same by way of the values themselves: a chunk's distinct ids, 65,536 at most, meet in one task in order; many chunks are packed in a call."""
    rows = checked(ids, universe_bits).select("set_id", "id").distinct()
    rows = rows.repartition("set_id", F.shiftright("id", 16)).sortWithinPartitions("set_id", "id")

    def chunk_of(t: pa.Table) -> np.ndarray:
        return t.column(1).to_numpy() >> 16

    def emit(t: pa.Table) -> pa.RecordBatch:
        key = chunk_of(t)
        low = (t.column(1).to_numpy() & (C.CHUNK - 1)).astype(np.uint16)
        cuts = run_starts(name_codes(t), key)
        card = np.diff(cuts)
        kind, values = (card > C.ARRAY_MOST).astype(np.int8), low.tobytes()
        payload = [C.from_values(low[a:b]).payload if dense else values[2 * a : 2 * b] for a, b, dense in zip(cuts[:-1].tolist(), cuts[1:].tolist(), kind.tolist(), strict=True)]
        keys = pa.array(key[cuts[:-1]], pa.int32() if universe_bits == 32 else pa.int64())
        return pa.RecordBatch.from_arrays([t.column(0).combine_chunks().take(pa.array(cuts[:-1])), keys, pa.array(kind), pa.array(card.astype(np.int32)), pa.array(payload, pa.binary())], ["set_id", "key", "kind", "card", "payload"])

    return rows.mapInArrow(lambda batches: whole_chunks(batches, chunk_of, emit), schema(universe_bits))


def run_starts(*cols: np.ndarray) -> np.ndarray:
    n = len(cols[0])
    new = np.zeros(n, bool)
    new[:1] = True
    for c in cols:
        new[1:] |= c[1:] != c[:-1]
    return np.append(np.flatnonzero(new), n)


def name_codes(t: pa.Table) -> np.ndarray:
    """Of the sets in the first column, to be compared with each other."""
    return t.column(0).combine_chunks().dictionary_encode().indices.to_numpy()


def whole_chunks(batches: Iterator[pa.RecordBatch], chunk_of: Callable[[pa.Table], np.ndarray], emit: Callable[[pa.Table], pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """emit of tables that never cut a chunk; batches come sorted by set and chunk."""
    held: list[pa.RecordBatch] = []
    rows = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        rows += batch.num_rows
        if rows >= 1 << 16:
            t = pa.Table.from_batches(held).combine_chunks()
            cut = int(run_starts(name_codes(t), chunk_of(t))[-2])
            if cut:
                yield emit(t.slice(0, cut))
            rest = t.slice(cut)
            held, rows = rest.to_batches(), rest.num_rows
    if rows:
        yield emit(pa.Table.from_batches(held).combine_chunks())


def pack_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def emit(t: pa.Table) -> pa.RecordBatch:
        key = t.column(1).to_numpy()
        cuts = run_starts(name_codes(t), key)
        widx, word = t.column(2).to_numpy().astype(np.int64), t.column(3).to_numpy().view(np.uint64)
        ones = np.bitwise_count(word).astype(np.int64)
        card = np.add.reduceat(ones, cuts[:-1])
        kind, payload = (card > C.ARRAY_MOST).astype(np.int8), []
        bits = np.unpackbits(np.ascontiguousarray(word).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        for a, b, dense in zip(cuts[:-1].tolist(), cuts[1:].tolist(), kind.tolist(), strict=True):
            if dense:
                full = np.zeros(C.WORDS, np.uint64)
                full[widx[a:b]] = word[a:b]
                payload.append(full.tobytes())
            else:
                w, bit = np.nonzero(bits[a:b])
                payload.append((widx[a:b][w] * 64 + bit).astype(np.uint16).tobytes())
        first = pa.array(cuts[:-1])
        return pa.RecordBatch.from_arrays([t.column(0).combine_chunks().take(first), t.column(1).combine_chunks().take(first), pa.array(kind), pa.array(card.astype(np.int32)), pa.array(payload, pa.binary())], ["set_id", "key", "kind", "card", "payload"])

    return whole_chunks(batches, lambda t: t.column(1).to_numpy(), emit)


def build_halves(ids: DataFrame) -> DataFrame:
    """(set_id, key, lower, upper, card): bitmaps of 4,096 bytes from the built-in aggregate, a missing half as zeros."""
    key, low = split_id(F.col("id"))
    rows = ids.select("set_id", key.alias("key"), F.shiftright(low, 15).alias("half"), low.bitwiseAND(32767).alias("at"))
    halves = rows.groupBy("set_id", "key", "half").agg(F.bitmap_construct_agg("at").alias("bits"))
    zero = F.lit(bytes(4096))
    pick = lambda h: F.coalesce(F.max(F.when(F.col("half") == h, F.col("bits"))), zero)
    both = halves.groupBy("set_id", "key").agg(pick(0).alias("lower"), pick(1).alias("upper"))
    return both.withColumn("card", F.bitmap_count("lower") + F.bitmap_count("upper"))


def kernel(rows: DataFrame, out_schema: str, per_row) -> DataFrame:
    """Applies per_row(dict of columns as Python values) -> iterable of output tuples, batch by batch."""
    names = [f.split()[0] for f in out_schema.split(", ")]
    kinds = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "tinyint": pa.int8(), "binary": pa.binary(), "boolean": pa.bool_(), "double": pa.float64()}
    types = [kinds[f.split()[1]] for f in out_schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, 1024):
                batch = whole.slice(i, 1024)
                cols = batch.to_pydict()
                out = [r for values in zip(*cols.values(), strict=True) for r in per_row(dict(zip(cols, values, strict=True)))]
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate(types)], names)

    return rows.mapInArrow(run, out_schema)


def to_ids(containers: DataFrame) -> DataFrame:
    """The inverse of build."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, 256):
                b = whole.slice(i, 256)
                lows = [C.plain_values(C.from_payload(k, p)) for k, p in zip(b.column("kind").to_pylist(), b.column("payload").to_pylist(), strict=True)]
                n = np.array([len(x) for x in lows])
                key = np.repeat(b.column("key").to_numpy().astype(np.int64), n)
                ids = key << 16 | (np.concatenate(lows).astype(np.int64) if len(lows) else np.empty(0, np.int64))
                yield pa.RecordBatch.from_arrays([b.column("set_id").take(pa.array(np.repeat(np.arange(len(n)), n))), pa.array(ids)], ["set_id", "id"])

    return containers.select("set_id", "key", "kind", "payload").mapInArrow(run, "set_id string, id long")


def to_words(containers: DataFrame) -> DataFrame:
    """(set_id, w, word): the containers' words that aren't zero, at w = id >> 6. Up to 64 ids a row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, 256):
                b = whole.slice(i, 256)
                if not b.num_rows:
                    continue
                words = np.stack([C.to_bitmap(C.from_payload(k, p)).data for k, p in zip(b.column("kind").to_pylist(), b.column("payload").to_pylist(), strict=True)])
                row, at = np.nonzero(words)
                w = (b.column("key").to_numpy().astype(np.int64) << 10)[row] + at
                yield pa.RecordBatch.from_arrays([b.column("set_id").take(pa.array(row)), pa.array(w), pa.array(words[row, at].view(np.int64))], ["set_id", "w", "word"])

    return containers.select("set_id", "key", "kind", "payload").mapInArrow(run, "set_id string, w long, word long")


def violations(containers: DataFrame) -> DataFrame:
    """(set_id, key, problem) for rows that break the canonical form; none if all is well."""

    def check(r: dict):
        box = C.from_payload(r["kind"], r["payload"])
        v = C.plain_values(box)
        if r["card"] == 0:
            yield r["set_id"], r["key"], "empty"
        if len(v) != r["card"]:
            yield r["set_id"], r["key"], "count"
        if (r["kind"] == C.BITMAP) != (r["card"] > C.ARRAY_MOST):
            yield r["set_id"], r["key"], "kind"
        if len(r["payload"]) != (2 * r["card"] if r["kind"] == C.ARRAY else 8 * C.WORDS):
            yield r["set_id"], r["key"], "size"
        if r["kind"] == C.ARRAY and (np.diff(box.data.astype(int)) <= 0).any():
            yield r["set_id"], r["key"], "order"

    twice = containers.groupBy("set_id", "key").count().filter("count > 1").select("set_id", F.col("key").cast("int").alias("key"), F.lit("twice").alias("problem"))
    return kernel(containers.select("set_id", "key", "kind", "card", "payload"), "set_id string, key int, problem string", check).union(twice)


def census(containers: DataFrame) -> DataFrame:
    """Per set: arrays, bitmaps, members, payload bytes. The payload itself isn't read."""
    return containers.groupBy("set_id").agg(
        F.sum((F.col("kind") == C.ARRAY).cast("long")).alias("arrays"),
        F.sum((F.col("kind") == C.BITMAP).cast("long")).alias("bitmaps"),
        F.sum("card").alias("card"),
        F.sum(payload_bytes()).alias("payload_bytes"),
    )


def census_of_ids(ids: DataFrame) -> DataFrame:
    """The census of what build would make of the ids, from counts of their words: no container is made."""
    counts = words(ids).groupBy("set_id", "key").agg(F.sum(F.bit_count("word")).cast("long").alias("card"))
    return census(counts.withColumn("kind", F.when(F.col("card") > C.ARRAY_MOST, C.BITMAP).otherwise(C.ARRAY)))


def payload_bytes() -> Column:
    """Of canonical containers, from their counts."""
    return F.when(F.col("card") <= C.ARRAY_MOST, F.col("card").cast("long") * 2).otherwise(F.lit(8 * C.WORDS).cast("long"))


PACKED_MOST = 1 << 16


def pack(containers: DataFrame) -> DataFrame:
    """One row a set, its containers in key order, for sets of at most PACKED_MOST containers (larger ones raise)."""
    rows = containers.groupBy("set_id").agg(F.sum("card").alias("card"), F.sort_array(F.collect_list(F.struct("key", "kind", "card", "payload"))).alias("containers"))
    return rows.withColumn("containers", F.when(F.size("containers") <= PACKED_MOST, F.col("containers")).otherwise(F.raise_error(F.lit("too many containers to pack")).cast(rows.schema["containers"].dataType)))


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("set_id", F.inline("containers"))


def suitability(ids: DataFrame, n: int) -> DataFrame:
    """(set_id, card, dense, moderate, doubtful): which representation a set's density in [0, n) speaks for. Bands may overlap."""
    counts = ids.groupBy("set_id").agg(F.countDistinct("id").alias("card"))
    c = F.col("card")
    return counts.select("set_id", "card", (c * 64 > n).alias("dense"), ((c * 10000 > n) & (c * 64 <= n)).alias("moderate"), (c * 1000 < n).alias("doubtful"))


def with_kinds(containers: DataFrame, kinds: tuple[int, ...]) -> DataFrame:
    """Recodes each container as the smallest of the allowed kinds. The result isn't canonical."""

    def recode(r: dict):
        b = C.smallest(C.from_payload(r["kind"], r["payload"]), kinds)
        yield r["set_id"], r["key"], b.kind, b.card, b.payload

    return kernel(containers.select("set_id", "key", "kind", "card", "payload"), schema(64 if dict(containers.dtypes)["key"] == "bigint" else 32), recode)
