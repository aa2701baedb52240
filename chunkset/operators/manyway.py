"""Operations on many sets at once: union in four strategies, intersection, and threshold queries."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chunkset.functions import containers as C
from chunkset.operators.build import SCHEMA, build, to_ids, words
from chunkset.sources.storage import small_side


def members(containers: DataFrame, groups: DataFrame) -> DataFrame:
    """Containers with the group (group_id, set_id) that each set belongs to, in place of the set's name."""
    return containers.join(small_side(groups), "set_id").withColumn("set_id", F.col("group_id").cast("string")).drop("group_id")


def partial(rows: DataFrame, fold, most: int = 256) -> DataFrame:
    """Folds the containers that a task holds by (group, key) into one each; memory is bounded by folding early. fold: list of Box -> Box."""

    def batch(held: dict) -> pa.RecordBatch:
        out = [(s, k, (box := boxes[0] if len(boxes) == 1 else fold(boxes)).kind, box.card, box.payload) for (s, k), boxes in held.items()]
        return pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], t) for i, t in enumerate((pa.string(), pa.int32(), pa.int8(), pa.int32(), pa.binary()))], ["set_id", "key", "kind", "card", "payload"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[str, int], list[C.Box]] = {}
        size = 0
        for b in batches:
            for s, key, kind, card, payload in zip(*(b.column(c).to_pylist() for c in ("set_id", "key", "kind", "card", "payload")), strict=True):
                boxes = held.setdefault((s, key), [])
                boxes.append(C.from_payload(kind, payload, card))
                size += 1
                if len(boxes) >= most:
                    size -= len(boxes) - 1
                    held[s, key] = [fold(boxes)]
            if size > 8192:
                yield batch(held)
                held, size = {}, 0
        if held:
            yield batch(held)

    return rows.select("set_id", "key", "kind", "card", "payload").mapInArrow(run, SCHEMA)


def by_key(rows: DataFrame, fold) -> DataFrame:
    """All containers of a (group, key) in one task; fold: list of Box -> Box."""

    def run(table: pa.Table) -> pa.Table:
        boxes = [C.from_payload(k, p, c) for k, p, c in zip(table.column("kind").to_pylist(), table.column("payload").to_pylist(), table.column("card").to_pylist(), strict=True)]
        out = fold(boxes)
        kept = [(table.column("set_id")[0].as_py(), table.column("key")[0].as_py(), out.kind, out.card, out.payload)] if out.card else []
        return pa.Table.from_arrays([pa.array([o[i] for o in kept], t) for i, t in enumerate((pa.string(), pa.int32(), pa.int8(), pa.int32(), pa.binary()))], names=["set_id", "key", "kind", "card", "payload"])

    return rows.select("set_id", "key", "kind", "card", "payload").groupBy("set_id", "key").applyInArrow(run, SCHEMA)


def union_all(containers: DataFrame, groups: DataFrame, strategy: str = "buffer") -> DataFrame:
    """Containers of each group's union.

    buffer: containers of a key meet by a shuffle, after each task has folded its own, and are folded largest first into one
    buffer, counted once. pairwise: one after the other, counted each time. words: bits of all members through the hash
    aggregate. builtin: halves through the built-in bitmap aggregates.
    """
    rows = members(containers, groups)
    if strategy == "buffer":
        return by_key(partial(rows, C.union_many), C.union_many)
    if strategy == "pairwise":
        return by_key(rows, C.union_pairwise)
    if strategy == "words":
        return build(to_ids(rows))
    ids = to_ids(rows)
    low = F.col("id").bitwiseAND(C.CHUNK - 1).cast("int")
    halves = ids.groupBy("set_id", F.shiftright("id", 16).cast("int").alias("key"), F.shiftright(low, 15).alias("half")).agg(F.bitmap_construct_agg(low.bitwiseAND(32767)).alias("bits"))
    merged = halves.groupBy("set_id", "key", "half").agg(F.bitmap_or_agg("bits").alias("bits"))
    zero = F.lit(bytes(4096))
    both = merged.groupBy("set_id", "key").agg(*[F.coalesce(F.max(F.when(F.col("half") == h, F.col("bits"))), zero).alias(n) for h, n in ((0, "a"), (1, "b"))])
    return by_key(both.select("set_id", "key", F.lit(1).cast("tinyint").alias("kind"), (F.bitmap_count("a") + F.bitmap_count("b")).cast("int").alias("card"), F.concat("a", "b").alias("payload")), lambda boxes: C.canonical(boxes[0]))


def intersect_all(containers: DataFrame, groups: DataFrame) -> DataFrame:
    """Only keys that all members of a group have are read; each task intersects what it holds, an empty result included, then what is left
    meets, smallest first."""
    rows = members(containers, groups)
    sizes = groups.groupBy(F.col("group_id").cast("string").alias("set_id")).agg(F.countDistinct("set_id").alias("members"))
    keys = rows.groupBy("set_id", "key").agg(F.count(F.lit(1)).alias("n")).join(small_side(sizes), "set_id").filter("n = members").select("set_id", "key")
    return by_key(partial(rows.join(keys, ["set_id", "key"], "left_semi"), C.intersect_many), C.intersect_many)


def threshold(containers: DataFrame, groups: DataFrame, t: int, strategy: str = "counters") -> DataFrame:
    """(set_id, id): ids that t members or more of a group hold. counters: per chunk, added up in each task first; rows: through the ids."""
    rows = members(containers, groups)
    if strategy != "counters":
        return to_ids(rows).groupBy("set_id", "id").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= t).select("set_id", "id")

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[str, int], np.ndarray] = {}
        for b in batches:
            for s, key, kind, payload in zip(*(b.column(c).to_pylist() for c in ("set_id", "key", "kind", "payload")), strict=True):
                counts = held.setdefault((s, key), np.zeros(C.CHUNK, np.int32))
                counts[C.plain_values(C.from_payload(kind, payload))] += 1
                if len(held) >= 256:  # of 256 kB each
                    yield counters(held)
                    held = {}
        if held:
            yield counters(held)

    def counters(held: dict) -> pa.RecordBatch:
        at = [np.flatnonzero(c) for c in held.values()]
        payload = [a.astype(np.uint16).tobytes() + c[a].tobytes() for a, c in zip(at, held.values(), strict=True)]
        return pa.RecordBatch.from_arrays([pa.array([s for s, _ in held]), pa.array([k for _, k in held], pa.int32()), pa.array(payload, pa.binary())], ["set_id", "key", "counts"])

    def added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name, total = None, np.zeros(C.CHUNK, np.int64)

        def ids() -> Iterator[pa.RecordBatch]:
            found = np.flatnonzero(total >= t) + (name[1] << 16)
            if len(found):
                yield pa.RecordBatch.from_arrays([pa.array([name[0]]).take(pa.array(np.zeros(len(found), np.int64))), pa.array(found)], ["set_id", "id"])

        for b in batches:
            for s, key, counts in zip(*(b.column(c).to_pylist() for c in ("set_id", "key", "counts")), strict=True):
                if (s, key) != name:
                    if name:
                        yield from ids()
                    name, total[:] = (s, key), 0
                n = len(counts) // 6
                total[np.frombuffer(counts, np.uint16, n)] += np.frombuffer(counts[2 * n :], np.int32)
        if name:
            yield from ids()

    sums = rows.select("set_id", "key", "kind", "payload").mapInArrow(counted, "set_id string, key int, counts binary")
    return sums.repartition("set_id", "key").sortWithinPartitions("set_id", "key").mapInArrow(added, "set_id string, id long")


def word_aggregate(ids: DataFrame) -> DataFrame:
    """(set_id, any, all, odd, ones): popcounts of the OR, AND and XOR of each set's words, and of the words themselves."""
    w = words(ids)
    return w.groupBy("set_id").agg(F.bit_count(F.bit_or("word")).alias("any_bits"), F.bit_count(F.bit_and("word")).alias("all_bits"), F.bit_count(F.bit_xor("word")).alias("odd_bits"), F.sum(F.bit_count("word")).alias("ones"))
