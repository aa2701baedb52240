"""Operations on pairs of sets: containers meet by an equi-join on (pair, key), and a kernel works on each two that meet."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chunkset.functions import batch as K
from chunkset.functions import containers as C
from chunkset.operators.build import kernel, to_words
from chunkset.sources.storage import small_side

JOIN = {"and": "inner", "or": "full_outer", "xor": "full_outer", "andnot": "left"}
OUT = "set_id string, key int, kind tinyint, card int, payload binary"


def bind(containers: DataFrame, pairs: DataFrame, side: str) -> DataFrame:
    """(pair, key, kind_, card_, payload_): the containers of one side of each pair. The pair list is broadcast while it is short."""
    named = small_side(pairs.select(F.col("pair_id").cast("string").alias("pair"), F.col(side).alias("set_id")))
    return containers.join(named, "set_id").select("pair", "key", *[F.col(c).alias(f"{c}_{side[0]}") for c in ("kind", "card", "payload")])


def align(left: DataFrame, right: DataFrame, op: str, hint: str | None = None) -> DataFrame:
    right = right.hint(hint) if hint else right
    return left.join(right, ["pair", "key"], JOIN[op])


def apply(aligned: DataFrame, op: str, inplace: bool = False, predict: bool = True, method: str = "auto") -> DataFrame:
    """Containers of the results, named by pair; empty ones are dropped. A container alone passes as it is (or, XOR, AND NOT).

    AND and OR work off whole batches at once; in place, and for XOR and AND NOT, one pair of containers after the other.
    """
    rows = aligned.select("pair", "key", "kind_l", "card_l", "payload_l", "kind_r", "card_r", "payload_r")
    if op in ("and", "or") and not inplace:
        return rows.mapInArrow(by_batch(lambda a, b: K.intersection(a, b, method) if op == "and" else K.union(a, b, predict)), OUT)

    def work(r: dict):
        a = None if r["payload_l"] is None else C.from_payload(r["kind_l"], r["payload_l"], r["card_l"])
        b = None if r["payload_r"] is None else C.from_payload(r["kind_r"], r["payload_r"], r["card_r"])
        if a is None or b is None:
            out = a or b
        elif op == "or":
            if (a.kind, b.kind) != (C.ARRAY, C.ARRAY):
                if a.kind != C.BITMAP:
                    a, b = b, a
                a = C.Box(a.kind, a.card, a.data.copy())  # the one buffer that the operation then overwrites
            out = C.union(a, b, inplace=a.kind == C.BITMAP, predict=predict)
        elif op == "and":
            if a.kind == b.kind == C.BITMAP:
                a = C.Box(a.kind, a.card, a.data.copy())
            out = C.intersection(a, b, inplace=a.kind == b.kind == C.BITMAP, method=method)
        else:
            out = C.OPERATIONS[op](a, b)
        if out.card:
            yield r["pair"], r["key"], out.kind, out.card, out.payload

    return kernel(rows, OUT, work)


NAMES = ["set_id", "key", "kind", "card", "payload"]


def by_batch(op):
    """mapInArrow function over aligned rows; op: two Stacks -> Stack. Containers of other kinds than array and bitmap are made canonical first."""

    def plain(kind: pa.Array, payload: pa.Array) -> K.Stack:
        if (pc.max(kind).as_py() or 0) > C.BITMAP:
            boxes = [C.canonical(C.from_payload(k, p)) for k, p in zip(kind.to_pylist(), payload.to_pylist(), strict=True)]
            kind, payload = pa.array([b.kind for b in boxes], pa.int8()), pa.array([b.payload for b in boxes], pa.binary())
        return K.from_column(kind, payload)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, 512):
                b = whole.slice(i, 512)
                left, right = (b.column(f"payload_{s}").is_valid() for s in "lr")
                both = b.filter(pc.and_(left, right))
                if both.num_rows:
                    out = op(*(plain(both.column(f"kind_{s}"), both.column(f"payload_{s}")) for s in "lr"))
                    some = np.flatnonzero(out.card)
                    out, at = out.take(some), pa.array(some)
                    yield pa.RecordBatch.from_arrays([both.column("pair").take(at), both.column("key").take(at), pa.array(out.kind), pa.array(out.card.astype(np.int32)), out.payloads()], NAMES)
                for side, other in (("l", right), ("r", left)):
                    alone = b.filter(pc.invert(other))
                    if alone.num_rows:
                        yield pa.RecordBatch.from_arrays([alone.column("pair"), alone.column("key"), *[alone.column(f"{c}_{side}") for c in ("kind", "card", "payload")]], NAMES)

    return run


def pair_op(containers: DataFrame, pairs: DataFrame, op: str, hint: str | None = None, prune: bool = False, **how) -> DataFrame:
    """Containers of op on each pair (pair_id, left_set, right_set); set_id is the pair's id.

    prune, for AND on stored containers: keys meet first, without payloads, and only containers whose key both sides have are
    joined. Worth its extra pass over keys where most chunks of a side have no partner.
    """
    left, right = bind(containers, pairs.withColumnRenamed("left_set", "left"), "left"), bind(containers, pairs.withColumnRenamed("right_set", "right"), "right")
    if prune and op == "and":
        keys = small_side(left.select("pair", "key").join(right.select("pair", "key"), ["pair", "key"]))
        left, right = (side.join(keys, ["pair", "key"], "left_semi") for side in (left, right))
    return apply(align(left, right, op, hint), op, **how)


def same_sets(left: DataFrame, right: DataFrame, op: str) -> DataFrame:
    """op between the sets of the same name in two container tables."""
    named = lambda df, s: df.select(F.col("set_id").alias("pair"), "key", *[F.col(c).alias(f"{c}_{s}") for c in ("kind", "card", "payload")])
    return apply(align(named(left, "l"), named(right, "r"), op), op)


def union_pairs(containers: DataFrame, pairs: DataFrame, **how) -> DataFrame:
    return pair_op(containers, pairs, "or", **how)


def intersect_pairs(containers: DataFrame, pairs: DataFrame, **how) -> DataFrame:
    return pair_op(containers, pairs, "and", **how)


def shared(containers: DataFrame, pairs: DataFrame) -> DataFrame:
    """(pair_id, shared): sizes of the intersections; no result container is written."""
    left, right = bind(containers, pairs.withColumnRenamed("left_set", "left"), "left"), bind(containers, pairs.withColumnRenamed("right_set", "right"), "right")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, 512):
                b = whole.slice(i, 512)
                if b.num_rows:
                    n = K.shared_counts(*(K.from_column(b.column(f"kind_{s}"), b.column(f"payload_{s}")) for s in "lr"))
                    yield pa.RecordBatch.from_arrays([b.column("pair"), pa.array(n)], ["pair", "n"])

    met = align(left, right, "and").select("pair", "kind_l", "payload_l", "kind_r", "payload_r")
    counted = met.mapInArrow(count, "pair string, n long").groupBy("pair").agg(F.sum("n").alias("n"))
    named = pairs.select("pair_id", F.col("pair_id").cast("string").alias("pair"))
    return named.join(counted, "pair", "left").select("pair_id", F.coalesce("n", F.lit(0)).alias("shared"))


def pair_counts(containers: DataFrame, pairs: DataFrame) -> DataFrame:
    """(pair_id, card_left, card_right, card_and, card_or, subset, equal, disjoint, jaccard_ppm), all from counts."""
    cards = containers.groupBy("set_id").agg(F.sum("card").alias("card"))
    one = lambda s: cards.select(F.col("set_id").alias(f"{s}_set"), F.col("card").alias(f"card_{s}"))
    both = pairs.join(one("left"), "left_set", "left").join(one("right"), "right_set", "left").join(shared(containers, pairs), "pair_id")
    left, right = F.coalesce("card_left", F.lit(0)), F.coalesce("card_right", F.lit(0))
    both = both.select("pair_id", left.alias("card_left"), right.alias("card_right"), F.col("shared").alias("card_and"), (left + right - F.col("shared")).alias("card_or"))
    return both.withColumns({"subset": F.col("card_and") == F.col("card_left"), "equal": F.col("card_or") == F.col("card_and"), "disjoint": F.col("card_and") == 0, "jaccard_ppm": F.expr("cast(card_and * 1000000 div greatest(card_or, 1) as bigint)")})


def complement(containers: DataFrame, n: int) -> DataFrame:
    """What each set lacks of [0, n). Chunks that a set doesn't touch are whole."""
    keys = containers.select("set_id").distinct().select("set_id", F.explode(F.slice(F.sequence(F.lit(0), F.lit(n >> 16)), 1, -(-n // C.CHUNK))).alias("key"))
    rows = keys.join(containers, ["set_id", "key"], "left")

    def flip(r: dict):
        size = min(C.CHUNK, n - (r["key"] << 16))
        box = C.array_box([]) if r["payload"] is None else C.from_payload(r["kind"], r["payload"], r["card"])
        out = C.flipped(box, size)
        if out.card:
            yield r["set_id"], r["key"], out.kind, out.card, out.payload

    return kernel(rows.select("set_id", "key", "kind", "card", "payload"), OUT, flip)


def held(table: DataFrame, id_col: str, containers: DataFrame, how: str) -> DataFrame:
    """Rows meet the sets' words by an equi-join on id >> 6, and their bit is tested: up to 64 ids a joined row, none decoded."""
    words = to_words(containers).groupBy(F.col("w").alias("_w")).agg(F.bit_or("word").alias("_word"))
    ident = F.col(id_col).cast("long")
    bit = F.col("_word").bitwiseAND(F.expr(f"shiftleft(1L, cast(`{id_col}` & 63 as int))"))
    return table.join(words, (F.shiftright(ident, 6) == F.col("_w")) & (bit != 0), how)


def rows_in(table: DataFrame, id_col: str, containers: DataFrame) -> DataFrame:
    """The rows of table whose id is in any of the sets. table must not have columns _w and _word."""
    return held(table, id_col, containers, "left_semi")


def rows_not_in(table: DataFrame, id_col: str, containers: DataFrame) -> DataFrame:
    return held(table, id_col, containers, "left_anti")
