"""SQL functions over containers: scalar ones, aggregates, and a table function. register(spark) names them all."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, udtf
from pyspark.sql.types import ArrayType, StructField, StructType, BinaryType, BooleanType, IntegerType, LongType, ByteType

from chunkset.functions import containers as C

BOX = StructType([StructField("kind", ByteType()), StructField("card", IntegerType()), StructField("payload", BinaryType())])


def boxes(kind: pa.Array, payload: pa.Array) -> Iterator[C.Box | None]:
    for k, p in zip(kind.to_pylist(), payload.to_pylist(), strict=True):
        yield None if p is None else C.from_payload(k, p)


def as_struct(found: list[C.Box | None]) -> pa.Array:
    return pa.array([None if b is None else {"kind": b.kind, "card": b.card, "payload": b.payload} for b in found], pa.struct([("kind", pa.int8()), ("card", pa.int32()), ("payload", pa.binary())]))


def on_two(op):
    """Of two containers; a null operand counts as the empty set."""

    def f(k1: pa.Array, p1: pa.Array, k2: pa.Array, p2: pa.Array) -> pa.Array:
        empty = C.array_box([])
        return as_struct([op(a or empty, b or empty) for a, b in zip(boxes(k1, p1), boxes(k2, p2), strict=True)])

    return arrow_udf(f, BOX)


@arrow_udf(BooleanType())
def hb_contains(kind: pa.Array, payload: pa.Array, low: pa.Array) -> pa.Array:
    return pa.array([None if b is None or x is None else C.contains(b, x) for b, x in zip(boxes(kind, payload), low.to_pylist(), strict=True)], pa.bool_())


@arrow_udf(IntegerType())
def hb_card(kind: pa.Array, payload: pa.Array) -> pa.Array:
    return pa.array([None if b is None else C.canonical(b).card for b in boxes(kind, payload)], pa.int32())


@arrow_udf(IntegerType())
def hb_rank(kind: pa.Array, payload: pa.Array, low: pa.Array) -> pa.Array:
    return pa.array([None if b is None or x is None else C.rank(b, x) for b, x in zip(boxes(kind, payload), low.to_pylist(), strict=True)], pa.int32())


@arrow_udf(IntegerType())
def hb_select(kind: pa.Array, payload: pa.Array, j: pa.Array) -> pa.Array:
    return pa.array([None if b is None or x is None else C.select(b, x) for b, x in zip(boxes(kind, payload), j.to_pylist(), strict=True)], pa.int32())


@arrow_udf(ArrayType(IntegerType()))
def hb_lowest_bits(word: pa.Array) -> pa.Array:
    return pa.array([None if w is None else C.lowest_bits(w & (1 << 64) - 1) for w in word.to_pylist()], pa.list_(pa.int32()))


@arrow_udf(LongType())
def hb_union_card(kind: pa.Array, payload: pa.Array) -> int:
    """Aggregate: the size of the union of a group's containers of one key."""
    return C.union_many(list(boxes(kind, payload))).card if len(kind) else 0


@arrow_udf(LongType())
def hb_intersect_card(kind: pa.Array, payload: pa.Array) -> int:
    return C.intersect_many(list(boxes(kind, payload))).card if len(kind) else 0


@udtf(returnType="id long")
class HbExplode:
    """The ids of a container."""

    def eval(self, key: int, kind: int, payload: bytes):
        if payload is not None:
            for x in C.plain_values(C.from_payload(kind, bytes(payload))).tolist():
                yield ((key << 16) + x,)


def register(spark: SparkSession) -> None:
    scalar = {"hb_contains": hb_contains, "hb_card": hb_card, "hb_rank": hb_rank, "hb_select": hb_select, "hb_lowest_bits": hb_lowest_bits, "hb_union_card": hb_union_card, "hb_intersect_card": hb_intersect_card}
    for name, f in scalar.items():
        spark.udf.register(name, f)
    for name, op in (("hb_and", C.intersection), ("hb_or", C.union), ("hb_andnot", C.difference), ("hb_xor", C.symmetric_difference)):
        spark.udf.register(name, on_two(op))
    spark.udtf.register("hb_explode", HbExplode)
