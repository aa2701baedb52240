"""Queries on tables larger or more uniform than the given ones."""

import datetime

import pytest
from pyspark.sql import functions as F

from chunkset.operators import build as B
from chunkset.plans import catalog


def test_probes_reach_the_last_id(spark, tmp_path):
    day = datetime.date(1995, 1, 1)
    keys = [0, 37 * 5, 300_000, 37 * 10_000, 37 * 10**7]
    rows = [(k, line, 1, 1, 1.0, 10.0, 0.05, 0.0, "A", "F", day) for k in keys for line in range(1, 8)]
    columns = "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate date"
    spark.createDataFrame(rows, columns).write.parquet(f"{tmp_path}/lineitem.parquet")
    ids = {r[0] * 8 + r[1] for r in rows}
    want = {(s, i) for s in catalog.ACCESS for i in ids if i % 37 == 5}
    assert max(i for _, i in want) > 1 << 21
    got = [tuple(r) for r in catalog.contains_many(spark, str(tmp_path)).select("set_id", "id").collect()]
    assert len(got) == len(want) and set(got) == want


def test_top_sets_keeps_all_ties(spark, tmp_path):
    text = " ".join(f"w{i}" for i in range(1500))
    spark.createDataFrame([(1, text), (2, "w0 w1")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["set_id"]: (r["card"], r["rk"]) for r in catalog.top_sets(spark, str(tmp_path)).collect()}
    assert got == {f"w{i}": (2, 1) if i < 2 else (1, 3) for i in range(1500)}


def test_values_are_packed_many_chunks_a_call(spark):
    n = 70_000  # more values than a call holds: chunks are cut by no call
    ids = spark.range(n).select(F.concat(F.lit("s"), (F.col("id") % 9_000).cast("string")).alias("set_id"), (F.col("id") * 40).alias("id"))
    ids = ids.union(spark.range(n).select(F.lit("dense"), F.col("id"))).union(spark.createDataFrame([("dense", 7), ("dense", 7), ("end", 2**32 - 1)], ids.schema))
    made = B.build_kernel(ids)
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "FlatMapGroups" not in plan
    columns = ["set_id", "key", "kind", "card", "payload"]
    rows = lambda df: sorted(tuple(r) for r in df.select(*columns).collect())
    got = rows(made)
    assert got == rows(B.build(ids)) and len({(r[0], r[1]) for r in got}) == len(got)


#: What follows from 140,000 line items and 210,000 orders: the distinct values of a column, or a number of rows that its values add up to.
MOVED = {
    "container_kind_boundary": lambda rows: sorted(r["card"] for r in rows) == sorted(min(n, m) for n in catalog.BOUNDARIES for m in (65536, 65536, 8928)),
    "crossing_down": lambda rows: sorted((r["key"], r["kind"], r["card"]) for r in rows) == [(k, 0, 4096) for k in range(3)],
    "crossing_up": lambda rows: sorted((r["key"], r["kind"], r["card"]) for r in rows) == [(0, 1, 4097), (1, 1, 4097), (2, 0, 4096)],
    "example_decode_sum": lambda rows: rows[0]["members"] == 140_000,
    "example_layout": lambda rows: [r["card"] for r in sorted(rows, key=lambda r: r["key"])] == [1000, 100, 32768] * 4 + [1000, 100, 3428],
    "period_sizes": lambda rows: [r["card"] for r in rows] == [210_000, 210_000],
    "syn_and": lambda rows: {int(r["pair"]) for r in rows} == {part * 16 + e for part in range(3) for e in (1, 4, 6)},
    "syn_beta_sizes": lambda rows: len(rows) == 24 and max(r["card"] for r in rows) <= 70_000,
    "syn_or": lambda rows: {int(r["pair"]) for r in rows} == {part * 16 + e for part in range(3) for e in (1, 4, 6)},
    "syn_uniform_sizes": lambda rows: len(rows) == 24 and max(r["card"] for r in rows) <= 70_000,
    "toy_and_or": lambda rows: len(rows) == len(set(rows)) == 210_000 // 8 * 6,
}


@pytest.mark.parametrize("name", MOVED)
def test_rows_come_from_the_table(spark, tmp_path, name):
    spark.range(140_000).select((F.col("id") * 3).alias("l_orderkey")).write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.range(210_000).select(F.col("id").alias("o_orderkey")).write.parquet(f"{tmp_path}/orders.parquet")
    assert MOVED[name](catalog.QUERIES[name](spark, str(tmp_path)).collect())
