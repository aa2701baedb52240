"""Queries against their SQL on one small scale, and operators on edge cases."""

import glob
import os

import duckdb
import numpy as np
import pytest
from pyspark.errors import PySparkException
from pyspark.sql import functions as F

from chunkset.operators import access, baselines, index, manyway, pairwise
from chunkset.operators import build as B
from chunkset.plans import catalog
from chunkset.sources import tables

SF = "/root/testdata/sf0.01"
CHECKED = """split_ids container_census container_kind_boundary build_halves_card decode_roundtrip first_level_index pack_unpack example_layout toy_and_or
validate_clean extract_bits contains_many add_many remove_many crossing_up crossing_down rank select range_count min_max and_pairs or_pairs andnot_pairs xor_pairs
and_bb or_inplace and_aa_gallop ancestor_convert_after_or and_card jaccard_pairs complement union_all_heap union_all_pairwise union_all_words union_all_builtin intersect_all
threshold_t_of_k plain_and fillrun_words posfill_words fillrun_and posfill_or run_rows_and run_rows_or bits_per_int_table sample_pairs real4_and real5_or
table2_expansion_3 sort_ablation_sizes star_filter predicate_not_null inverted_t_of_k distinct_cube cumulative_users udtf_explode sql_functions stream_tumbling stream_session stream_late stream_containers""".split()


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    c.execute("set TimeZone='UTC'")
    for f in glob.glob(f"{SF}/*.parquet"):
        c.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return c


@pytest.mark.parametrize("name", CHECKED)
def test_against_sql(spark, duck, name):
    df = catalog.QUERIES[name](spark, SF)
    got = sorted(repr(tuple(r[c] for c in sorted(df.columns))) for r in df.collect())
    result = duck.execute(catalog.ORACLES[name])
    cols = [d[0] for d in result.description]
    at = [cols.index(c) for c in sorted(cols)]
    assert sorted(df.columns) == sorted(cols)
    assert got == sorted(repr(tuple(r[i] for i in at)) for r in result.fetchall())


def sets(spark, rows):
    return spark.createDataFrame(rows, "set_id string, id long")


def test_ids_at_the_ends_of_the_universe(spark):
    ids = sets(spark, [("a", x) for x in (0, 65535, 65536, 2**32 - 1)])
    assert {r["id"] for r in B.to_ids(B.build(ids)).collect()} == {0, 65535, 65536, 2**32 - 1}
    for bad in (-1, 2**32):
        with pytest.raises(PySparkException):
            B.build(sets(spark, [("a", bad)])).collect()
    far = sets(spark, [("a", 2**40 + 5)])
    assert B.to_ids(B.build(far, universe_bits=64)).first()["id"] == 2**40 + 5


def test_empty_and_repeated(spark):
    nothing = sets(spark, [])
    assert B.build(nothing).count() == 0
    assert access.cardinality(B.build(sets(spark, [("a", 1), ("a", 1)]))).first()["card"] == 1
    pairs = spark.createDataFrame([(1, "a", "b")], "pair_id int, left_set string, right_set string")
    one = B.build(sets(spark, [("a", 1)]))
    assert pairwise.pair_op(one, pairs, "and").count() == 0
    assert pairwise.pair_op(one, pairs, "or").first()["card"] == 1
    assert pairwise.pair_op(one, pairs, "andnot").first()["card"] == 1


def test_validator_finds_faults(spark):
    rows = [("a", 0, 0, 2, np.array([5, 3], np.uint16).tobytes()), ("b", 0, 1, 1, bytes(8191) + b"\x01"), ("c", 0, 0, 0, b"")]
    bad = spark.createDataFrame(rows, B.SCHEMA)
    assert {(r["set_id"], r["problem"]) for r in B.violations(bad).collect()} == {("a", "order"), ("b", "kind"), ("c", "empty")}


def test_slabs_change_nothing(spark):
    ids = sets(spark, [("a", i) for i in range(5000)] + [("b", i) for i in range(0, 9000, 3)])
    pairs = spark.createDataFrame([(1, "a", "b")], "pair_id int, left_set string, right_set string")
    for op in ("and", "or"):
        counts = {s: baselines.run_pairs(ids, pairs, op, s).agg(F.sum(F.bit_count("bits") * F.col("length"))).first()[0] for s in (3, 64, 4096)}
        assert len(set(counts.values())) == 1


def test_predicates(spark):
    t = spark.range(100).select("id", (F.col("id") % 7).alias("x"), F.when(F.col("id") % 3 > 0, F.col("id") % 5).alias("y"))
    idx = B.build(tables.to_id_sets(t, F.col("id"), {"x": F.col("x"), "y": F.col("y")}))
    p = index.And((index.Between("x", 2, 5), index.Not(index.In("y", (1, 2)))))
    got = sorted(r["id"] for r in index.ids_where(idx, p).collect())
    assert got == [i for i in range(100) if 2 <= i % 7 <= 5 and i % 3 > 0 and i % 5 not in (1, 2)]


def test_folding_early_is_exact(spark):
    rows = [(f"s{i}", (i * 37 + j * 11) % 70_000) for i in range(60) for j in range(40)]
    c = B.build(sets(spark, rows))
    groups = spark.createDataFrame([("g", f"s{i}") for i in range(60)], "group_id string, set_id string")
    got = {r["id"] for r in B.to_ids(manyway.union_all(c, groups)).collect()}
    assert got == {x for _, x in rows}


def test_sources_and_sinks(spark, tmp_path):
    ids = sets(spark, [("x=1", i) for i in range(0, 100_000, 7)] + [("y=2", 5)])
    ids.write.csv(str(tmp_path / "csv"))
    ids.write.json(str(tmp_path / "json"))
    ids.select(F.concat_ws(" ", "set_id", "id")).write.text(str(tmp_path / "text"))
    for fmt in ("csv", "json", "text"):
        assert tables.read_ids(spark, str(tmp_path / fmt), fmt).exceptAll(ids).count() == 0
    tables.write_index(B.build(ids), str(tmp_path / "index"))
    assert B.to_ids(tables.read_index(spark, str(tmp_path / "index"), "x")).count() == 14_286


def test_plans(spark):
    """Counting reads no payloads; words combine before the shuffle; the short side is broadcast."""
    path_plan = catalog.QUERIES["plain_encode_size"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "partial_max" in path_plan
    words = B.words(tables.order_sets(spark, SF))._jdf.queryExecution().executedPlan().toString()
    assert "HashAggregate" in words and "partial_bit_or" in words and "SortAggregate" not in words
