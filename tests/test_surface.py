"""Sets that change, packed arrays, the fold's invariant, sources and sinks, membership without decoding, partial folds."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from chunkset.functions import containers as C
from chunkset.functions import runs as R
from chunkset.operators import access, build, manyway, pairwise
from chunkset.sources import tables
from chunkset.streaming import users


@pytest.mark.parametrize("seed", range(3))
def test_sets_that_change(seed):
    r = random.Random(seed)
    start = np.unique(np.random.default_rng(seed).integers(0, 1 << 18, (100, 9000, 60_000)[seed]))
    s = C.MutableSet({int(k): C.from_values(start[start >> 16 == k] & 65535) for k in np.unique(start >> 16)})
    want = set(start.tolist())
    for _ in range(9000):
        x = r.randrange(1 << 18) if r.random() < 0.7 else r.choice([65535, 65536, 200_000])
        add = r.random() < (0.7, 0.5, 0.3)[seed]
        (s.add if add else s.remove)(x)
        (want.add if add else want.discard)(x)
    for x in range(300_000, 304_200):  # new maxima, across the change of kind
        s.add(x)
        want.add(x)
    got = {k: s.box(k) for k in s.data}
    assert sorted(k << 16 | int(v) for k, b in got.items() for v in C.plain_values(b)) == sorted(want)
    assert all(b.card and (b.kind == C.BITMAP) == (b.card > C.ARRAY_MOST) == s.dense(k) for k, b in got.items())


def test_packed_arrays():
    r = np.random.default_rng(1)
    for n in (0, 1, 2, 50, 4096):
        for most in (4096, 65_536):
            box = C.array_box(np.sort(r.choice(most, n, replace=False)))
            packed = C.pack_gaps(box)
            assert len(packed) == -(-C.packed_bits(box) // 8) and C.unpack_gaps(packed, n).payload == box.payload


def test_fold_takes_canonical_boxes_only():
    small, large = C.from_values(np.arange(10)), C.from_values(np.arange(5000))
    C.assert_fold_kinds([large, small])
    with pytest.raises(ValueError):
        C.assert_fold_kinds([small, large])
    with pytest.raises(ValueError):
        C.assert_fold_kinds([C.Box(C.BITMAP, 10, C.bits_of(np.arange(10)))])


def test_compact_owns_its_buffer():
    whole = np.arange(100, dtype=np.uint16)
    box = C.compact(C.Box(C.ARRAY, 10, whole[:10]))
    whole[:] = 0
    assert box.data.tolist() == list(range(10)) and box.data.base is None


def test_plain_bits():
    words, ids = np.empty(0, np.uint64), set()
    for x in [3, 64, 5000, 5001, 70, 9000]:
        words = R.plain_set(words, x)
        ids.add(x)
        assert set(R.plain_decode(words).tolist()) == ids
    assert len(words) >= 9000 // 64 + 1 and set(R.plain_decode(R.plain_clear(R.plain_clear(words, 64), 10**7)).tolist()) == ids - {64}
    assert R.doubling_words([0, 64, 128, 10_000]) == 157


@pytest.mark.parametrize("codec", ["fillrun", "posfill"])
def test_codecs_word_by_word(codec):
    """Against the formats' definition, read one word at a time."""
    r = np.random.default_rng(2)
    for k in range(60):
        ids = np.unique(np.concatenate([r.integers(0, 5000, r.integers(0, 60)), np.arange(*np.sort(r.integers(0, 5000, 2)))]))
        out, group = [], 0
        for w in R.encode(ids, codec, fill_most=(None, 4)[k % 2] if codec == "fillrun" else None).tolist():
            if not w >> 31:
                out += [group * 31 + b for b in range(31) if w >> b & 1]
                group += 1
                continue
            ones, odd, n = w >> 30 & 1, 0, w & ((1 << 30) - 1)
            if codec == "posfill":
                odd, n = w >> 25 & 31, w & ((1 << 25) - 1)
                if odd:
                    out += [group * 31 + b for b in range(31) if ones ^ (b == odd - 1)]
                    group += 1
                else:
                    n += 1
            if ones:
                out += range(group * 31, (group + n) * 31)
            group += n
        assert out == ids.tolist() and R.decode(R.encode(ids, codec), codec).tolist() == ids.tolist()


def test_id_lists(spark, tmp_path):
    rows = spark.createDataFrame([("a", 1), ("b", 70_000)], "set_id string, id long")
    rows.write.csv(str(tmp_path / "csv"))
    rows.write.json(str(tmp_path / "json"))
    rows.select(F.concat_ws(" ", "set_id", "id").alias("value")).write.text(str(tmp_path / "text"))
    for fmt in ("csv", "json", "text"):
        assert sorted(map(tuple, tables.read_ids(spark, str(tmp_path / fmt), fmt).collect())) == [("a", 1), ("b", 70_000)]


def test_bucketed_table(spark):
    c = build.build(tables.range_set(spark, 0, 200_000, 3, "s"))
    try:
        t = tables.write_bucketed(c, "chunkset_bucketed", 4)
        assert sorted(map(tuple, t.select("set_id", "key", "card").collect())) == sorted(map(tuple, c.select("set_id", "key", "card").collect()))
        joined = t.alias("x").hint("merge").join(t.alias("y"), "key")
        assert "Exchange" not in joined._jdf.queryExecution().sparkPlan().toString()
    finally:
        spark.sql("DROP TABLE IF EXISTS chunkset_bucketed")


def test_merged_batches(spark, tmp_path):
    for i, ids in enumerate(([1, 2, 70_000], [2, 3])):
        spark.createDataFrame([("s", x) for x in ids], "set_id string, id long").coalesce(1).write.parquet(str(tmp_path / f"in/part={i}"))
    stream = spark.readStream.schema("set_id string, id long, part int").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    path = str(tmp_path / "out")
    users.merge_batches(stream, path)
    users.merge_batches(stream, path)  # nothing new: nothing changes
    kept = spark.read.parquet(path).drop("batch")
    groups = spark.createDataFrame([("all", "s")], "group_id string, set_id string")
    assert sorted(r["id"] for r in build.to_ids(manyway.union_all(kept, groups)).collect()) == [1, 2, 3, 70_000]


def test_membership_by_words(spark):
    c = build.build(tables.range_set(spark, 0, 300_000, 7, "a").union(tables.range_set(spark, 100_000, 110_000, 1, "b")))
    table = spark.range(0, 300_000, 5).withColumn("word", F.lit("mine"))
    want = [x for x in range(0, 300_000, 5) if x % 7 == 0 or 100_000 <= x < 110_000]
    assert sorted(r["id"] for r in pairwise.rows_in(table, "id", c).collect()) == want
    assert pairwise.rows_not_in(table, "id", c).count() == 60_000 - len(want)
    assert access.cardinality(c).count() == 2


@pytest.mark.parametrize("t", [1, 2, 5])
def test_threshold_and_intersection_of_many(spark, t):
    r = random.Random(t)
    members = {f"s{i}": set(r.sample(range(140_000), r.choice([20, 9000]))) | {5, 66_000} for i in range(6)}
    ids = spark.createDataFrame([(s, x) for s, xs in members.items() for x in xs], "set_id string, id long")
    groups = spark.createDataFrame([("g", s) for s in members], "group_id string, set_id string").repartition(3)
    c = build.build(ids.repartition(5))
    counts = {x: sum(x in m for m in members.values()) for x in set().union(*members.values())}
    assert sorted(x["id"] for x in manyway.threshold(c, groups, t).collect()) == sorted(x for x, n in counts.items() if n >= t)
    assert sorted(x["id"] for x in build.to_ids(manyway.intersect_all(c, groups)).collect()) == sorted(x for x, n in counts.items() if n == 6)
