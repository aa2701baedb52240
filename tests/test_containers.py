"""Containers and codecs against Python sets, at random and at every boundary."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from chunkset.functions import containers as C
from chunkset.functions import runs as R

SIZES = [0, 1, 50, 4095, 4096, 4097, 9000, 65535, 65536]
REFERENCE = {"and": np.intersect1d, "or": np.union1d, "andnot": np.setdiff1d, "xor": np.setxor1d}
EXAMPLE = np.unique(np.concatenate([62 * np.arange(1000), 65536 + np.arange(100), 131072 + 2 * np.arange(32768)]))


def some(n, seed):
    return np.sort(np.random.default_rng(seed).choice(C.CHUNK, n, replace=False))


def check(box, values):
    assert C.plain_values(box).tolist() == values.tolist()
    assert box.card == len(values)
    assert (box.kind == C.BITMAP) == (len(values) > C.ARRAY_MOST)
    assert len(box.payload) == (2 * box.card if box.kind == C.ARRAY else 8192)


@pytest.mark.parametrize("n1", SIZES)
@pytest.mark.parametrize("n2", SIZES)
def test_pairs(n1, n2):
    a, b = some(n1, n1), some(n2, n2 + 1)
    x, y = C.from_values(a), C.from_values(b)
    for op, f in REFERENCE.items():
        check(C.OPERATIONS[op](x, y), f(a, b))
    check(C.union(x, y, predict=False), np.union1d(a, b))
    assert C.shared_count(x, y) == len(np.intersect1d(a, b))
    if n1 and n2:
        check(C.union_many([x, y, x]), np.union1d(a, b))
        check(C.intersect_many([x, y]), np.intersect1d(a, b))
        check(C.at_least([x, y, y], 2), np.union1d(b, np.intersect1d(a, b)))


@pytest.mark.parametrize(("common", "kind"), [(4096, C.ARRAY), (4097, C.BITMAP)])
def test_bitmap_and_at_threshold(common, kind):
    a, b = np.arange(10_000), np.arange(10_000 - common, 20_000)
    out = C.intersection(C.from_values(a), C.from_values(b))
    assert (out.card, out.kind) == (common, kind)


@pytest.mark.parametrize(("total", "overlap", "kind"), [(4096, 0, C.ARRAY), (4097, 0, C.BITMAP), (4097, 1, C.ARRAY), (8192, 4096, C.ARRAY)])
def test_array_union_prediction(total, overlap, kind):
    half = total // 2
    a, b = np.arange(half), np.arange(half - overlap, total - overlap)
    work = C.Work()
    out = C.or_arrays(C.array_box(a), C.array_box(b), work)
    assert out.kind == kind
    assert (work.popcounts > 0) == (total > 4096)


def test_galloping_ratio_and_steps():
    assert not C.gallops(63, 1 * 1) or C.gallops(64, 1)
    assert [C.gallops(1, n) for n in (63, 64, 65)] == [False, True, True]
    large, small = C.array_box(np.arange(0, 8192, 2)), C.array_box([3, 4000, 8190])
    g, m = C.Work(), C.Work()
    assert C.and_arrays(large, small, g, "gallop").data.tolist() == C.and_arrays(large, small, m, "merge").data.tolist()
    assert (g.gallop_probes + g.binary_steps) * 20 < m.comparisons


def test_many_way_counts_once():
    boxes = [C.from_values(some(6000, s)) for s in range(10)]
    heap, fold = C.Work(), C.Work()
    assert C.union_many(boxes, heap).payload == C.union_pairwise(boxes, fold).payload
    assert heap.popcounts == C.WORDS
    assert fold.popcounts == 9 * C.WORDS


def test_in_place_saves_allocations():
    a, b = some(9000, 1), some(9000, 2)
    plain, here = C.Work(), C.Work()
    x = C.union(C.from_values(a), C.from_values(b), plain)
    y = C.union(C.from_values(a), C.from_values(b), here, inplace=True)
    assert x.payload == y.payload and here.allocs < plain.allocs


def test_sparse_with_dense_touches_few_words():
    work = C.Work()
    C.intersection(C.from_values(some(60_000, 1)), C.from_values(some(30, 2)), work)
    assert work.words_touched == 30


@settings(max_examples=60, deadline=None)
@given(st.sets(st.integers(0, 65535), max_size=300), st.integers(0, 65535))
def test_single_values(values, x):
    v = np.array(sorted(values), np.int64)
    box = C.from_values(v)
    assert C.contains(box, x) == (x in values)
    assert C.rank(box, x) == sum(y <= x for y in values)
    if x in values:
        assert C.select(box, C.rank(box, x) - 1) == x
    else:
        again = C.remove(C.add(box, x), x)
        assert (again.kind, again.payload) == (box.kind, box.payload)
    assert C.select(box, len(values)) is None


def test_crossing_the_threshold():
    assert C.add(C.from_values(np.arange(4096)), 9000).kind == C.BITMAP
    assert C.remove(C.from_values(np.arange(4097)), 5).kind == C.ARRAY


def test_lowest_bits_and_popcounts():
    rng = np.random.default_rng(0)
    for w in [0, 1, 1 << 63, (1 << 64) - 1, *rng.integers(0, 1 << 62, 50).tolist()]:
        assert C.lowest_bits(w) == [i for i in range(64) if w >> i & 1]
    words = rng.integers(0, 1 << 62, 100).astype(np.uint64)
    assert C.count_ones(words) == C.count_ones(words, table=True) == sum(int(w).bit_count() for w in words)


def test_further_kinds():
    full = C.from_values(np.setdiff1d(np.arange(C.CHUNK), [5, 77]))
    assert C.smallest(full).kind in (C.COMPLEMENT, C.RUNS)
    assert C.smallest(full, (C.ARRAY, C.BITMAP, C.COMPLEMENT)).kind == C.COMPLEMENT
    assert C.smallest(C.from_values(np.arange(100, 900))).kind == C.RUNS
    for n in SIZES[1:]:
        box = C.from_values(some(n, n))
        small = C.smallest(box)
        assert C.plain_values(small).tolist() == C.plain_values(box).tolist() and len(small.payload) <= len(box.payload)
        assert C.from_payload(small.kind, small.payload).card == n
    assert C.packed_bits(C.from_values(np.arange(0, 4000, 4))) < 16 * 1000


def test_blob():
    parts = [(7, C.from_values(some(5000, 3))), (2, C.from_values(some(10, 4)))]
    back = C.from_blob(C.to_blob(parts))
    assert [(k, b.kind, b.payload) for k, b in back] == [(k, b.kind, b.payload) for k, b in sorted(parts, key=lambda p: p[0])]


def test_example_sizes():
    assert len(EXAMPLE) == 33_868 and int(EXAMPLE.sum()) == 5_406_203_902
    assert [len(R.encode(EXAMPLE, c)) for c in ("posfill", "fillrun")] == [3119, 4119]
    spread = 62 * np.arange(1000)
    assert [len(R.encode(spread, c)) for c in ("posfill", "fillrun")] == [1000, 1999]
    assert [len(R.plain_encode(x)) for x in (spread, EXAMPLE)] == [968, 3072]


SETS = [np.array([0]), np.array([31, 62]), np.arange(31 * 5), np.arange(31, 31 * 3 + 1), 62 * np.arange(50), np.arange(0, 1000, 2), np.array([0, 31 << 26]), EXAMPLE]


@pytest.mark.parametrize("codec", ["fillrun", "posfill"])
@pytest.mark.parametrize("i", range(len(SETS)))
def test_codecs(codec, i):
    a = SETS[i]
    stream = R.encode(a, codec)
    assert R.decode(stream, codec).tolist() == a.tolist()
    for b in SETS:
        other = R.encode(b, codec)
        for op, f in (("and", np.intersect1d), ("or", np.union1d), ("xor", np.setxor1d)):
            assert R.decode(R.combine(stream, other, codec, op)[0], codec).tolist() == f(a, b).tolist()
    members = set(a.tolist())
    for x in [*a[:50].tolist(), *range(0, 4000, 37)]:
        assert R.contains(stream, codec, x)[0] == (x in members)
    more = int(a.max()) + 17
    assert R.decode(R.append(stream, codec, more), codec).tolist() == [*a.tolist(), more]
    assert R.decode(R.remove(stream, codec, int(a[0])), codec).tolist() == a[1:].tolist()


@settings(max_examples=60, deadline=None)
@given(st.sets(st.integers(0, 3000), max_size=400))
def test_codec_sizes(values):
    a = np.array(sorted(values), np.int64)
    assert len(R.encode(a, "posfill")) <= len(R.encode(a, "fillrun"))
    assert R.decode(R.encode(a, "posfill", 4), "posfill").tolist() == a.tolist()


def test_fill_overflow():
    """A gap of over 2^25 groups takes one more position-fill word than a shorter one; the other codec's field is longer."""
    far, near = np.array([0, 31 << 26]), np.array([0, 31 << 20])
    assert [len(R.encode(x, "posfill")) for x in (near, far)] == [2, 3]
    assert [len(R.encode(x, "fillrun")) for x in (near, far)] == [3, 3]


def test_plain_bitset():
    a, b = some(300, 1), some(500, 2)
    for op, f in (("and", np.intersect1d), ("or", np.union1d), ("xor", np.setxor1d)):
        assert R.plain_decode(R.plain_combine(R.plain_encode(a), R.plain_encode(b), op)).tolist() == f(a, b).tolist()
    assert R.doubling_words([0, 64, 128, 256]) == 8 and R.doubling_words([100_000]) == 1563


def test_claims_on_sizes():
    rng = np.random.default_rng(42)
    sparse = np.unique((rng.random(100_000) * 100_000 * 1024).astype(np.int64))
    cards = np.unique(sparse >> 16, return_counts=True)[1]
    hybrid = (2 * cards + 4).sum() * 8
    words = {c: len(R.encode(sparse, c)) * 32 for c in ("posfill", "fillrun")}
    assert 0.45 < hybrid / words["posfill"] < 0.55 and 0.22 < hybrid / words["fillrun"] < 0.28
    runs = np.arange(5000, 200_000)
    assert len(R.encode(runs, "posfill")) * 32 < 8 * 2 * len(runs) / 16
