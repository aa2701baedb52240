"""Batches of containers against the operations on single ones."""

import numpy as np
import pyarrow as pa
import pytest

from chunkset.functions import batch as K
from chunkset.functions import containers as C


def boxes(seed, n=60):
    r = np.random.default_rng(seed)
    out = []
    for _ in range(n):
        size = int(r.choice([1, 2, 30, 64, 4000, 4096, 4097, 9000, 40_000, 65_536]))
        most = int(r.choice([C.CHUNK, max(size, 5000)]))
        out.append(C.from_values(np.sort(r.choice(most, min(size, most), replace=False))))
    return out


def column(list_):
    return K.from_column(pa.array([b.kind for b in list_], pa.int8()), pa.array([b.payload for b in list_], pa.binary()))


def same(stack, want):
    payload = stack.payloads().to_pylist()
    for i, b in enumerate(want):
        assert (stack.card[i], stack.kind[i] if b.card else 0, payload[i]) == (b.card, b.kind if b.card else 0, b.payload)


@pytest.mark.parametrize("seed", range(4))
def test_pairs(seed):
    a, b = boxes(seed), boxes(100 + seed)
    x, y = column(a), column(b)
    same(K.union(x, y), [C.union(p, q) for p, q in zip(a, b, strict=True)])
    for method in ("auto", "merge", "gallop"):
        same(K.intersection(x, y, method), [C.canonical(C.intersection(p, q)) for p, q in zip(a, b, strict=True)])
    same(K.union(x, y, predict=False), [C.union(p, q, predict=False) for p, q in zip(a, b, strict=True)])
    assert K.shared_counts(x, y).tolist() == [C.intersection(p, q).card for p, q in zip(a, b, strict=True)]


def test_slices_and_empty_columns():
    a = boxes(7)
    kinds, payloads = pa.array([b.kind for b in a], pa.int8()), pa.array([b.payload for b in a], pa.binary())
    same(K.from_column(kinds.slice(11, 20), payloads.slice(11, 20)), a[11:31])
    none = K.from_column(kinds.slice(0, 0), payloads.slice(0, 0))
    assert len(K.union(none, none)) == len(K.intersection(none, none)) == 0


@pytest.mark.parametrize("seed", range(6))
def test_whole_sets(seed):
    r = np.random.default_rng(seed)
    one = lambda: np.unique(np.concatenate([r.integers(0, 1 << 21, r.integers(0, 3000)), r.integers(0, 1 << 17, 60_000 * (seed % 2)), np.arange(1 << 18, (1 << 18) + 9000)]))
    a, b = one(), one()
    p, q = K.Packed.of(a), K.Packed.of(b)
    assert (p.ids() == a).all()
    both, either = K.intersect_sets(p, q), K.unite_sets(p, q)
    assert both.ids().tolist() == np.intersect1d(a, b).tolist() and either.ids().tolist() == np.union1d(a, b).tolist()
    for s in (both, either):
        assert ((s.boxes.kind == C.BITMAP) == (s.boxes.card > C.ARRAY_MOST)).all() and (s.boxes.card > 0).all() and (np.diff(s.keys) > 0).all()
    none = K.Packed.of(np.empty(0, np.int64))
    assert len(K.intersect_sets(p, none).keys) == 0 and K.unite_sets(none, q).ids().tolist() == b.tolist()
