"""The tables of op7 meet noisy pairs at the threshold, whatever the width of the code and the number of vectors."""

import numpy as np
import pytest

from chunkset.llm import vectors


@pytest.mark.parametrize("dim", [1, 5, 8, 16, 24, 32, 64, 128])
def test_plan_meets_pairs_at_the_threshold(dim):
    bits = min(vectors.CODE_BITS, dim)
    tables, radius = vectors.table_plan(1 << 20, bits)
    assert vectors.table_plan((1 << 20) + 1, bits) == vectors.table_plan(1 << 40, bits) == (tables, radius)
    r = np.random.default_rng(dim)
    x = r.normal(size=(3000, dim))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    aside = r.normal(size=x.shape)
    aside -= (aside * x).sum(1, keepdims=True) * x
    y = 0.95 * x + (np.sqrt(1 - 0.95**2) * aside / np.linalg.norm(aside, axis=1, keepdims=True) if dim > 1 else 0)
    a, b = (vectors.binary_codes(z, *vectors.fit_rotation(np.vstack([x, y]))).view(np.uint64) for z in (x, y))
    edges = np.linspace(0, bits, tables + 1).astype(int).tolist()
    met = np.zeros(len(x), bool)
    for lo, hi in zip(edges[:-1], edges[1:], strict=True):
        met |= np.bitwise_count((a ^ b) >> np.uint64(lo) & np.uint64((1 << hi - lo) - 1)) <= radius
    assert met.mean() >= 0.99
