"""Additive quantisation as an index: recall and the share of rows reranked, both measures, repeated ids."""

import numpy as np
import pytest

from chunkset.llm import vectors


@pytest.mark.parametrize("measure", vectors.MEASURES)
def test_few_rows_are_reranked_for_the_recall(measure):
    r = np.random.default_rng(4)
    x = r.normal(size=(20_000, 48)) * r.uniform(0.5, 2, size=(20_000, 1))
    ids = np.arange(len(x))
    index = vectors.Index(ids[:6000], x[:6000])
    q = np.flatnonzero(ids % 200 == 0)
    search = vectors.Search(index, ids[q], x[q], index.threshold(ids[q], x[q], 20, measure), 20, measure)
    search.start()
    for a in range(0, len(x), 1024):
        search.block(ids[a : a + 1024], x[a : a + 1024], index.coded(x[a : a + 1024]))
    exact = x[q] @ x.T if measure == "inner product" else -((x[q][:, None] - x[None]) ** 2).sum(2)
    exact[np.arange(len(q)), q] = -np.inf
    hits = 0
    for i, row in enumerate(exact):
        mine = search.best[2][search.best[0] == i]
        assert len(mine) == 20
        hits += len(set(mine.tolist()) & set(np.argsort(-row, kind="stable")[:20].tolist()))
    assert hits >= 0.95 * 20 * len(q)
    assert search.reranked <= (0.08 if measure == "inner product" else 0.25) * len(x) * len(q)  # the codes decide, not the exact products


def test_estimates_are_the_codes_own():
    x = np.random.default_rng(5).normal(size=(400, 8))
    index = vectors.Index(np.arange(400), x)
    codes, norm, error = index.uncoded(index.coded(x))
    found = vectors.decode(codes, index.books.astype(float))
    assert np.allclose(norm, (found**2).sum(1)) and np.allclose(error, np.linalg.norm(x - found, axis=1))
    search = vectors.Search(index, np.arange(400), x, np.full(400, -np.inf), 5, "inner product")
    assert np.allclose(search.estimates(codes, norm, 0 * error), x @ found.T, atol=1e-3)


def test_repeated_ids_and_distance(spark):
    rows = [(i % 30, [float(i // 30), 1.0, float(i % 7)]) for i in range(90)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = vectors.nearest(df.repartition(3), lambda i: i == 0, k=5, measure="distance").collect()
    queries = [np.array(v) for i, v in rows if i == 0]
    best = {j: max(-((q - np.array(v)) ** 2).sum() for i, v in rows if i == j for q in queries) for j in range(1, 30)}
    want = sorted(((-s, j) for j, s in best.items()))[:5]
    assert [(r["rank"], r["vec_id"]) for r in sorted(got, key=lambda r: r["rank"])] == [(k + 1, j) for k, (_, j) in enumerate(want)]
