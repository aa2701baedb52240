"""Near copies of the pipeline against brute-force similarity."""

import random

import numpy as np

import corpus_pipeline
from chunkset.llm import near_copies
from chunkset.llm.common import local_components

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def shingles(text):
    w = (text or "").lower().split()
    return frozenset(" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset()


def similarity(a, b):
    return len(a & b) / len(a | b) if a | b else 1.0


def edited_rows():
    """Texts of 60 to 400 words with copies in which some words are others, a chain of edits, and a large group."""
    r = random.Random(5)
    word = lambda: f"w{r.randrange(4000)}"
    texts = []
    for _ in range(120):
        base = [word() for _ in range(r.randint(60, 400))]
        texts.append(" ".join(base))
        for share in (0.004, 0.012, 0.02, 0.03, 0.05):
            texts.append(" ".join(word() if r.random() < share else w for w in base))
    step = [word() for _ in range(100)]
    for i in range(12):
        step = step[:] if i % 2 else step[3:] + [word() for _ in range(3)]
        texts.append(" ".join(step))
    hot = [word() for _ in range(80)]
    texts += [" ".join(hot[:k] + [word()] + hot[k + 1 :]) for k in range(80)] + [" ".join(hot).upper(), "", None, " \n", "one two", "One  two"]
    r.shuffle(texts)
    return [(i, t, "en", "s", len(t or "")) for i, t in enumerate(texts)]


def brute_force(rows):
    sets = [shingles(t) for _, t, *_ in rows]
    u, v = zip(*[(i, j) for i in range(len(sets)) for j in range(i) if similarity(sets[i], sets[j]) >= 0.8], strict=True)
    nodes, low = local_components(np.array(u), np.array(v))
    return {i: i for i in range(len(sets))} | dict(zip(nodes.tolist(), low.tolist(), strict=True))


def test_near_copies_against_brute_force(spark, monkeypatch):
    rows = edited_rows()
    want = brute_force(rows)
    docs = spark.createDataFrame(rows, DOCS)
    got = {r["doc_id"]: r["component_id"] for r in near_copies.near_copies(docs).collect()}
    assert got == want
    monkeypatch.setattr(near_copies, "BLOCK_ROWS", 9)
    assert {r["doc_id"]: r["component_id"] for r in near_copies.near_copies(docs).collect()} == want


def test_stage_drops_exactly_what_is_similar(spark):
    rows = edited_rows()
    want = brute_force(rows)
    kept = {r["doc_id"] for r in corpus_pipeline.drop_near_copies(spark, spark.createDataFrame(rows, DOCS), "").collect()}
    assert kept == {i for i in want if want[i] == i}
    assert corpus_pipeline.drop_near_copies(spark, spark.createDataFrame([], DOCS), "").count() == 0


def test_candidates_reach_the_threshold():
    r = np.random.default_rng(3)
    met = 0
    for _ in range(300):
        x = r.integers(0, 1 << 63, 100, np.uint64)
        a, b = np.sort(x[:90]), np.sort(np.append(x[:80], x[90:]))  # 80 of 100
        met += bool((near_copies.band_values(a) == near_copies.band_values(b)).any())
    assert met == 300
