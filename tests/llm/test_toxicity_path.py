"""The restored span against all paths of its lattice, mixed disguises, and long tokens."""

import random
import time
from itertools import product

import numpy as np

from chunkset.llm import toxicity
from tests.llm.test_text_operators import planted


def model():
    r = np.random.default_rng(1)
    return toxicity.Model.of(r.integers(0, 40, toxicity.CLASSES**3) * (r.random(toxicity.CLASSES**3) < 0.3))


def price(path, m):
    total, p, q = 0.0, 0, 0
    for string, cost in path:
        total += cost
        for x in string:
            k = toxicity.class_of(x)
            total += float(m.cost[p, q, k])
            p, q = q, k
    return total + float(m.cost[p, q, 0])


def test_best_path_against_all_paths():
    m, r = model(), random.Random(2)
    for _ in range(300):
        span = "".join(r.choice("abcéж") if r.random() < 0.5 else r.choice(["1", "0", "ooo", "$$$", ".", " ", "*", "aaa", "_-"]) for _ in range(r.randint(1, 7)))
        options = list(toxicity.lattice(span))
        found = toxicity.restore(span, m)
        paths = [p for p in product(*options) if "".join(s for s, _ in p) == found]
        best = min(price(p, m) for p in product(*options))
        assert abs(min(price(p, m) for p in paths) - best) < 1e-3


def test_long_tokens_in_linear_time():
    m, r = toxicity.Restorer(model()), random.Random(3)
    began = time.time()
    for text in ("x" * 1_000_000, "aaa." * 250_000, "".join(r.choice("abcdefgh0123456789+/") for _ in range(300_000)), "a.b4" * 100_000, "a 4 , " * 100_000, "4" * 1_000_000, "l o s " * 50_000):
        list(m.restored(text))
    assert time.time() - began < 60


def test_mixed_disguises_and_held_out_rows(spark):
    docs, labels = planted(spark)
    m = toxicity.language_model(docs)
    s = toxicity.train(docs, labels, m)
    clean = "thing reand oned inal eris onou anal reis ering"
    rows = [(i, f"{clean} {x} {clean}") for i, x in enumerate(["m 0 r 0 n", "l.0.s.3.r", "l  o  s  e  r", "m, o, r, o, n", "p-4-t-h-3-t-1-c", "1 2 3 4 5", "a 1 b 2 c 3", "3 + 4 = 7"])]
    got = {r["doc_id"]: r for r in toxicity.score(spark.createDataFrame(rows, "doc_id long, text string"), m, s, with_text=True).collect()}
    for i, word in enumerate(["moron", "loser", "loser", "moron", "pathetic"]):
        assert word in got[i]["restored"].split(), got[i]["restored"]
    plain = toxicity.score(spark.createDataFrame([(9, f"{clean} {clean}")], "doc_id long, text string"), m, s).first()["score"]
    assert all(got[i]["score"] > plain for i in range(5)) and all(got[i]["score"] < 0.7 for i in (5, 6, 7))
    scored = toxicity.score(docs, m, s).join(labels, "doc_id").withColumn("out", toxicity.held_out()).filter("out").collect()
    assert len(scored) > 40 and sum((r["score"] >= 0.7) == (r["toxic"] == 1) for r in scored) >= 0.98 * len(scored)
