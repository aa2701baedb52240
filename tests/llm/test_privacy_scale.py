"""Sanitising: long texts in time close to linear, replacements and information measure against plain Python."""

import random
import time
from math import log2

from pyspark.sql import functions as F

from chunkset.llm import privacy


def test_sums_and_maxima_of_earlier_elements(spark):
    r = random.Random(1)
    rows = [(i, [r.randint(0, 9) for _ in range(n)]) for i, n in enumerate([0, 1, 63, 64, 65, 4096, 4097, 20_000])]
    df = spark.createDataFrame(rows, "i int, v array<int>")
    out = df.select("i", "v", privacy.before(F.col("v"), lambda a, b: a + b).alias("s"), privacy.before(F.col("v"), privacy.larger).alias("m"))
    for x in out.collect():
        assert x["s"] == [sum(x["v"][:k]) for k in range(len(x["v"]))] if len(x["v"]) < 5000 else x["s"][-1] == sum(x["v"][:-1])
        assert x["m"] == [max([0, *x["v"][:k]]) for k in range(len(x["v"]))] if len(x["v"]) < 5000 else x["m"][-1] == max(x["v"][:-1])


def test_replacement_against_slices(spark):
    r = random.Random(2)
    parts = ["a@b.cd ", "1.2.3.4", "+1 (555) 010-2000", "4111 1111 1111 1111", "é😀 ", "plain words " * 300, "\n"]
    rows = [(i, "".join(r.choice(parts) for _ in range(r.randint(0, 30)))) for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {x["doc_id"]: x["text"] for x in df.select("doc_id", privacy.masked(F.col("text"), privacy.base_spans(F.col("text"))).alias("text")).collect()}
    for x in privacy.detect(df).collect():
        text, out, at = dict(rows)[x["doc_id"]], [], 0
        for s in x["base_spans"]:
            assert text[s["start"] : s["end"]] == s["value"]
            if s["start"] >= at:
                out += [text[at : s["start"]], f"[{s['kind'].upper()}]"]
            at = max(at, s["end"])
        assert got[x["doc_id"]] == "".join(out) + text[at:]


def test_many_matches_in_one_text(spark):
    rows = [(1, " ".join(f"user{i}@host.example" for i in range(100_000))), (2, "é " * 500_000 + "a@b.cd"), (3, "1.2.3.4 " * 100_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    began = time.time()
    found = {x["doc_id"]: x for x in privacy.detect(df).select("doc_id", "n_email", "n_ip", F.element_at("base_spans", -1)["end"].alias("end")).collect()}
    assert [found[1]["n_email"], found[2]["n_email"], found[3]["n_ip"]] == [100_000, 1, 100_000]
    assert [found[i]["end"] for i in (1, 2, 3)] == [len(rows[0][1]), len(rows[1][1]), len(rows[2][1]) - 1]
    text = {x["doc_id"]: x["text"] for x in privacy.sanitise(df).collect()}
    assert text[1] == " ".join(["[EMAIL]"] * 100_000) and text[2] == "é " * 500_000 + "[EMAIL]"
    assert time.time() - began < 90


def by_hand(rows):
    """The measure from its definition, with one identifier a document."""
    docs = [(t.split()[0], t.split()[1], set(t.split()[2:])) if "@" in t else (None, None, set(t.split())) for _, t in rows]
    pairs = {}
    for e in {d[0] for d in docs} - {None}:
        own = [d for d in docs if d[0] == e]
        n_e, d_e = len({d[1] for d in own}), len(own)
        if n_e < privacy.CONTEXTS:
            continue
        for t in set().union(*(d[2] | {d[1]} for d in own)):
            with_t = [d for d in own if t in d[2] or t == d[1]]
            d_t = sum(t in d[2] or t == d[1] for d in docs)
            pairs[e, t] = (len({d[1] for d in with_t}), n_e, d_e, len(with_t), d_t)
    pairs = {k: v for k, v in pairs.items() if v[0] >= privacy.CONTEXTS}
    bits, telling = log2(max(len(pairs), 1)) + privacy.MARGIN_BITS, {}
    for (_, t), (n_et, n_e, d_e, d_et, d_t) in pairs.items():
        units = len(docs) - d_e + n_e
        pmi, content = log2(n_et * units / (n_e * (n_et + d_t - d_et))), log2(units / n_e)
        if n_et * pmi >= bits and pmi / content >= privacy.GENERALISE:
            telling[t] = max(telling.get(t, 0), pmi / content)
    return telling


def test_information_against_its_definition(spark):
    r = random.Random(3)
    common = [f"c{i}" for i in range(40)]
    rows = []
    for i in range(900):
        words = " ".join(r.sample(common, 6))
        if i % 3 == 0:
            who = i % 4
            own = [f"tells{who}"] * (r.random() < 0.9) + [f"oft{who}"] * (r.random() < 0.7)
            # padding of an own length sets the context apart; every tenth document repeats the first one's
            rows.append((i, f"user{who}@host.example {'u' + 'abcdefghijklmnopqrstuvwxyz'[(0 if i % 10 == 0 else i) % 26] * 30} {' '.join(own)} {words}"))
        else:
            rows.append((i, words + (" oft1" if i % 97 == 1 else "") + (" ab" if i % 50 == 0 else "")))
    rows += [(2000 + i, "user9@host.example " + "u" + "z" * 30 + " quixote " + common[i % 40]) for i in range(100)]  # one context: no evidence
    df = spark.createDataFrame(rows, "doc_id long, text string")
    found = privacy.saved(privacy.found_in(df, "doc_id", "text"), "t")
    got = {x["term"]: x["share"] for x in privacy.telling_terms(df, found, "doc_id", "text").collect()}
    want = by_hand(rows)
    assert "tells0" in want and "quixote" not in want and set(got) == set(want)
    assert all(abs(got[t] - want[t]) < 1e-9 for t in got)
