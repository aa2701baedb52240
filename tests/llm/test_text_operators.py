"""The text operators against brute force, the libraries that they must agree with, and planted cases."""

import base64
import hashlib
import random
import re
import struct

import numpy as np
import pytest
import public_tokenizers as P
import tiktoken
import tokenizers
from pyspark.sql import functions as F

from chunkset.llm import byte_bpe, mixing, privacy, quality, simhash, token_counts, toxicity

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
ALPHABET = "abcde ABC'sTre  \n\t\r\x1c\x1f\x85　 é日本123²Ⅷ!?.,-_😀́'llx\x00"


def texts(n, seed=1):
    r = random.Random(seed)
    return ["".join(r.choice(ALPHABET) for _ in range(r.randint(0, 40))) for _ in range(n)]


@pytest.fixture(scope="module")
def edges(spark):
    """Nulls in every column, empty and long texts, repeated rows, and columns with names that operators add."""
    long = " ".join(f"word{i % 977} and" for i in range(30_000))
    rows = [(1, None, None, None, None), (None, "a null id", "en", "s", 9), (2, "", "en", "s", 0), (3, "   \n ", "en", "s", 5), (4, long, "en", None, len(long)), (4, long, "en", None, len(long)), (5, "x" * 50_000, "en", "s", 50_000), (6, "same", "en", "s", 4), (7, "same", "en", "t", 4)]
    df = spark.createDataFrame(rows, SCHEMA)
    return df.withColumns({"n_tokens": F.lit("clash"), "score": F.lit("clash"), "k1": F.lit("clash"), "extra": F.lit(1)})


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def reference():
    with open(P.path("byte_bpe_50k.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_agrees_with_the_library(reference):
    c = byte_bpe.codec("byte_bpe_50k.tiktoken")
    r = random.Random(2)
    for t in [*texts(3000), "".join(r.choice("abcdefgh") for _ in range(30_000)), "a" * 5000]:
        ids = c.encode(t)
        assert list(struct.unpack(f"<{len(ids) // 4}I", ids)) == reference.encode_ordinary(t)
        assert c.decode(ids) == t.encode()


def test_rank_queue_with_ranks_that_fall():
    """A pair may rank below the one just merged: leftmost of the lowest rank, always."""
    ranks = {bytes([b]): b for b in range(97, 105)} | {b"bc": 300, b"abc": 200, b"ab": 400, b"abcabc": 250, b"cd": 301}
    r = random.Random(5)
    for _ in range(2000):
        piece = bytes(r.choice(b"abcd") for _ in range(r.randint(1, 14)))
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while piece not in ranks and (pairs := [(ranks[a + b], i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False)) if a + b in ranks]):
            _, i = min(pairs)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        assert byte_bpe.merge_ranked(piece, ranks) == ([ranks[piece]] if piece in ranks else [ranks[p] for p in parts])


def test_bpe_tables(spark, edges, empty, reference):
    back = byte_bpe.decode_ids(byte_bpe.encode_texts(edges)).collect()
    assert len(back) == edges.count() and {r["extra"] for r in back} == {1}
    want = sorted((t or "").encode() for (t,) in edges.select("text").collect())
    assert sorted(bytes(r["decoded"]) for r in back) == want
    assert byte_bpe.round_trip_digests(empty).count() == 0
    for r in byte_bpe.round_trip_digests(edges).collect():
        assert r["decoded_sha256"] in {hashlib.sha256(t).hexdigest() for t in want}


def test_counts_agree_with_the_library():
    t, c = tokenizers.Tokenizer.from_file(P.path("byte_bpe_50k.json")), token_counts.counter("byte_bpe_50k.json")
    for i, x in enumerate(texts(3000, 7)):
        if i % 7 == 0:
            x = x[:5] + "<|endoftext|>" + x[5:]
        assert c.count(x, (3, 8, 1000)[i % 3]) == len(t.encode(x, add_special_tokens=False).ids)


def test_state_maps_compose_in_any_grouping():
    c = token_counts.counter("byte_bpe_50k.json")
    for x in texts(300, 9):
        cut = [x[i : i + 5] for i in range(0, len(x), 5)]
        maps = [c.state_map(p) for p in cut]
        for i, m in enumerate(c.scan(maps)):
            assert c.closed(m) == c.count("".join(cut[: i + 1]))


def test_running_counts(spark):
    c = token_counts.counter("byte_bpe_50k.json")
    x = " ".join(f"token{i}" for i in range(500))
    rows = token_counts.running_counts(spark.createDataFrame([(1, x), (2, None)], "id long, text string"), "id", chunk_chars=100).collect()
    for r in rows:
        assert r["tokens"] == c.count((x if r["id"] == 1 else "")[: r["end_char"]])


def test_count_tables(edges, empty):
    rows = token_counts.count_tokens(edges).collect()
    assert len(rows) == edges.count()
    assert all(r["n_tokens"] == 0 and not r["over_limit"] for r in rows if r["doc_id"] in (1, 2))
    assert token_counts.count_tokens(empty).count() == 0


PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def base(text):
    out = []
    for o, (kind, p) in enumerate(PATTERNS.items()):
        for m in re.finditer(p, text):
            d = re.sub("[^0-9]", "", m.group())
            luhn = sum(x if i % 2 == 0 else x * 2 - 9 * (x > 4) for i, x in enumerate(map(int, reversed(d)))) % 10 == 0
            if {"email": True, "ip": all(int(x) <= 255 for x in m.group().split(".") if kind == "ip"), "card": 14 <= len(d) <= 19 and luhn, "phone": 10 <= len(d) <= 15}[kind]:
                out.append((m.start(), o, kind, m.end()))
    return [f"{k}:{a}:{b}" for a, _, k, b in sorted(out)]


def test_direct_identifiers(spark):
    r = random.Random(3)
    parts = ["1", "12", "255", "256", "0001", ".", "..", "@", "a", "b.c", "-", " ", "+", "(", ")", "4111111111111111", "4111 1111 1111 1111", "é", "😀", "%", "_", "x@y.z", "9" * 10, "\n"]
    rows = [(i, "".join(r.choice(parts) for _ in range(r.randint(0, 25)))) for i in range(800)]
    rows += [(9000, None), (9001, "1 " * 20_000), (9002, "a" * 50_000 + "@b"), (9003, "1." * 20_000), (9004, "é" * 30_000 + " x@y.zz +" + "9" * 20_000)]
    known = dict(rows)
    for x in privacy.detect(spark.createDataFrame(rows, "doc_id long, text string")).collect():
        assert [f"{s['kind']}:{s['start']}:{s['end']}" for s in x["base_spans"]] == base(known[x["doc_id"]] or "")


def letter(i):
    return "abcdefghijklmnop"[i % 16]


def test_telling_terms(spark, edges, empty):
    rows = [(i, f"{letter(i) * 26} Zephyrine wrote {letter(i + 3) * 26} jane.doe@corp.example.org {letter(i + 5) * 26} end") for i in range(8)]
    rows += [(100 + i, f"one passage copied whole with Quixote beside bob@example.com in number {i // 50}") for i in range(100)]
    rows += [(300 + i, f"plain words about nothing in particular, wrote {i}, end, beside number") for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("extra", F.lit("kept"))
    out = {r["doc_id"]: r for r in privacy.sanitise(df).collect()}
    assert len(out) == len(rows) and out[0]["extra"] == "kept"
    assert "Zephyrine" not in out[0]["text"] and "jane" not in out[0]["text"] and "[EMAIL]" in out[0]["text"]
    assert "wrote" in out[0]["text"] and "end" in out[0]["text"]
    assert "Quixote" in out[100]["text"] and "[EMAIL]" in out[100]["text"]  # copies of one passage are no evidence
    assert all(out[300 + i]["text"] == rows[108 + i][1] for i in range(300))
    spans = privacy.detect(df).filter("doc_id = 0").first()
    assert [s["kind"] for s in spans["base_spans"]] == ["email"] and len(spans["all_spans"]) > 1
    assert privacy.sanitise(edges).count() == edges.count() and privacy.sanitise(edges).columns == edges.columns
    assert privacy.detect(empty).count() == 0


def planted(spark, n=240):
    r = random.Random(4)
    words = [a + b for a in ("th", "re", "on", "er", "an", "in") for b in ("ing", "and", "ed", "al", "ou", "is")]
    rows, labels = [], []
    for i in range(n):
        body = [r.choice(words) for _ in range(r.randint(20, 60))]
        bad, toxic = i % 4 == 1, i % 3 == 2
        if toxic:
            for w in r.sample(["loser", "moron", "stupid", "pathetic"], 3):
                body.insert(r.randrange(len(body)), w)
        text = " ".join(w.upper() + "!!" if bad else w for w in body)
        rows.append((i, text, "en", f"s{i % 3}", len(text)))
        labels.append((i, int(not bad), int(toxic)))
    return spark.createDataFrame(rows, SCHEMA), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_quality_learns_and_holds_out(spark, edges, empty):
    docs, labels = planted(spark)
    m = quality.train(docs, labels)
    rows = quality.score(docs, m).join(labels, "doc_id").withColumn("out", quality.held_out()).collect()
    assert any(r["out"] for r in rows) and all((r["score"] >= 0.5) == (r["quality"] == 1) for r in rows)
    flipped = labels.withColumn("quality", F.when(quality.held_out(), 1 - F.col("quality")).otherwise(F.col("quality")))
    assert (quality.train(docs, flipped).w == m.w).all()  # held-out labels teach nothing
    scored = quality.score(edges, m)
    assert scored.count() == edges.count() and all(0 <= r["score"] <= 1 for r in scored.collect())
    assert quality.score(empty, m).count() == 0
    none = quality.train(docs, labels.limit(0))
    assert {r["score"] for r in quality.score(docs.limit(5), none).collect()} == {0.5}


def test_linear_time_identity():
    r = np.random.default_rng(0)
    m = quality.Machine(0.3, r.normal(size=50), r.normal(size=(50, 4)))
    at, x = r.choice(50, 9, replace=False), r.normal(size=9)
    pairs = sum(m.v[at[i]] @ m.v[at[j]] * x[i] * x[j] for i in range(9) for j in range(i))
    assert abs(m.margin(at, x) - (0.3 + m.w[at] @ x + pairs)) < 1e-9


def test_toxicity_restores_disguises(spark, edges, empty):
    docs, labels = planted(spark)
    model = toxicity.language_model(docs)
    s = toxicity.train(docs, labels, model)
    rows = toxicity.score(docs, model, s).join(labels, "doc_id").collect()
    assert all((r["score"] >= 0.7) == (r["toxic"] == 1) for r in rows)
    clean = "thing reand oned inal eris onou anal reis ering"
    hidden = {1: f"{clean} l0ser and m0r0n, st00oopid", 2: f"{clean} l o s e r, p4th3tic m.o.r.o.n", 3: f"{clean} losssser stupppid p@thetic", 4: clean, 5: f"{clean} 100 2nd a.b@c.de +1 555 010 2000"}
    found = {r["doc_id"]: r for r in toxicity.score(spark.createDataFrame(list(hidden.items()), "doc_id long, text string"), model, s, with_text=True).collect()}
    assert [found[i]["score"] >= 0.7 for i in range(1, 6)] == [True, True, True, False, False]
    assert "loser" in found[2]["restored"] and "moron" in found[2]["restored"] and found[4]["restored"] == clean
    assert toxicity.score(edges, model, s).count() == edges.count() and toxicity.score(empty, model, s).count() == 0
    assert toxicity.train(docs, labels.limit(0), model).features == {}


def fingerprint_by_hand(text, k):
    from xxhash import xxh64_intdigest

    w = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    s = [" ".join(w[i : i + k]) for i in range(len(w) - k + 1)] or ([" ".join(w)] if w else [])
    h = [xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def classes_by_hand(fps, distance):
    ids = sorted(fps)
    low = {i: i for i in ids}
    while True:
        new = {i: min(low[j] for j in ids if (fps[i] ^ fps[j]).bit_count() <= distance) for i in ids}
        if new == low:
            return low
        low = new


@pytest.mark.parametrize(("distance", "parts"), [(3, 4), (7, 4), (3, 3), (5, 6), (13, 4)])
def test_simhash_classes(spark, distance, parts):
    r = random.Random(6)
    words = [f"w{i}" for i in range(400)]
    rows, i = [(0, None), (1, ""), (2, " \t"), (3, "ÀB cd"), (4, "Àb CD")], 10
    for _ in range(25):
        text = [r.choice(words) for _ in range(r.choice((3, 30, 120)))]
        for _ in range(r.choice((1, 2, 12))):
            copy = list(text)
            if r.random() < 0.7:
                copy[r.randrange(len(copy))] = r.choice(words)
            rows.append((i, " ".join(copy)))
            i += 1
    fps = {i: fingerprint_by_hand(t, 3) for i, t in rows}
    want = classes_by_hand(fps, distance)
    got = {x["doc_id"]: (x["fp"] & (1 << 64) - 1, x["component_id"]) for x in simhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), 3, distance, parts).collect()}
    assert got == {i: (fps[i], want[i]) for i, _ in rows}


def test_simhash_hot_buckets(spark):
    """Fingerprints in one Hamming ball: buckets are cut into blocks, and no link is lost."""
    r = np.random.default_rng(1)
    flips = [sum(1 << int(b) for b in r.choice(64, r.integers(0, 4), replace=False)) for _ in range(900)]
    fps = sorted({(0x123456789ABCDEF0 ^ f) & (1 << 64) - 1 for f in flips} | {int(x) for x in r.integers(0, 1 << 62, 300)})
    signed = [(f - (1 << 64) if f >> 63 else f,) for f in fps]
    links = simhash.fingerprint_links(spark.createDataFrame(signed, "fp long"))
    from chunkset.llm.common import components

    low = {x["node"] & (1 << 64) - 1: x["component"] & (1 << 64) - 1 for x in components(links).collect()}
    groups = {}
    for f, c in low.items():
        groups.setdefault(c, set()).add(f)
    hand = classes_by_hand({f: f for f in fps}, 3)
    want = {}
    for f, c in hand.items():
        want.setdefault(c, set()).add(f)
    assert sorted(map(sorted, groups.values())) == sorted(sorted(g) for g in want.values() if len(g) > 1)


def test_threshold_allocation_loses_nothing_and_costs_least():
    from itertools import product

    r = np.random.default_rng(2)
    met = [simhash.met_at_radius(r.integers(0, 50, 16), 2) for _ in range(3)]
    values = r.integers(0, 16, (40, 3))
    got = simhash.allot(values, met, 4)
    assert (got.sum(1) == 2).all()
    probes = {-1: 0, 0: 1, 1: 5, 2: 11}
    cost = lambda v, t: sum(met[k][t[k] + 1][v[k]] + simhash.PROBE_COST * probes[t[k]] for k in range(3))
    for v, t in zip(values, got, strict=True):
        best = min(cost(v, c) for c in product(range(-1, 3), repeat=3) if sum(c) == 2)
        assert abs(cost(v, t) - best) < 1e-6


def test_met_at_radius():
    counts = np.random.default_rng(3).integers(0, 9, 64)
    met = simhash.met_at_radius(counts, 2)
    for radius in (0, 1, 2):
        for v in range(64):
            assert round(met[radius + 1][v]) == sum(counts[u] for u in range(64) if (u ^ v).bit_count() <= radius)


def test_simhash_tables(edges, empty):
    rows = {r["doc_id"]: r for r in simhash.near_duplicates(edges.filter("doc_id is not null")).collect()}
    assert rows[1]["fp"] == 0 and rows[1]["component_id"] == rows[2]["component_id"] == rows[3]["component_id"] == 1
    assert rows[7]["component_id"] == 6
    assert simhash.near_duplicates(empty).count() == 0


def test_mix(spark, edges, empty):
    r = random.Random(8)
    rows = [(i, " ".join(["w"] * r.choice((1, 5, 40, 200, 900))), "en", r.choice(["a", "a", "a", "b", "c", None]), 0) for i in range(3000)]
    df = spark.createDataFrame(rows, SCHEMA)
    got = mixing.mix(df).collect()
    again = {(x["doc_id"], x["taken"]) for x in mixing.mix(df.repartition(7)).collect()}
    assert {(x["doc_id"], x["taken"]) for x in got} == again
    source = {i: s for i, _, _, s, _ in rows}
    size = {i: len(t.split()) for i, t, *_ in rows}
    assert all(x["size"] == size[x["doc_id"]] and x["taken"] in (0, x["size"], 2 * x["size"]) for x in got)
    names = ["a", "b", "c", None]
    totals = {s: sum(size[i] for i in size if source[i] == s) for s in names}
    target, free, left = {}, dict(zip(names, (3, 1, 2, 3), strict=True)), 1.5 * sum(totals.values())
    while over := [s for s in free if left * free[s] / sum(free.values()) > 2 * totals[s]]:
        for s in over:
            target[s] = 2 * totals[s]
        left -= sum(2 * totals[s] for s in over)
        free = {s: w for s, w in free.items() if s not in over}
    target |= {s: left * w / sum(free.values()) for s, w in free.items()}
    for s in names:
        mine = [x for x in got if source[x["doc_id"]] == s]
        assert abs(mine[0]["target"] - target[s]) < 1e-6 and mine[0]["source_size"] == totals[s]
        assert abs(sum(x["taken"] for x in mine) - target[s]) <= 450  # half the largest document
    assert mixing.mix(edges).count() == edges.count() and mixing.mix(empty).count() == 0
    out = mixing.mixed_rows(df)
    assert out.count() == sum(x["taken"] // x["size"] for x in got) and out.columns == df.columns


def test_flight_keeps_both_totals():
    r = np.random.default_rng(5)
    size, p = r.integers(1, 5000, 256), r.uniform(0.05, 0.95, 256)
    q = mixing.fly(p, size, r.random(256), False)
    assert abs(q.sum() - p.sum()) < 1e-6 and abs((q - p) @ size) < 1e-3
    assert ((q > 0) & (q < 1)).sum() <= mixing.HELD + 2
    landed = mixing.fly(p, size, r.random(256), True)
    assert set(landed) <= {0.0, 1.0} and abs((landed - p) @ size) < 50
