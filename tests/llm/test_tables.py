"""Vector operators, WARC archives, shared helpers and the pipeline."""

import base64
import hashlib
import importlib.util
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from chunkset.llm import vectors, warc
from chunkset.llm.common import components, local_components, saved


def vector_rows(n=1500, dim=16, seed=1):
    r = np.random.default_rng(seed)
    base = r.normal(size=(n, dim))
    base[200:500] = base[200] + 0.05 * r.normal(size=(300, dim))  # a dense group
    base[500:800] = base[500]  # copies
    base[800:810] = 2 * base[810]
    return [(i, v.astype(np.float32).tolist()) for i, v in enumerate(base)]


BAD = [(5000, None), (5020, [0.0] * 16), (5040, [float("nan")] + [1.0] * 15), (5060, [None] + [1.0] * 15), (5080, [float("inf")] + [1.0] * 15), (5100, [1.0, 2.0])]
VECTORS = "vec_id long, embedding array<float>"


def test_links(spark):
    rows = vector_rows()
    df = spark.createDataFrame([*rows, *BAD], VECTORS).withColumn("score", F.lit("clash"))
    got = {r["vec_id"]: r for r in vectors.linked(df).collect()}
    x = np.array([v for _, v in rows])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    near = x @ x.T >= 0.95
    np.fill_diagonal(near, False)
    u, v = np.nonzero(near)
    nodes, low = local_components(u, v)
    want = dict(zip(nodes.tolist(), low.tolist(), strict=True))
    found = sum(got[i]["n_links"] for i, _ in rows)
    assert 0.9 * near.sum() <= found <= near.sum()
    assert all(got[i]["n_links"] <= near[i].sum() for i, _ in rows)
    assert all(got[i]["component_id"] == want.get(i, i) for i in range(800))
    assert all(got[i]["n_links"] == 0 and got[i]["kept"] for i, _ in BAD)
    assert len(got) == len(rows) + len(BAD)


def test_probing_with_a_radius(spark, monkeypatch):
    rows = [(i, np.random.default_rng(i // 4).normal(size=64).astype(np.float32).tolist()) for i in range(400)]
    rows = [(i, (np.array(v) + 0.02 * np.random.default_rng(i).normal(size=64)).tolist()) for i, v in rows]
    plain = {tuple(r) for r in vectors.linked(spark.createDataFrame(rows, VECTORS)).collect()}
    monkeypatch.setattr(vectors, "table_plan", lambda n, bits: (4, 1))
    assert {tuple(r) for r in vectors.linked(spark.createDataFrame(rows, VECTORS)).collect()} == plain
    assert {r[1] for r in plain} == {3}


def test_search_recall_and_ties(spark):
    rows = vector_rows()
    df = spark.createDataFrame([*rows, *BAD], VECTORS)
    got = vectors.nearest(df, lambda i: i % 20 == 0, k=20).collect()
    x = np.array([np.array(v, np.float32) for _, v in rows]).astype(float)
    hits = total = 0
    for q in range(0, len(rows), 20):
        s = x @ x[q]
        s[q] = -np.inf
        best = np.lexsort((np.arange(len(x)), -s))[:20]
        mine = sorted((r for r in got if r["query_id"] == q), key=lambda r: r["rank"])
        assert [r["rank"] for r in mine] == list(range(1, 21))
        assert all(abs(r["score"] - s[r["vec_id"]]) < 1e-9 for r in mine)
        assert all((a["score"], -a["vec_id"]) > (b["score"], -b["vec_id"]) for a, b in zip(mine, mine[1:], strict=False))
        hits += len({r["vec_id"] for r in mine} & set(best.tolist()))
        total += 20
    assert hits / total >= 0.9
    assert not {r["query_id"] for r in got} & {i for i, _ in BAD}
    few = vectors.nearest(df.filter("vec_id < 5"), lambda i: i % 20 == 0).collect()
    assert len(few) == 4
    assert vectors.nearest(df.limit(0), lambda i: i % 20 == 0).count() == 0
    assert vectors.linked(df.limit(0)).count() == 0


def test_beam_beats_greedy():
    x = np.random.default_rng(0).normal(size=(600, 16))
    books = vectors.fit_codebooks(x, 4, 16)
    error = lambda beam: ((x - sum(books[m][vectors.encode(x, books, beam)[:, m]] for m in range(4))) ** 2).sum()
    assert error(8) <= error(1)


def test_components_against_brute_force(spark):
    r = np.random.default_rng(7)
    chain = [(i, i + 1) for i in range(300)]
    star = [(1000, 1001 + i) for i in range(400)]
    noise = [(int(a), int(b)) for a, b in r.integers(2000, 2400, (250, 2))]
    links = chain + star + noise
    got = {x["node"]: x["component"] for x in components(spark.createDataFrame(links, "u long, v long").repartition(6)).collect()}
    u, v = (np.array(z) for z in zip(*[p for p in links if p[0] != p[1]], strict=True))
    nodes, low = local_components(u, v)
    assert got == dict(zip(nodes.tolist(), low.tolist(), strict=True))
    assert components(spark.createDataFrame([], "u long, v long")).count() == 0


PAGES = [(1, "http://a/", "<p>x</p>"), (2, None, "<p>x</p>"), (3, "http://b/\n c", ""), (4, "u", None), (None, "u", "<p>x</p>"), (6, "u", "é" * 100_000), (6, "u", "é" * 100_000), (7, "u", "only\r\n\r\nthis")]


def test_archives(spark, tmp_path):
    df = spark.createDataFrame(PAGES, "page_id long, url string, html string").withColumn("payload", F.lit("clash"))
    path = str(tmp_path / "warc")
    manifest = saved(warc.write_archives(warc.with_originals(df), path, archive_bytes=300), "m")
    assert manifest.agg(F.sum("records")).first()[0] == len(PAGES) and manifest.count() > 1
    rows = warc.read_archives(spark, path, payloads=True).collect()
    assert len(rows) == len(PAGES) and all(r["sound"] for r in rows)
    want = {(i, len((h or "").encode()), base64.b32encode(hashlib.sha1((h or "").encode()).digest()).decode()) for i, _, h in PAGES}
    assert {(r["page_id"], r["payload_bytes"], r["payload_digest"]) for r in rows} == want
    kinds = sorted((r["page_id"] or 0, r["record_type"], r["refers_to"]) for r in rows)
    assert kinds == [(0, "revisit", 2), (1, "revisit", 2), (2, "response", None), (3, "revisit", 4), (4, "response", None), (6, "response", None), (6, "response", None), (7, "response", None)]
    assert next(bytes(r["payload"]) for r in rows if r["page_id"] == 7) == b"only\r\n\r\nthis"


def test_reader_refuses_damage():
    one = warc.member("response", "urn:page:1", "http://a/", 5, warc.base32_sha1(b"hello"), b"hello", "2024-01-01T00:00:00Z", None)
    for step in (1, 7, 1 << 16):
        found = list(warc.records(iter([(one + one)[i : i + step] for i in range(0, 2 * len(one), step)])))
        assert len(found) == 2 and all(r.sound and r.payload == b"hello" for r in found)
    with pytest.raises(warc.FormatError):
        list(warc.records(iter([one[:-9]])))
    raw = zlib.decompress(one, 31)
    squeeze = lambda b: (c := zlib.compressobj(1, zlib.DEFLATED, 31)).compress(b) + c.flush()
    with pytest.raises(warc.FormatError):
        list(warc.records(iter([squeeze(raw[:-4] + b"!!\r\n\r\n")])))
    assert not next(warc.records(iter([squeeze(raw.replace(b"hello", b"hellp"))]))).sound
    assert list(warc.records(iter([]))) == []


@pytest.mark.skipif(importlib.util.find_spec("corpus_pipeline") is None, reason="the pipeline isn't there")
def test_pipeline(spark):
    import corpus_pipeline as c

    from chunkset.llm import byte_bpe, privacy, simhash

    sf = "/root/testdata/sf0.001"
    docs, seen = spark.read.parquet(f"{sf}/documents.parquet"), {}
    for name, stage in c.STAGES:
        docs = saved(stage(spark, docs, sf), "stage")
        seen[name] = docs
        if name != c.STAGES[-1][0]:
            assert docs.columns == list(c.COLUMNS)
    source = {r["doc_id"]: r for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    good = {r["doc_id"]: r for r in seen["quality classifier"].collect()}
    assert all(good[i]["text"] == source[i]["text"] for i in good)
    kept = [labels[i] for i in good if i in labels]
    assert sum(kept) >= 0.98 * sum(labels.values()) and len(kept) - sum(kept) <= 0.3 * (len(labels) - sum(labels.values()))
    sets = {i: frozenset(simhash.shingle_hashes((r["text"] or "").encode(), 5).tolist()) for i, r in good.items()}
    near = {(i, j) for i in sets for j in sets if sets[i] == sets[j] or len(sets[i] & sets[j]) >= c.SIMILARITY * len(sets[i] | sets[j])}
    low = {i: i for i in sets}
    while True:
        new = {i: min(low[j] for j in sets if (i, j) in near) for i in sets}
        if new == low:
            break
        low = new
    assert {r["doc_id"] for r in seen["simhash near-dedup"].collect()} == {i for i in sets if low[i] == i}
    hidden = {r["doc_id"]: r for r in seen["personal data"].collect()}
    plain = {r["doc_id"]: r for r in privacy.detect(seen["simhash near-dedup"]).collect()}
    for i, r in hidden.items():
        if not plain[i]["all_spans"]:
            assert r["text"] == good[i]["text"]
        assert r["n_chars"] == len(r["text"])
    mixed = seen["mixing"].collect()
    assert {r["doc_id"] for r in mixed} <= set(hidden) and all(r["text"] == hidden[r["doc_id"]]["text"] for r in mixed)
    codec = byte_bpe.codec("byte_bpe_50k.tiktoken")
    last = seen["byte-level bpe"].collect()
    assert sorted((r["doc_id"], codec.decode(bytes(r["token_ids"])).decode()) for r in last) == sorted((r["doc_id"], r["text"]) for r in mixed)
    assert all(r["n_tokens"] * 4 == len(r["token_ids"]) for r in last)
    odd = [(None, None, None, None, None), (None, "no id", "en", "s", 1), (1, None, None, None, None), (2, "", "en", None, 0), (3, "a b c " * 9000, "en", "s", 5), (4, "same words in two rows", "en", "s", 1), (4, "same words in two rows", "en", "t", 2), (4, "quite another text", "en", "s", 3)]
    odd = spark.createDataFrame(odd, "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in c.STAGES:
        stage(spark, odd.withColumn("score", F.lit("clash")), sf).count()
    kept = c.drop_near_copies(spark, odd, sf).collect()
    assert sorted(r["doc_id"] or 0 for r in kept) == [0, 0, 1, 3, 4]
    none = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, stage in c.STAGES:
        assert stage(spark, none, sf).count() == 0
