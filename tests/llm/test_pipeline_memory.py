"""What the pipeline's stages leave in memory for those after them."""

import public_tokenizers

import corpus_pipeline
from chunkset.llm import byte_bpe
from chunkset.llm.common import BATCH_KEY


def test_stages_take_small_batches_and_caches(spark):
    words = " ".join(f"word{i} other{i * 7919}" for i in range(60_000))
    docs = spark.createDataFrame([(1, words, "en", "a", len(words)), (2, None, "en", None, None), (3, words[:1000], "de", "b", 1000)], "doc_id long, text string, lang string, source string, n_chars long")
    want = sorted((r["doc_id"], r["n_tokens"], bytes(r["token_ids"])) for r in byte_bpe.encode_texts(docs).collect())
    had = spark.conf.get(BATCH_KEY)
    try:
        coded = corpus_pipeline.tokenise(spark, docs, "")
        assert int(spark.conf.get(BATCH_KEY).rstrip("b")) <= 1 << 20
        assert sorted((r["doc_id"], r["n_tokens"], bytes(r["token_ids"])) for r in coded.collect()) == want
    finally:
        spark.conf.set(BATCH_KEY, had)
    codec = byte_bpe.Codec(byte_bpe.vocabulary_path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, corpus_pipeline.CACHED_BYTES)
    codec.encode(words)
    kept = [len(k) + len(v) for part in (codec.memo.young, codec.memo.old) for k, v in part.items()]
    assert len(kept) * 100 + sum(kept) < 16 << 20
