"""State maps of the token transducer: texts without white space cut anywhere, and distributed running counts."""

import random

import public_tokenizers as P
import tokenizers

from chunkset.llm import token_counts

PARTS = ["'s", "'re", "'r", "''", "'", "ll", "don't", "aaaa", "b", "12", "3", "é", "日本", "😀", "--", ".", "²", "_", "x'l", "'ve"]


def test_unspaced_texts_cut_anywhere():
    c, library, r = token_counts.counter("byte_bpe_50k.json"), tokenizers.Tokenizer.from_file(P.path("byte_bpe_50k.json")), random.Random(3)
    for i in range(800):
        x = "".join(r.choice(PARTS if i % 2 else [*PARTS, " ", "  ", "\n", " \n ", "　"]) for _ in range(r.randint(0, 14)))
        cuts = sorted(r.randint(0, len(x)) for _ in range(r.randint(0, 6)))
        maps = c.scan([c.state_map(x[a:b]) for a, b in zip([0, *cuts], [*cuts, len(x)], strict=True)])
        for m, end in zip(maps, [*cuts, len(x)], strict=True):
            assert c.closed(m) == len(library.encode(x[:end], add_special_tokens=False).ids)


def test_grouping_does_not_matter():
    c, r = token_counts.counter("byte_bpe_50k.json"), random.Random(4)
    for _ in range(100):
        f, g, h = (c.state_map("".join(r.choice([*PARTS, " "]) for _ in range(r.randint(0, 5)))) for _ in range(3))
        left = token_counts.Composed(token_counts.Composed(f, g), h)
        right = token_counts.Composed(f, token_counts.Composed(g, h))
        assert left.at(token_counts.START) == right.at(token_counts.START)


def test_a_long_text_without_white_space():
    c, library = token_counts.counter("byte_bpe_50k.json"), tokenizers.Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    for x in ("abcabd" * 60_000, "a" * 200_000, "a1'" * 50_000):
        assert c.count(x, 1 << 12) == len(library.encode(x, add_special_tokens=False).ids)


def test_running_counts_without_white_space(spark):
    library, x = tokenizers.Tokenizer.from_file(P.path("byte_bpe_50k.json")), "don'tstop1234'rest" * 20
    rows = token_counts.running_counts(spark.createDataFrame([(1, x), (2, None), (3, "a b " * 50)], "id long, text string"), "id", chunk_chars=17).collect()
    assert len(rows) == -(-len(x) // 17) + 1 + -(-200 // 17)
    for row in rows:
        text = {1: x, 2: "", 3: "a b " * 50}[row["id"]][: row["end_char"]]
        assert row["tokens"] == len(library.encode(text, add_special_tokens=False).ids)
