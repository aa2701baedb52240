"""Byte-level BPE encoding and decoding with a hierarchical-bitmap rank queue.

A pre-token is a linked list of parts. Every adjacent pair that is in the vocabulary stands in the bucket of
its merge rank. Two levels of bitmaps over the ranks say which buckets have entries: find-first-set on the
upper, then on the lower level gives the next rank without comparing entries. An entry whose pair has changed
meanwhile is skipped when it comes up. A pre-token of n bytes costs O(n) queue steps besides the leftmost-first
order inside one bucket, so that very long pre-tokens aren't quadratic.

Null text: as the empty text, no ids. Ties (equal ranks): the leftmost pair first. Repeated rows are encoded
again; other columns pass through unless they carry a name of an added one, in which case the added one wins.
"""

from __future__ import annotations

import base64
import hashlib
import re
import struct
from collections.abc import Iterator
from functools import lru_cache
from heapq import heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chunkset.llm.common import Memo, bounded_text, parts, raw, read, small_batches, tidy

#: Unicode White_Space; a cell is a run of it and the run of other characters after it. Every pre-token ends with its cell.
SPACE = "\t-\r \x85\xa0" + "".join(map(chr, (0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)))
CELL = re.compile(f"[{SPACE}]*[^{SPACE}]+|[{SPACE}]+")
CACHED_BYTES, CACHED_CHARS = 96 << 20, 64  # a generation, of which a worker keeps two


def merge_ranked(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of one pre-token."""
    if (whole := ranks.get(piece)) is not None:
        return [whole]
    n = len(piece)
    get = ranks.get
    following, before = list(range(1, n + 1)), list(range(-1, n - 1))
    pair = [get(piece[i : i + 2], -1) for i in range(n - 1)]
    pair.append(-1)
    buckets: dict[int, list[int]] = {}
    words: dict[int, int] = {}
    summary = 0
    for i, r in enumerate(pair):
        if r >= 0:
            if r in buckets:
                buckets[r].append(i)
            else:
                buckets[r] = [i]
                w = r >> 6
                words[w] = words.get(w, 0) | 1 << (r & 63)
                summary |= 1 << w
    while summary:
        w = (summary & -summary).bit_length() - 1
        bits = words[w]
        r = w << 6 | (bits & -bits).bit_length() - 1
        bucket = buckets[r]
        i = heappop(bucket)
        if not bucket:
            del buckets[r]
            words[w] = bits = bits & (bits - 1)
            if not bits:
                summary &= summary - 1
        if pair[i] != r:
            continue
        j = following[i]
        k = following[i] = following[j]
        pair[j] = -1
        if k < n:
            before[k] = i
            pair[i] = r = get(piece[i : following[k]], -1)
            if r >= 0:
                if r in buckets:
                    heappush(buckets[r], i)
                else:
                    buckets[r] = [i]
                    w = r >> 6
                    words[w] = words.get(w, 0) | 1 << (r & 63)
                    summary |= 1 << w
        else:
            pair[i] = -1
        p = before[i]
        if p >= 0:
            pair[p] = r = get(piece[p:k], -1)
            if r >= 0:
                if r in buckets:
                    heappush(buckets[r], p)
                else:
                    buckets[r] = [p]
                    w = r >> 6
                    words[w] = words.get(w, 0) | 1 << (r & 63)
                    summary |= 1 << w
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : following[i]]])
        i = following[i]
    return out


class Codec:
    """Encoder and decoder for one vocabulary; remembers short cells and pieces, up to a bound."""

    def __init__(self, path: str, pattern: str, cached_bytes: int = CACHED_BYTES):
        import regex

        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.bytes_of = [b""] * (max(self.ranks.values()) + 1)
        for token, i in self.ranks.items():
            self.bytes_of[i] = token
        self.pieces = regex.compile(pattern).findall
        self.memo = Memo(cached_bytes, self.encode_cell)  # of cells and pieces alike: a piece on its own is a cell of one piece

    def encode_piece(self, piece: str) -> bytes:
        return struct.pack(f"<{len(ids := merge_ranked(piece.encode(), self.ranks))}I", *ids)

    def encode_cell(self, cell: str) -> bytes:
        memo, out, pieces = self.memo, [], self.pieces(cell)
        if len(pieces) == 1:
            return self.encode_piece(cell)
        for piece in pieces:
            ids = memo.young.get(piece)
            if ids is None:
                ids = memo.find(piece, self.encode_piece) if len(piece) <= CACHED_CHARS else self.encode_piece(piece)
            out.append(ids)
        return b"".join(out)

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        memo, out = self.memo, []
        for cell in CELL.findall(text):
            ids = memo.young.get(cell)
            if ids is None:
                ids = memo.find(cell) if len(cell) <= CACHED_CHARS else self.encode_cell(cell)
            out.append(ids)
        return b"".join(out)

    def decode(self, ids: bytes) -> bytes:
        of = self.bytes_of
        return b"".join([of[i] for i in np.frombuffer(ids, "<u4").tolist()])


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return name if "/" in name else public_tokenizers.path(name)


@lru_cache(maxsize=2)
def codec(name: str, cached_bytes: int = CACHED_BYTES) -> Codec:
    import public_tokenizers

    return Codec(vocabulary_path(name), public_tokenizers.PATTERN, cached_bytes)


def _apply(df: DataFrame, text_col: str, added: dict[str, str], per_text, vocabulary: str, cached_bytes: int = CACHED_BYTES, forget: bool = False) -> DataFrame:
    keep = [c for c in df.columns if c != text_col and c not in added]
    schema = ", ".join([f"`{c}` {df.schema[c].dataType.simpleString()}" for c in keep] + [f"{c} {t}" for c, t in added.items()])
    kinds = {"long": pa.int64(), "binary": pa.binary(), "string": pa.string()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(vocabulary, cached_bytes)
        for b in parts(batches, len(keep)):
            rows = [per_text(c, raw(x)) for x in b.column(len(keep))]
            new = [pa.array([r[i] for r in rows], kinds[t]) for i, t in enumerate(added.values())]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], *new], [*keep, *added])
        if forget:
            c.memo.clear()

    return small_batches(df).select(*[F.col(f"`{c}`") for c in keep], bounded_text(text_col)).mapInArrow(tidy(run), schema)


def encode_texts(df: DataFrame, text_col: str = "text", vocabulary: str = "byte_bpe_50k.tiktoken", cached_bytes: int = CACHED_BYTES, forget: bool = False) -> DataFrame:
    """Every column but the text, n_tokens and token_ids (little-endian unsigned 32-bit integers). forget: workers drop their caches after each task."""

    def one(c: Codec, x: bytes):
        ids = c.encode(x.decode("utf-8", "replace"))
        return len(ids) // 4, ids

    return _apply(df, text_col, {"n_tokens": "long", "token_ids": "binary"}, one, vocabulary, cached_bytes, forget)


def decode_ids(df: DataFrame, ids_col: str = "token_ids", vocabulary: str = "byte_bpe_50k.tiktoken") -> DataFrame:
    """Every column but the ids, and decoded, the bytes that the ids stand for."""
    return _apply(df, ids_col, {"decoded": "binary"}, lambda c, x: (c.decode(x),), vocabulary)


def round_trip_digests(df: DataFrame, text_col: str = "text", vocabulary: str = "byte_bpe_50k.tiktoken") -> DataFrame:
    """Encodes and decodes in one pass: n_tokens, ids_sha256, decoded_sha256 instead of the text."""

    def one(c: Codec, x: bytes):
        ids = c.encode(x.decode("utf-8", "replace"))
        return len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(c.decode(ids)).hexdigest()

    return _apply(df, text_col, {"n_tokens": "long", "ids_sha256": "string", "decoded_sha256": "string"}, one, vocabulary)


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip_digests(read(spark, sf_dir, "documents").select("doc_id", "text"))
