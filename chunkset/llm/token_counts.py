"""Token counts by a compiled finite-state tokenizer.

The merges of a byte-level BPE vocabulary are compiled into a deterministic transducer over the bytes of a
pre-token. A state holds the longest suffix read that some vocabulary entry begins with and, for each position in
it, the last token of the encoding up to there and that encoding's token count relative to the current one; nothing
further back can matter. A transition carries the number of tokens by which the encoding grows (or shrinks). States
and transitions are compiled when first met, and kept up to a bound.

A text is read in chunks. Between two characters the state is that of the pre-token pattern (in a run of letters, digits, other
signs or white space, or after the start of a contraction), what it holds back for want of a next character, and the transducer's own. A
chunk's state map takes a state before the chunk to the state after it and the tokens that come in between; it is worked out for the
states that are asked for, and no further than to the first place at which all of them agree, where white space follows another character.
Maps compose, so a prefix scan gives the count up to every chunk's end. Texts spread over many tasks send only states: each chunk
is read from the start state and from the states that the chunk before it may end in, until no new ones come up.

Null text: the empty text, 0 tokens. Special strings of the vocabulary inside a text are one token each, as the
library treats them by default. Repeated rows are counted again; extra columns pass through, added ones win.
"""

from __future__ import annotations

import json
import pickle
from collections.abc import Iterator
from functools import lru_cache
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chunkset.llm.byte_bpe import CELL, vocabulary_path
from chunkset.llm.common import Memo, bounded_text, parts, raw, read, saved, small_batches

MAX_STATES, CACHED_BYTES, CACHED_CHARS, CHUNK_CHARS = 200_000, 48 << 20, 64, 1 << 16
INNER = (b"", ((-1, 0),))
CLASSES = {"L": r"\p{L}", "N": r"\p{N}", "P": r"[^\s\p{L}\p{N}]"}


class State(NamedTuple):
    """kind: L, N, P in a run of letters, digits or other signs; W in white space; empty between pre-tokens. held: characters that wait for the
    next one, the last white space or the start of a contraction. inner: the transducer's state inside the pre-token."""

    kind: str = ""
    held: str = ""
    inner: tuple = INNER


START = State()


def printable_bytes() -> dict[str, int]:
    """Character that stands for each byte in the vocabulary file: itself if printable, else the next free one from 256."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


class Transducer:
    def __init__(self, vocab: dict[bytes, int], merges: list[tuple[bytes, bytes]]):
        self.merge = {(vocab[a], vocab[b]): (i, vocab[a + b]) for i, (a, b) in enumerate(merges)}
        self.vocab, self.token = vocab, {i: t for t, i in vocab.items()}
        self.prefixes = {t[:n] for t in vocab for n in range(len(t) + 1)}
        self.adjacent: dict[tuple[int, int], bool] = {}
        self.clear()

    def clear(self) -> None:
        self.states, self.number, self.step = [INNER], {INNER: 0}, {}

    def encode(self, piece: bytes) -> list[int]:
        """Plain merging, for short strings: what the transducer is compiled from."""
        ids = [self.vocab[piece[i : i + 1]] for i in range(len(piece))]
        while len(ids) > 1:
            found = [(self.merge[p][0], i) for i, p in enumerate(zip(ids, ids[1:], strict=False)) if p in self.merge]
            if not found:
                break
            _, i = min(found)
            ids[i : i + 2] = [self.merge[ids[i], ids[i + 1]][1]]
        return ids

    def stands(self, a: int, b: int) -> bool:
        """Whether an encoding can have a and b side by side."""
        if (a, b) not in self.adjacent:
            if len(self.adjacent) > 2_000_000:
                self.adjacent.clear()
            self.adjacent[a, b] = self.encode(self.token[a] + self.token[b]) == [a, b]
        return self.adjacent[a, b]

    def compile(self, state: int, byte: int) -> int:
        """The transition for byte: its target and, in the low 10 bits, the tokens it adds plus 512."""
        suffix, window = self.states[state]
        suffix += bytes((byte,))
        cut = 0
        while suffix[cut:] not in self.prefixes:
            cut += 1
        for at in range(cut, len(suffix)):
            token = self.vocab.get(suffix[at:])
            if token is not None and (window[at][0] < 0 or self.stands(window[at][0], token)):
                break
        else:
            raise ValueError("the vocabulary has no token for a byte")
        grows = window[at][1] + 1
        new = (suffix[cut:], (*((t, c - grows) for t, c in window[cut:]), (token, 0)))
        target = self.number.setdefault(new, len(self.states))
        if target == len(self.states):
            self.states.append(new)
        self.step[state << 8 | byte] = packed = target << 10 | (grows + 512)
        return packed

    def feed(self, inner: tuple, piece: bytes) -> tuple[tuple, int]:
        """The state after a further piece of a pre-token, and the tokens that it adds."""
        if len(self.states) > MAX_STATES:
            self.clear()
        state = self.number.setdefault(inner, len(self.states))
        if state == len(self.states):
            self.states.append(inner)
        get, total = self.step.get, 0
        for byte in piece:
            e = get(state << 8 | byte)
            if e is None:
                e = self.compile(state, byte)
            state = e >> 10
            total += (e & 1023) - 512
        return self.states[state], total

    def count(self, piece: bytes) -> int:
        return self.feed(INNER, piece)[1]


class Chunk:
    """The state map of a chunk, for the states that at() is asked for."""

    def __init__(self, counter: Counter, text: str):
        cells = CELL.finditer(text)
        next(cells, None)
        cut = next((m.start() for m in cells), None)
        self.counter, self.known = counter, {}
        self.head, self.rest = (text, None) if cut is None else (text[:cut], text[cut:])
        self.after: tuple[State, int] | None = None  # of the rest, which starts between pre-tokens whatever came before

    def at(self, state: State) -> tuple[State, int]:
        if state not in self.known:
            end, n = self.counter.advance(state, self.head)
            if self.rest is not None:
                self.after = self.after or self.counter.advance(START, self.rest)
                end, n = self.after[0], n + self.counter.left_over(end) + self.after[1]
            self.known[state] = end, n
        return self.known[state]


class Composed:
    """The state map of two chunks, or runs of chunks, one after the other."""

    def __init__(self, first: Chunk | Composed, second: Chunk | Composed):
        self.first, self.second, self.known = first, second, {}

    def at(self, state: State) -> tuple[State, int]:
        if state not in self.known:
            between, n = self.first.at(state)
            end, more = self.second.at(between)
            self.known[state] = end, n + more
        return self.known[state]


class Known:
    """A state map that is given as a table."""

    def __init__(self, known: dict[State, tuple[State, int]]):
        self.at = known.__getitem__


class Counter:
    def __init__(self, path: str, pattern: str):
        import regex

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        of = printable_bytes()
        raw = lambda s: bytes(of[c] for c in s)
        special = {x["content"] for x in spec["added_tokens"]}
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in spec["model"]["merges"]]
        vocab = {raw(t): i for t, i in spec["model"]["vocab"].items() if t not in special}
        self.special = sorted(special, key=len, reverse=True)
        self.transducer = Transducer(vocab, [(raw(a), raw(b)) for a, b in merges])
        self.pieces = regex.compile(pattern).findall
        self.white = regex.compile(r"\s*")
        self.runs = {kind: regex.compile(f"{c}*") for kind, c in CLASSES.items()}
        self.by_cell = Memo(CACHED_BYTES, self.cell)

    def cell(self, cell: str) -> int:
        return sum(self.transducer.count(p.encode()) for p in self.pieces(cell))

    def whole(self, text: str) -> int:
        memo, total = self.by_cell, 0
        for cell in CELL.findall(text):
            n = memo.young.get(cell)
            total += self.count_cell(cell) if n is None else n
        return total

    def advance(self, state: State, text: str) -> tuple[State, int]:
        """The state after a further piece of a text, and the tokens that it adds, those of an unfinished pre-token included."""
        n = 0
        if state.kind in self.runs:
            run = self.runs[state.kind].match(text).group()
            inner, n = self.transducer.feed(state.inner, run.encode())
            if len(run) == len(text):
                return State(state.kind, "", inner), n
            text = text[len(run) :]
        elif state.kind == "W":
            run = state.held + self.white.match(text).group()
            text = text[len(run) - 1 :]
            inner, n = self.transducer.feed(state.inner, run[:-1].encode())
            if not text:
                return State("W", run[-1], inner), n
            if run[-1] == " ":  # goes with what follows
                text = " " + text
            else:
                n += self.cell(run[-1])
        else:
            text = state.held + text
        if not text:
            return START, n
        cells = CELL.findall(text)
        n += sum(map(self.count_cell, cells[:-1]))
        *closed, last = self.pieces(cells[-1])
        held = ""
        if last == "'":
            held = last
        elif last in ("r", "v", "l") and closed and closed[-1] == "'":
            held = closed.pop() + last
        n += sum(self.transducer.count(p.encode()) for p in closed)
        if held:
            return State("", held), n
        if self.white.fullmatch(last):
            inner, more = self.transducer.feed(INNER, last[:-1].encode())
            return State("W", last[-1], inner), n + more
        inner, more = self.transducer.feed(INNER, last.encode())
        if last[0] == "'" and self.runs["L"].fullmatch(last, 1) and len(last) > 1:  # a whole contraction
            return START, n + more
        kind = next(k for k, run in self.runs.items() if run.fullmatch(last[-1]))
        return State(kind, "", inner), n + more

    def left_over(self, state: State) -> int:
        """Tokens that the text's end, or white space after another character, adds."""
        if state.kind == "W":
            return self.transducer.feed(state.inner, state.held.encode())[1]
        return self.cell(state.held)

    def count_cell(self, cell: str) -> int:
        n = self.by_cell.young.get(cell)
        if n is None:
            n = self.by_cell.find(cell) if len(cell) <= CACHED_CHARS else self.cell(cell)
        return n

    def state_map(self, chunk: str) -> Chunk:
        return Chunk(self, chunk)

    def scan(self, maps: list) -> list:
        """Composition of the first 1, 2, ... maps, in log2(n) rounds of independent compositions."""
        out, gap = list(maps), 1
        while gap < len(out):
            out = [Composed(out[i - gap], x) if i >= gap else x for i, x in enumerate(out)]
            gap *= 2
        return out

    def closed(self, state_map) -> int:
        """Tokens of a text with this map."""
        end, n = state_map.at(START)
        return n + self.left_over(end)

    def segment(self, text: str, chunk_chars: int) -> int:
        if len(text) <= chunk_chars:
            return self.whole(text)
        return self.closed(self.scan([self.state_map(text[i : i + chunk_chars]) for i in range(0, len(text), chunk_chars)])[-1])

    def split_special(self, text: str) -> tuple[list[str], int]:
        parts, n = [text], 0
        for s in self.special:
            if s in text:
                parts = [y for x in parts for y in x.split(s)]
                n = text.count(s) + n
        return parts, n

    def count(self, text: str, chunk_chars: int = CHUNK_CHARS) -> int:
        parts, n = self.split_special(text)
        return n + sum(self.segment(p, chunk_chars) for p in parts)


@lru_cache(maxsize=2)
def counter(name: str) -> Counter:
    import public_tokenizers

    return Counter(vocabulary_path(name), public_tokenizers.PATTERN)


def count_tokens(df: DataFrame, text_col: str = "text", vocabulary: str = "byte_bpe_50k.json", limit: int = 512, chunk_chars: int = CHUNK_CHARS) -> DataFrame:
    """Every column but the text, n_bytes, n_tokens and over_limit (more than limit tokens)."""
    keep = [c for c in df.columns if c not in (text_col, "n_bytes", "n_tokens", "over_limit")]
    schema = ", ".join([f"`{c}` {df.schema[c].dataType.simpleString()}" for c in keep] + ["n_bytes long, n_tokens long"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = counter(vocabulary)
        for b in parts(batches, len(keep)):
            texts = [raw(x) for x in b.column(len(keep))]
            counts = [c.count(x.decode("utf-8", "replace"), chunk_chars) for x in texts]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(map(len, texts), pa.int64()), pa.array(counts, pa.int64())], [*keep, "n_bytes", "n_tokens"])

    counted = small_batches(df).select(*[F.col(f"`{c}`") for c in keep], bounded_text(text_col)).mapInArrow(run, schema)
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)


def running_counts(df: DataFrame, id_col: str, text_col: str = "text", vocabulary: str = "byte_bpe_50k.json", chunk_chars: int = CHUNK_CHARS) -> DataFrame:
    """(id, chunk, end_char, tokens): for each chunk of each text, the tokens of the text cut after that chunk.

    Chunks of one text are read by different tasks; only states and counts meet. id_col must be unique. A special string counts as the
    plain text that it is.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    pieces = small_batches(df).select(F.col(id_col).alias("id"), text.alias("text")).select("id", "text", F.explode(F.sequence(F.lit(0), F.greatest(F.lit(0), F.floor((F.length("text") - 1) / chunk_chars)).cast("int"))).alias("chunk"))
    pieces = saved(pieces.select("id", "chunk", F.substr("text", F.col("chunk") * chunk_chars + 1, F.lit(chunk_chars)).alias("piece"), F.least(F.length("text"), (F.col("chunk") + 1) * chunk_chars).alias("end_char")), "text-chunks")
    kind = df.schema[id_col].dataType.simpleString()

    def read_chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = counter(vocabulary)
        for b in batches:
            ends = [c.state_map(x).at(pickle.loads(s)) for x, s in zip(b.column("piece").to_pylist(), b.column("entry").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("chunk"), b.column("entry"), pa.array([pickle.dumps(e) for e, _ in ends], pa.binary()), pa.array([n for _, n in ends], pa.int64())], ["id", "chunk", "entry", "end", "n"])

    asked, maps = pieces.select("id", "chunk").withColumn("entry", F.lit(pickle.dumps(START))), None
    while maps is None or not asked.isEmpty():
        new = pieces.join(asked, ["id", "chunk"]).select("id", "chunk", "entry", "piece").repartition("id", "chunk", "entry")
        new = saved(new.mapInArrow(read_chunks, f"id {kind}, chunk int, entry binary, end binary, n long"), "state-maps")
        maps = new if maps is None else maps.unionByName(new)
        follows = maps.select("id", (F.col("chunk") + 1).alias("chunk"), F.col("end").alias("entry")).distinct().join(pieces.select("id", "chunk"), ["id", "chunk"])
        asked = saved(follows.join(maps, ["id", "chunk", "entry"], "left_anti"), "states-asked")

    def scanned(pdf):
        c = counter(vocabulary)
        each = [Known({pickle.loads(s): (pickle.loads(e), n) for s, e, n in zip(g["entry"], g["end"], g["n"], strict=True)}) for _, g in pdf.sort_values("chunk").groupby("chunk")]
        ends = pdf.drop_duplicates("chunk").sort_values("chunk")[["id", "chunk", "end_char"]]
        return ends.assign(tokens=[c.closed(m) for m in c.scan(each)])

    return maps.join(pieces.select("id", "chunk", "end_char"), ["id", "chunk"]).groupBy("id").applyInPandas(scanned, f"id {kind}, chunk int, end_char int, tokens long")


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(read(spark, sf_dir, "documents").select("doc_id", "text"))
