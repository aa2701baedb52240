"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

A text's features are the hashed words with damped counts, a dozen statistics of its structure, and its declared
length as metadata. The machine's pairwise term is the sum over the factors of the squared sum less the sum of squares,
so that a score costs time linear in the features. It is fitted on a bounded sample of labelled rows (SAMPLE_ROWS,
the first by a hash of the id); every text is scored whole.

Null and empty texts have no words and the statistics of an empty text; they get the score that these lead to. A null
n_chars is taken from the text. Repeated rows score alike. Extra columns pass through, added ones win.
Without labelled rows every score is 0.5, with rows of one kind all are of that kind. An empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from chunkset.llm.common import Memo, bounded_text, parts, raw, read, saved, small_batches, tidy

SAMPLE_ROWS, BUCKETS, FACTORS, EPOCHS, BATCH = 8_000, 1 << 16, 8, 4, 128
CACHED_BYTES = 16 << 20
STATISTICS = ("bias", "length", "word_length", "distinct", "upper", "digit", "mark", "symbol", "line", "repeat", "top", "declared")


@dataclass
class Machine:
    w0: float
    w: np.ndarray
    v: np.ndarray

    def margin(self, at: np.ndarray, x: np.ndarray) -> float:
        vx = self.v[at] * x[:, None]
        return float(self.w0 + self.w[at] @ x + 0.5 * (vx.sum(0) ** 2 - (vx**2).sum(0)).sum())


def bucket(word: bytes) -> int:
    return crc32(word) % BUCKETS


class Reader:
    """Turns texts into features; remembers the buckets of words."""

    def __init__(self):
        self.memo = Memo(CACHED_BYTES, bucket)

    def features(self, text: bytes, declared: int | None) -> tuple[np.ndarray, np.ndarray]:
        words = text.split()
        counts = Counter(words)
        memo = self.memo
        at = [memo.young.get(w) or (memo.find(w) if len(w) <= 64 else bucket(w)) for w in counts]
        n = len(words)
        tf = np.fromiter(counts.values(), np.float64, len(counts))
        x = np.log1p(tf)
        x /= max(np.sqrt((x**2).sum()), 1e-9)
        stats = statistics(text, n, tf, words, declared)
        return np.append(np.array(at, np.int64), BUCKETS + np.arange(len(STATISTICS))), np.append(x, stats)


def statistics(text: bytes, n: int, tf: np.ndarray, words: list[bytes], declared: int | None) -> np.ndarray:
    size = max(len(text), 1)
    byte = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    letters = max(byte[65:91].sum() + byte[97:123].sum(), 1)
    marks = byte[[33, 34, 39, 40, 41, 44, 46, 58, 59, 63]].sum()
    symbols = byte[[35, 36, 37, 38, 42, 60, 61, 62, 64, 91, 92, 93, 94, 95, 96, 123, 124, 125, 126]].sum()
    repeats = sum(a == b for a, b in zip(words, words[1:], strict=False)) if n else 0
    return np.array([
        1.0,
        np.log1p(size) / 10,
        size / max(n, 1) / 10 if n else 0.0,
        len(tf) / max(n, 1),
        byte[65:91].sum() / letters,
        min(1.0, 5 * byte[48:58].sum() / size),
        min(1.0, 5 * marks / size),
        min(1.0, 10 * symbols / size),
        min(1.0, 20 * byte[10] / size),
        repeats / max(n, 1),
        tf.max() / n if n else 0.0,
        np.log1p(declared if declared is not None else len(text.decode("utf-8", "replace"))) / 10,
    ])


def held_out(id_col: str = "doc_id") -> Column:
    """A null id isn't held out."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(3)) == 1, F.lit(False))


def fit(rows: list[tuple[np.ndarray, np.ndarray, int]], seed: int = 1) -> Machine:
    """Logistic loss, stochastic gradients with per-parameter rates."""
    size = BUCKETS + len(STATISTICS)
    rng = np.random.default_rng(seed)
    m = Machine(0.0, np.zeros(size), rng.normal(0, 0.01, (size, FACTORS)))
    y = np.array([r[2] for r in rows], float)
    if not 0 < y.sum() < len(y):
        return Machine(0.0 if not len(y) else 5.0 * (2 * y[0] - 1), m.w, np.zeros_like(m.v))
    gw, gv, g0 = np.full(size, 1e-6), np.full((size, FACTORS), 1e-6), 1e-6
    for epoch in range(EPOCHS):
        rate = 0.1 / (1 + epoch)
        for part in np.array_split(rng.permutation(len(rows)), max(1, len(rows) // BATCH)):
            at = np.concatenate([rows[i][0] for i in part])
            x = np.concatenate([rows[i][1] for i in part])
            cut = np.append(0, np.cumsum([len(rows[i][0]) for i in part]))[:-1]
            vx = m.v[at] * x[:, None]
            s = np.add.reduceat(vx, cut)
            margin = m.w0 + np.add.reduceat(m.w[at] * x, cut) + 0.5 * (s**2 - np.add.reduceat(vx**2, cut)).sum(1)
            slope = (1 / (1 + np.exp(-np.clip(margin, -30, 30))) - y[part]) / len(part)
            each = np.repeat(slope, np.diff(np.append(cut, len(at))))
            own = np.repeat(s, np.diff(np.append(cut, len(at))), axis=0)
            used, back = np.unique(at, return_inverse=True)
            dw = np.bincount(back, each * x) + 1e-6 * m.w[used]
            dv = each[:, None] * x[:, None] * (own - vx)
            dv = np.stack([np.bincount(back, dv[:, f]) for f in range(FACTORS)], axis=1) + 1e-6 * m.v[used]
            gw[used] += dw**2
            gv[used] += dv**2
            g0 += slope.sum() ** 2
            m.w[used] -= rate * dw / np.sqrt(gw[used])
            m.v[used] -= rate * dv / np.sqrt(gv[used])
            m.w0 -= rate * slope.sum() / np.sqrt(g0)
    return m


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, rows: int = SAMPLE_ROWS) -> DataFrame:
    """docs with the column label, for at most so many labelled rows that aren't held out. The sample's ids are few: they are broadcast."""
    wanted = labels.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max(label).cast("int").alias("label_is"))
    wanted = saved(wanted.orderBy(F.xxhash64("doc_id", F.lit(2)), "doc_id").limit(rows), "labelled")
    return docs.drop("label_is").join(F.broadcast(wanted), "doc_id")


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", sample_rows: int = SAMPLE_ROWS) -> Machine:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = Reader()
        for b in parts(batches, 0):
            made = [reader.features(raw(t), d) for t, d in zip(b.column(0), b.column(1).to_pylist(), strict=True)]
            at, x = ([np.asarray(m[i], t).tobytes() for m in made] for i, t in ((0, np.int32), (1, np.float32)))
            yield pa.RecordBatch.from_arrays([b.column(3), pa.array(at, pa.binary()), pa.array(x, pa.binary()), b.column(2)], ["doc_id", "at", "x", "y"])

    found = labelled_sample(small_batches(docs), labels, label, sample_rows).select(bounded_text(), "n_chars", "label_is", F.col("doc_id").cast("long").alias("doc_id")).mapInArrow(tidy(run), "doc_id long, at binary, x binary, y int")
    t = saved(found, "training-features").toArrow().sort_by("doc_id")
    rows = [(np.frombuffer(a, np.int32).astype(np.int64), np.frombuffer(x, np.float32).astype(float), y) for a, x, y in zip(t.column("at").to_pylist(), t.column("x").to_pylist(), t.column("y").to_pylist(), strict=True)]
    return fit(rows)


def score(docs: DataFrame, machine: Machine, text_col: str = "text", with_text: bool = False) -> DataFrame:
    """docs without the text and n_chars, with score: the probability of a good text. with_text: with all of docs' columns."""
    keep = [c for c in docs.columns if c not in (text_col, "score") and (with_text or c != "n_chars")]
    schema = ", ".join([f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep] + [f"`{text_col}` binary"] * with_text + ["score double"])
    shared = docs.sparkSession.sparkContext.broadcast((machine.w0, machine.w.astype(np.float32), machine.v.astype(np.float32)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, reader, at = Machine(*shared.value), Reader(), len(keep)
        for b in parts(batches, at):
            margins = [m.margin(*reader.features(raw(t), d)) for t, d in zip(b.column(at), b.column(at + 1).to_pylist(), strict=True)]
            p = 1 / (1 + np.exp(-np.clip(np.array(margins, float), -30, 30)))
            yield pa.RecordBatch.from_arrays([*b.columns[: at + with_text], pa.array(p)], [*keep, *[text_col] * with_text, "score"])

    declared = F.col("n_chars").cast("long") if "n_chars" in docs.columns else F.lit(None).cast("long")
    scored = small_batches(docs).select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text_col}`").cast("binary").alias(text_col), declared.alias("declared")).mapInArrow(tidy(run), schema)
    if not with_text:
        return scored
    return scored.select(*[(F.col(f"`{c}`").cast("string") if c == text_col else F.col(f"`{c}`")).alias(c) for c in docs.columns if c != "score"], "score")


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text", "n_chars")
    machine = train(docs, read(spark, sf_dir, "labels"))
    return score(docs, machine).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
