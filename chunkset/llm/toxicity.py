"""Toxicity of deobfuscated text: a noisy channel over character lattices, then weights of restored words.

A character language model (interpolated trigrams) is counted over all documents. Spans that look disguised, words with
digits or signs inside, letters set apart, letters repeated, become lattices: each sign may stand for the letters
that resemble it or for nothing, a repetition for one or two letters, a separator for nothing or a space. The Viterbi path, under
the model and the channel's costs, is the restored span; disguises may be mixed. Time is linear in a text, also in one long token. Restored texts are then scored by a logistic model of telling
words and word beginnings, which are learned from the labelled rows that aren't held out (at most SAMPLE_ROWS).

Null and empty texts: no words, the score of the intercept. Without labels of both kinds every score is the share
of toxic labels, or 0. Repeated rows score alike. Extra columns pass through, added ones win. Empty tables give empty results.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chunkset.llm.common import Memo, bounded_text, parts, raw, read, saved, small_batches
from chunkset.llm.quality import held_out, labelled_sample

SAMPLE_ROWS, FEATURES, BEGINNINGS, SUPPORT = 20_000, 600, (4, 5, 6), 4
#: Letters that a sign or digit may stand for (fixed values).
LOOKS = {"0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "il", "|": "il", "+": "t", "€": "e", "(": "c", "*": "aeiou", "#": "h", "¡": "i"}
SIGN_COST, DROP_COST, DOUBLE_COST, SPACE_COST = 0.7, 12.0, 1.0, 3.0
LETTER = r"[^\W\d_]"
WORD = re.compile(f"{LETTER}+")
SIGNS, FIRST_SIGNS, LAST_SIGNS = re.compile(r"[0-9@$!|+€(*#¡]+"), re.compile(r"[0-9@$|+€¡]+"), re.compile(r"[0-9$]+(?![^\s.,;:!?)])")
ONE, GAP = rf"(?:{LETTER}|[0-9@$!|+€(#¡])", r"(?:[ ._*,-]|\s)"
APART = re.compile(rf"(?<![^\W_]){ONE}(?:{GAP}+{ONE}){{2,}}(?![^\W_])")
REPEATED = re.compile(rf"({LETTER})\1\1")
TOKEN = re.compile(r"\S+")
SAME = re.compile(r"(.)\1*", re.DOTALL)
#: Classes of characters: 0 none of the letters, then a to z, then the accented letters of Latin-1, then any other letter.
CLASSES = 28 + 62
SPAN_CHARS, CACHED_BYTES = 64, 16 << 20


def class_table() -> np.ndarray:
    table = np.full(0x250, 0, np.int64)
    for c in range(0x250):
        if chr(c).isalpha():
            low = ord(chr(c).lower()[0])
            table[c] = low - 96 if 97 <= low <= 122 else 27 + low - 0xC0 if 0xC0 <= low <= 0xFF else CLASSES - 1
    return table


CLASS_OF = class_table()


def classes(text: str) -> np.ndarray:
    code = np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32).astype(np.int64)
    return np.where(code < 0x250, CLASS_OF[np.minimum(code, 0x24F)], np.where(code >= 0x2C0, CLASSES - 1, 0))


def trigram_counts(texts: Iterator[str]) -> np.ndarray:
    total = np.zeros(CLASSES**3, np.int64)
    for text in texts:
        c = classes(text)
        c = np.concatenate([[0, 0], c, [0]])
        total += np.bincount((c[:-2] * CLASSES + c[1:-1]) * CLASSES + c[2:], minlength=CLASSES**3)
    return total


@dataclass
class Model:
    """cost[a, b, c]: minus the log-probability of class c after a, b."""

    cost: np.ndarray

    @staticmethod
    def of(counts: np.ndarray) -> Model:
        n3 = counts.reshape(CLASSES, CLASSES, CLASSES).astype(float)
        n2, n1 = n3.sum(0), n3.sum((0, 1))
        p1 = (n1 + 0.5) / (n1.sum() + 0.5 * CLASSES)
        p2 = (n2 + 5 * p1) / (n2.sum(1, keepdims=True) + 5)
        p3 = (n3 + 5 * p2[None]) / (n3.sum(2, keepdims=True) + 5)
        return Model(-np.log(p3).astype(np.float32))


def lattice(span: str) -> Iterator[list[tuple[str, float]]]:
    """For each position the strings that it may stand for, with the channel's cost."""
    for m in SAME.finditer(span.lower()):
        c, n = m.group(1), m.end() - m.start()
        if c.isalpha():
            yield [(c, 0.0), (c + c, DOUBLE_COST)] if n > 2 else [(c * n, 0.0)]
        elif c in LOOKS:
            yield [(x, SIGN_COST) for x in LOOKS[c]] + [("", DROP_COST if n < 3 else 0.0)]
        else:
            yield [("", 0.0), (" ", SPACE_COST)]


def inside(text: str) -> Iterator[int]:
    """Where signs stand in words: between letters, before two at a token's start, after two at a word's end."""
    for m in SIGNS.finditer(text):
        a, b = m.span()
        letter = a > 0 and text[a - 1].isalpha()
        if letter:
            if text[b : b + 1].isalpha() or a > 1 and text[a - 2].isalpha() and LAST_SIGNS.match(text, a):
                yield a
        elif (not a or text[a - 1].isspace()) and text[b : b + 1].isalpha() and text[b + 1 : b + 2].isalpha() and FIRST_SIGNS.fullmatch(text, a, b):
            yield a


def class_of(x: str) -> int:
    return int(CLASS_OF[ord(x)]) if ord(x) < 0x250 else CLASSES - 1


def restore(span: str, model: Model) -> str:
    """The best path: states are the last two classes, as the model sees no further back. A path is a chain of back-pointers; where only one
    state is left, what all paths share is written out, so that time is linear in the span and memory in its longest doubtful stretch."""
    cost, out = model.cost, []
    best: dict[tuple[int, int], tuple[float, tuple | None]] = {(0, 0): (0.0, None)}

    def written(path: tuple | None) -> None:
        back = []
        while path is not None:
            path, string = path
            back.append(string)
        out.extend(reversed(back))

    for options in lattice(span):
        if len(best) == 1 and len(options) == 1:  # plain letters in no doubt
            ((p, q), (c, path)), string = next(iter(best.items())), options[0][0]
            if path is not None:
                written(path)
            out.append(string)
            for x in string:
                p, q = q, class_of(x)
            best = {(p, q): (0.0, None)}
            continue
        new: dict[tuple[int, int], tuple[float, tuple | None]] = {}
        strings = [(string, [class_of(x) for x in string], price) for string, price in options]
        for (a, b), (c, path) in best.items():
            for string, ks, price in strings:
                p, q, total = a, b, c + price
                for k in ks:
                    total += float(cost[p, q, k])
                    p, q = q, k
                if (p, q) not in new or total < new[p, q][0]:
                    new[p, q] = (total, (path, string))
        best = new
        if len(best) == 1:
            (state, (c, path)) = next(iter(best.items()))
            written(path)
            best = {state: (0.0, None)}
    written(min(best.items(), key=lambda x: x[1][0] + float(cost[x[0][0], x[0][1], 0]))[1][1])
    return "".join(out)


class Restorer:
    def __init__(self, model: Model):
        self.model = model
        self.memo = Memo(CACHED_BYTES, lambda span: restore(span, model))

    def span(self, span: str) -> str:
        found = self.memo.young.get(span)
        if found is None:
            found = self.memo.find(span) if len(span) <= SPAN_CHARS else restore(span, self.model)
        return found

    def restored(self, text: str) -> Iterator[tuple[int, int, str]]:
        """(start, end, what stands there) of each disguised span."""
        taken = -1
        ends = {m.start(): m.end() for m in APART.finditer(text) if any(map(str.isalpha, m.group()))}
        for places in (inside(text), (m.start() for m in REPEATED.finditer(text))):
            seen = -1  # places come in order, and none reaches past its token: each token is looked at once
            for a in places:
                if a < seen:
                    continue
                seen = b = TOKEN.match(text, a).end()
                while a > 0 and not text[a - 1].isspace():
                    a -= 1
                if "@" not in text[a:b] or "." not in text[a:b]:  # an address is what it is
                    ends[a] = max(b, ends.get(a, 0))
        for a in sorted(ends):
            if a < taken:
                continue
            taken = ends[a]
            core = text[a:taken].strip(".,;:!?)(\"'*#%&")
            found = self.span(core)
            if found and found != core.lower():
                yield a, taken, found

    def text(self, text: str) -> str:
        out, at = [], 0
        for a, b, found in self.restored(text):
            out += [text[at:a], found]
            at = b
        return "".join([*out, text[at:]])


def telling(word: str) -> tuple[str, ...]:
    """What a word may be recognised by: itself and how it begins."""
    return (f"={word}", *(word[:n] for n in BEGINNINGS if len(word) >= n))


def words_of(text: str, restorer: Restorer) -> Counter:
    words = Counter(WORD.findall(text.lower()))
    for _, _, found in restorer.restored(text):
        words.update(WORD.findall(found))
    return words


def language_model(docs: DataFrame, text_col: str = "text") -> Model:
    """Counted over every document; a task sends its nonzero counts, of which there are CLASSES ** 3 at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(CLASSES**3, np.int64)
        for b in parts(batches, 0):
            total += trigram_counts(["  ".join(raw(t).decode("utf-8", "replace") for t in b.column(0))])
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["at", "n"])

    rows = small_batches(docs).select(bounded_text(text_col)).mapInArrow(run, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).toArrow()
    counts = np.zeros(CLASSES**3, np.int64)
    counts[rows.column("at").to_numpy()] = rows.column("n").to_numpy()
    return Model.of(counts)


@dataclass
class Scorer:
    features: dict[str, int]
    weight: np.ndarray
    intercept: float


def columns_of(words: Counter, features: dict[str, int], memo: Memo | None = None) -> dict[int, int]:
    out: dict[int, int] = {}
    for w, n in words.items():
        known = memo.young.get(w) if memo else None
        if known is None:
            known = memo.find(w) if memo and len(w) <= SPAN_CHARS else tuple(features[t] for t in telling(w) if t in features)
        for f in known:
            out[f] = out.get(f, 0) + n
    return out


def train(docs: DataFrame, labels: DataFrame, model: Model, label: str = "toxic", sample_rows: int = SAMPLE_ROWS) -> Scorer:
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model.cost)

    def words_in(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r = Restorer(Model(shared.value))
        for b in parts(batches, 0):
            words = [words_of(raw(t).decode("utf-8", "replace"), r) for t in b.column(0)]
            yield pa.RecordBatch.from_arrays([b.column(2), b.column(1), pa.array([list(w) for w in words], pa.list_(pa.string())), pa.array([list(w.values()) for w in words], pa.list_(pa.int64()))], ["doc_id", "y", "words", "counts"])

    rows = labelled_sample(small_batches(docs), labels, label, sample_rows).select(bounded_text(), "label_is", F.col("doc_id").cast("long").alias("doc_id"))
    rows = saved(rows.mapInArrow(words_in, "doc_id long, y int, words array<string>, counts array<long>"), "toxic-words")
    totals = rows.agg(F.sum("y").alias("bad"), F.count(F.lit(1)).alias("n")).first()
    n, bad = totals["n"] or 0, totals["bad"] or 0
    if not 0 < bad < n:
        p = bad / n if n else 0.0
        return Scorer({}, np.zeros(0), float(np.clip(np.log(max(p, 1e-9) / max(1 - p, 1e-9)), -30, 30)))
    # documents of either kind that each feature stands in; toxic ones decide which features are candidates
    word, begin = F.col("w"), [F.when(F.length("w") >= k, F.substring("w", 1, k)) for k in BEGINNINGS]
    names = F.array(F.concat(F.lit("="), word), *begin)
    long_rows = rows.select("doc_id", "y", F.explode("words").alias("w")).select("doc_id", "y", F.explode(names).alias("f")).filter("f is not null").distinct()
    counted = long_rows.groupBy("f").agg(F.sum("y").alias("b"), F.count(F.lit(1)).alias("d")).filter(F.col("b") >= SUPPORT)
    gain = F.log((F.col("b") + 0.5) / (bad + 1.0)) - F.log((F.col("d") - F.col("b") + 0.5) / (n - bad + 1.0))
    top = counted.withColumn("gain", gain).filter("gain > 1").orderBy(F.desc(F.col("gain") * F.sqrt("b")), "f").limit(FEATURES).collect()
    features = {r["f"]: i for i, r in enumerate(top)}

    def chosen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [columns_of(dict(zip(w, c, strict=True)), features) for w, c in zip(b.column("words").to_pylist(), b.column("counts").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("y"), pa.array([list(f) for f in found], pa.list_(pa.int64())), pa.array([list(f.values()) for f in found], pa.list_(pa.int64()))], ["doc_id", "y", "at", "n"])

    t = rows.mapInArrow(chosen, "doc_id long, y int, at array<long>, n array<long>").toArrow().sort_by("doc_id")
    x = np.zeros((t.num_rows, len(features)), np.float32)
    for i, (at, c) in enumerate(zip(t.column("at").to_pylist(), t.column("n").to_pylist(), strict=True)):
        x[i, at] = np.log1p(c)
    weight, intercept = logistic(x, t.column("y").to_numpy().astype(np.float32))
    return Scorer(features, weight, intercept)


def logistic(x: np.ndarray, y: np.ndarray, rounds: int = 400, penalty: float = 1e-4) -> tuple[np.ndarray, float]:
    """Accelerated gradient descent; weights of telling features stay at or above zero: clean words excuse nothing."""
    n, d = x.shape
    w, b = np.zeros(d + 1, np.float32), 0
    x1 = np.hstack([x, np.ones((n, 1), np.float32)])
    step = 4.0 / max(float(np.linalg.norm(x1.T @ x1 / n, 2)), 1e-6)
    ahead = w.copy()
    for k in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x1 @ ahead, -30, 30)))
        new = ahead - step * (x1.T @ (p - y) / n + penalty * np.append(ahead[:-1], 0))
        new[:-1] = np.maximum(new[:-1], 0)
        ahead = new + k / (k + 3) * (new - w)
        w = new.astype(np.float32)
    return w[:-1].astype(float), float(w[-1]) + b


def score(docs: DataFrame, model: Model, scorer: Scorer, text_col: str = "text", with_text: bool = False) -> DataFrame:
    """docs without the text, with score (and the restored text, if asked for)."""
    keep = [c for c in docs.columns if c not in (text_col, "score", "restored")]
    schema = ", ".join([f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep] + ["score double"] + ["restored string"] * with_text)
    shared = docs.sparkSession.sparkContext.broadcast((model.cost, scorer.features, scorer.weight, scorer.intercept))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cost, features, weight, intercept = shared.value
        r = Restorer(Model(cost))
        memo = Memo(CACHED_BYTES, lambda w: tuple(features[t] for t in telling(w) if t in features))
        for b in parts(batches, len(keep)):
            texts = [raw(t).decode("utf-8", "replace") for t in b.column(len(keep))]
            margins = []
            for t in texts:
                found = columns_of(words_of(t, r), features, memo)
                margins.append(intercept + sum(weight[f] * np.log1p(n) for f, n in found.items()))
            p = 1 / (1 + np.exp(-np.clip(np.array(margins, float), -30, 30)))
            extra = [pa.array([r.text(t) for t in texts], pa.string())] if with_text else []
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(p), *extra], [*keep, "score", *["restored"] * with_text])

    return small_batches(docs).select(*[F.col(f"`{c}`") for c in keep], bounded_text(text_col)).mapInArrow(run, schema)


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    model = language_model(docs)
    scorer = train(docs, read(spark, sf_dir, "labels"), model)
    return score(docs, model, scorer).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
