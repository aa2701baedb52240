"""Searching and linking embeddings: additive quantisation, and iterative quantisation with multi-index Hamming tables.

Vectors that are null, zero or of another length than most, or that hold null or non-finite components, take no part in
either operator: they are neither queries nor candidates, and link with nothing. Rows that repeat a vec_id are
vectors of their own; a search returns a vec_id once, with the nearest of its rows, and never the query's own. A null vec_id takes no part in searches.
Ties go to the smaller vec_id. Equal vectors are compared once. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chunkset.llm.common import components, into_blocks, local_components, read, run_starts, saved, small_batches, sorted_runs

SAMPLE_ROWS = 16_384  # an index is fitted on so many vectors at most; every vector is indexed


def usable(df: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(id, vec): the vectors that take part, as the bytes of their components: 32 bits each if they are floats, else 64."""
    v = F.col(vector_col).cast("array<double>")
    sound = F.col(vector_col).isNotNull() & (F.size(vector_col) > 0) & F.forall(v, lambda x: F.coalesce((F.abs(x) < float("inf")) & ~F.isnan(x), F.lit(False))) & F.exists(v, lambda x: x != 0)
    rows = small_batches(df).filter(sound).select(F.col(id_col).cast("long").alias("id"), v.alias("v"))
    usual = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    dim = usual["d"] if usual else 1

    kind = component_type(df, vector_col)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat = (b.column(1).flatten().to_numpy().reshape(-1, dim) + 0.0).astype(kind)  # no negative zeros
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x.tobytes() for x in flat], pa.binary())], ["id", "vec"])

    return rows.filter(F.size("v") == dim).mapInArrow(pack, "id long, vec binary")


def component_type(df: DataFrame, vector_col: str) -> str:
    return "<f4" if df.schema[vector_col].dataType.simpleString() == "array<float>" else "<f8"


def matrix(column, kind: str) -> np.ndarray:
    """Rows of equally long binary values as 64-bit components."""
    values = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if not len(values):
        return np.empty((0, 1))
    return np.frombuffer(b"".join(values.to_pylist()), kind).reshape(len(values), -1).astype(np.float64)


def sample(rows: DataFrame, kind: str, most: int = SAMPLE_ROWS) -> tuple[np.ndarray, np.ndarray]:
    """Ids and vectors of the first rows by a hash of the id."""
    t = rows.orderBy(F.xxhash64("id", F.lit(11)), "id").limit(most).select("id", "vec").toArrow()
    return t.column("id").to_numpy(), matrix(t.column("vec"), kind)


# -- additive quantisation ------------------------------------------------------------------------------------------

BOOKS, WORDS, BEAM, NEIGHBOURS = 32, 64, 4, 20
DATA_ROWS, QUERY_ROWS, FIT_ROWS, STRIPES = 1024, 2048, 1024, 24
#: A row is reranked if its estimate is less than so many standard errors below the k-th best score known so far: of the true nearest about
#: 0.023 fall short, however many rows there are.
SPREADS = 2.0
#: The k-th best score of so many rows of the sample is what a search starts with.
SEED_ROWS = 4096
MEASURES = ("inner product", "distance")


def nearest_words(x: np.ndarray, words: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    d = (words**2).sum(1)[None] - 2 * x @ words.T
    if k == 1:
        at = d.argmin(1)[:, None]
    else:
        at = np.argpartition(d, k - 1, axis=1)[:, :k] if k < d.shape[1] else np.argsort(d, axis=1)
    return at, np.take_along_axis(d, at, 1)


def fit_codebooks(x: np.ndarray, books: int = BOOKS, words: int = WORDS, rounds: int = 8) -> np.ndarray:
    """books x words x dimensions: k-means on what the earlier codebooks leave, then all refitted to the beam's codes at once."""
    rng = np.random.default_rng(5)
    words = min(words, len(x))
    out, left = [], x.copy()
    for _ in range(books):
        c = left[rng.choice(len(left), words, replace=False)].copy()
        for _ in range(rounds):
            hot = (nearest_words(left, c, 1)[0] == np.arange(words)).astype(np.float32)
            n = hot.sum(0)
            c[n > 0] = (hot.T @ left)[n > 0] / n[n > 0, None]
        out.append(c)
        left = left - c[nearest_words(left, c, 1)[0][:, 0]]
    found = np.stack(out)
    for _ in range(2):
        gram, right = 1e-2 * np.eye(books * words), 1e-2 * found.reshape(books * words, -1)
        for i in range(0, len(x), FIT_ROWS):
            part = x[i : i + FIT_ROWS]
            codes = encode(part, found)
            hot = np.zeros((len(part), books * words), np.float32)
            for m in range(books):
                hot[np.arange(len(part)), m * words + codes[:, m]] = 1
            gram += hot.T @ hot
            right = right + hot.T @ part
        found = np.linalg.solve(gram, right).reshape(found.shape)
    return found


def encode(x: np.ndarray, books: np.ndarray, beam: int = BEAM) -> np.ndarray:
    """Codes by beam search: of all continuations of the kept ones, the best stay at each codebook."""
    n, d = x.shape
    left, error = x[:, None, :], (x**2).sum(1)[:, None]
    codes = np.empty((n, 1, 0), np.int64)
    for c in books:
        width = left.shape[1]
        k = min(beam, len(c))
        at, gain = nearest_words(left.reshape(-1, d), c, k)
        total = (error[:, :, None] + gain.reshape(n, width, k)).reshape(n, -1)
        keep = np.argsort(total, axis=1, kind="stable")[:, :beam]
        parent, word = keep // k, np.take_along_axis(at.reshape(n, -1), keep, 1)
        error = np.take_along_axis(total, keep, 1)
        left = np.take_along_axis(left, parent[:, :, None], 1) - c[word]
        codes = np.concatenate([np.take_along_axis(codes, parent[:, :, None], 1), word[:, :, None]], axis=2)
    return codes[np.arange(n), error.argmin(1)]


def decode(codes: np.ndarray, books: np.ndarray) -> np.ndarray:
    return sum(book[codes[:, m]] for m, book in enumerate(books))


class Index:
    """Codebooks, and how the errors of decoded vectors are spread over directions: as a share of a row's squared error."""

    def __init__(self, ids: np.ndarray, x: np.ndarray):
        self.books = fit_codebooks(x).astype(np.float32)
        self.seed_ids, self.seeds = ids[:SEED_ROWS], x[:SEED_ROWS]
        left = x - decode(np.concatenate([encode(x[i : i + FIT_ROWS].astype(np.float32), self.books) for i in range(0, len(x), FIT_ROWS)]), self.books)
        self.spread = left.T @ left / max(float((left**2).sum()), 1e-300)

    def coded(self, x: np.ndarray) -> list[bytes]:
        """For each row its codes, the squared norm of the vector that they stand for, and its distance from the true one."""
        codes = encode(x.astype(np.float32), self.books)
        found = decode(codes, self.books.astype(np.float64))
        stored = np.stack([(found**2).sum(1), np.sqrt(((x - found) ** 2).sum(1))], axis=1)
        return [c.tobytes() + n.tobytes() for c, n in zip(codes.astype(np.uint8), stored, strict=True)]

    def uncoded(self, coded: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        width = len(self.books)
        both = np.frombuffer(b"".join(coded), np.uint8).reshape(len(coded), width + 16)
        norm, error = np.ascontiguousarray(both[:, width:]).view(np.float64).T
        return both[:, :width], norm, error

    def score(self, q: np.ndarray, x: np.ndarray, measure: str) -> np.ndarray:
        """Of all pairs, larger is nearer."""
        return q @ x.T if measure == "inner product" else 2 * q @ x.T - (q**2).sum(1)[:, None] - (x**2).sum(1)[None]

    def seeded(self, ids: np.ndarray, q: np.ndarray, measure: str) -> np.ndarray:
        """The scores of the seeds; a query's own are out, and of repeated ids all but the first."""
        found = self.score(q, self.seeds, measure)
        again = np.ones(len(self.seed_ids), bool)
        again[np.unique(self.seed_ids, return_index=True)[1]] = False
        found[(ids[:, None] == self.seed_ids[None]) | again[None]] = -np.inf
        return found

    def threshold(self, ids: np.ndarray, q: np.ndarray, k: int, measure: str) -> np.ndarray:
        """A score that each query's k-th nearest reaches at least."""
        return np.full(len(q), -np.inf) if len(self.seeds) < k else np.partition(self.seeded(ids, q, measure), -k, axis=1)[:, -k]


class Search:
    """The k nearest of a block of queries, over the blocks of rows that it is given."""

    def __init__(self, index: Index, qids: np.ndarray, q: np.ndarray, threshold: np.ndarray, k: int, measure: str):
        self.index, self.qids, self.q, self.threshold, self.k, self.measure = index, qids, q, threshold.copy(), k, measure
        self.tables = np.einsum("qd,mwd->mqw", q.astype(np.float32), index.books)
        self.spread = np.sqrt(np.maximum(((q @ index.spread) * q).sum(1), 0))
        self.widest = float(np.sqrt(max(np.linalg.eigvalsh(index.spread)[-1], 0)))
        self.best = (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))
        self.reranked = 0

    def estimates(self, codes: np.ndarray, norm: np.ndarray, error: np.ndarray) -> np.ndarray:
        """What the scores may reach, by table look-ups."""
        rough = np.zeros((len(self.q), len(codes)), np.float32)
        for m, table in enumerate(self.tables):
            rough += table[:, codes[:, m]]
        if self.measure == "inner product":
            return rough + SPREADS * self.spread[:, None] * error[None]
        away = np.maximum((self.q**2).sum(1)[:, None] - 2 * rough + norm[None], 0)
        return 2 * SPREADS * self.widest * error[None] * np.sqrt(away) - away - error[None] ** 2

    def block(self, ids: np.ndarray, x: np.ndarray, coded: list[bytes]) -> None:
        order = np.lexsort((ids, *x.T[::-1]))
        same = np.append(False, (x[order][1:] == x[order][:-1]).all(1))
        run = np.arange(len(order)) - np.maximum.accumulate(np.where(same, 0, np.arange(len(order))))
        keep = order[run <= self.k]  # of equal vectors, no more than k + 1 can be among the nearest
        ids, x, coded = ids[keep], x[keep], [coded[i] for i in keep.tolist()]
        # look-ups are made in 32 bits: a little slack, so that rounding excludes nothing
        slack = 1e-5 * (1 + np.abs(self.threshold))
        qi, xi = np.nonzero(self.estimates(*self.index.uncoded(coded)) >= (self.threshold - np.where(np.isfinite(slack), slack, 0))[:, None])
        other = ids[xi] != self.qids[qi]
        qi, xi = qi[other], xi[other]
        self.reranked += len(qi)
        self.rerank(qi, ids[xi], x[xi])

    def start(self) -> None:
        """Reranks the seeds that reach the threshold."""
        found = self.index.seeded(self.qids, self.q, self.measure)
        qi, xi = np.nonzero(found + 1e-9 * (1 + np.abs(found)) >= np.maximum(self.threshold, -1e300)[:, None])
        self.rerank(qi, self.index.seed_ids[xi], self.index.seeds[xi])

    def rerank(self, qi: np.ndarray, ids: np.ndarray, x: np.ndarray) -> None:
        score = np.einsum("ij,ij->i", self.q[qi], x) if self.measure == "inner product" else -((self.q[qi] - x) ** 2).sum(1)
        near = score >= self.threshold[qi] - 1e-9 * (1 + np.abs(score))  # products of whole matrices round otherwise
        new = (qi[near], self.qids[qi[near]], ids[near], score[near])
        at, qid, ids, score = (np.concatenate(c) for c in zip(self.best, new, strict=True))
        by = np.lexsort((-score, ids, at))
        by = by[np.append(True, (ids[by][1:] != ids[by][:-1]) | (at[by][1:] != at[by][:-1]))[: len(by)]]  # an id once
        by = by[np.lexsort((ids[by], -score[by], at[by]))]
        at, qid, ids, score = at[by], qid[by], ids[by], score[by]
        rank = np.arange(len(at)) - np.searchsorted(at, at)
        self.threshold[at[rank == self.k - 1]] = score[rank == self.k - 1]
        self.best = tuple(c[rank < self.k] for c in (at, qid, ids, score))


def nearest(df: DataFrame, queries, id_col: str = "vec_id", vector_col: str = "embedding", k: int = NEIGHBOURS, measure: str = "inner product") -> DataFrame:
    """(query_id, rank, vec_id, score): for rows that the condition queries picks, the k rows with the largest inner product, or with the smallest
    distance, as minus its square.

    Blocks of queries meet all rows, which are dealt over STRIPES stripes. A task goes through a stripe block by block and keeps the
    best k so far; which rows are reranked follows from the k-th of them and the errors of the codes, not from a number. What leaves the
    tasks is k rows a query and stripe, however many rows there are.
    """
    spark, kind = df.sparkSession, component_type(df, vector_col)
    rows = saved(usable(df, id_col, vector_col).filter("id is not null"), "vectors")
    ids, fitted = sample(rows, kind)
    if not len(fitted):
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    shared = spark.sparkContext.broadcast(Index(ids, fitted))
    n = rows.count()

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 1024):
                part = b.slice(i, 1024)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(shared.value.coded(matrix(part.column(1), kind)), pa.binary())], ["id", "vec", "codes"])

    def bounded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(0, b.num_rows, 1024):
                part = b.slice(i, 1024)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(shared.value.threshold(part.column(0).to_numpy(), matrix(part.column(1), kind), k, measure))], ["id", "vec", "threshold"])

    data_blocks, query_blocks = max(1, -(-n // DATA_ROWS)), max(1, -(-n // (20 * QUERY_ROWS)))
    to_queries = F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1)))
    to_stripes = F.explode(F.sequence(F.lit(0), F.lit(STRIPES - 1)))
    db = F.pmod(F.xxhash64("id"), F.lit(data_blocks)).cast("int")
    data = rows.mapInArrow(coded, "id long, vec binary, codes binary")
    data = data.select(to_queries.alias("qb"), F.pmod(db, F.lit(STRIPES)).alias("stripe"), db.alias("db"), "id", "vec", "codes", F.lit(0.0).alias("threshold"))
    # queries come first in their stripe, as block -1
    asked = rows.filter(queries(F.col("id"))).mapInArrow(bounded, "id long, vec binary, threshold double")
    asked = asked.select(F.pmod(F.xxhash64("id", F.lit(3)), F.lit(query_blocks)).cast("int").alias("qb"), to_stripes.alias("stripe"), F.lit(-1).alias("db"), "id", "vec", F.lit(None).cast("binary").alias("codes"), "threshold")
    order = ["qb", "stripe", "db"]
    dealt = data.unionByName(asked).repartition("qb", "stripe").sortWithinPartitions(*order)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, running = None, None
        out = lambda: pa.RecordBatch.from_arrays([pa.array(c) for c in running.best[1:]], ["query_id", "vec_id", "score"])
        for t in sorted_runs(batches, order, 4 * (DATA_ROWS + QUERY_ROWS)):
            cuts = run_starts(*(t.column(c).to_numpy() for c in order))
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                g = t.slice(a, b - a)
                qb, stripe, block = (g.column(c)[0].as_py() for c in order)
                if (qb, stripe) != at:
                    if running:
                        yield out()
                    at, running = (qb, stripe), None
                ids, x = g.column("id").to_numpy(), matrix(g.column("vec"), kind)
                if block < 0:
                    running = Search(shared.value, ids, x, g.column("threshold").to_numpy(), k, measure)
                    if not stripe:
                        running.start()
                elif running:
                    running.block(ids, x, g.column("codes").to_pylist())
        if running:
            yield out()

    best = dealt.select(*order, "id", "vec", "codes", "threshold").mapInArrow(search, "query_id long, vec_id long, score double")
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return best.groupBy("query_id", "vec_id").agg(F.max("score").alias("score")).withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op6_additive_quantisation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(read(spark, sf_dir, "embeddings").select("vec_id", "embedding"), lambda i: F.pmod(i, F.lit(20)) == 0)


# -- iterative quantisation, multi-index Hamming tables -----------------------------------------------------------

CODE_BITS, LINK_ROWS = 64, 1024


def fit_rotation(x: np.ndarray, bits: int = CODE_BITS, rounds: int = 30) -> tuple[np.ndarray, np.ndarray]:
    """(mean, projection): principal axes turned so that the signs are balanced and lose least."""
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    mean = x.mean(0)
    _, axes = np.linalg.eigh((x - mean).T @ (x - mean))
    axes = axes[:, ::-1][:, :bits]
    v = (x - mean) @ axes
    turn = np.linalg.qr(np.random.default_rng(3).normal(size=(axes.shape[1],) * 2))[0]
    for _ in range(rounds):
        left, _, right = np.linalg.svd(np.where(v @ turn >= 0, 1.0, -1.0).T @ v)
        turn = (left @ right).T
    return mean, axes @ turn


def binary_codes(x: np.ndarray, mean: np.ndarray, projection: np.ndarray) -> np.ndarray:
    bits = ((x / np.linalg.norm(x, axis=1, keepdims=True) - mean) @ projection) >= 0
    full = np.zeros((len(x), CODE_BITS), bool)
    full[:, : bits.shape[1]] = bits
    return np.packbits(full, axis=1, bitorder="little").view(np.int64)[:, 0]


RECALL, MOST_PROBES, LINK_COSINE = 0.995, 16, 0.95


def met_share(bits: int, tables: int, radius: int, cosine: float = LINK_COSINE) -> float:
    """Expected share of the pairs of a cosine that meet in a table: bits differ independently, each by the angle over pi."""
    p = float(np.arccos(cosine)) / np.pi
    widths = np.diff(np.linspace(0, bits, tables + 1).astype(int)).tolist()
    missed = [1 - sum(comb(w, r) * p**r * (1 - p) ** (w - r) for r in range(min(radius, w) + 1)) for w in widths]
    return 1 - float(np.prod(missed))


def widest_difference(bits: int, cosine: float) -> int:
    """The fewest bits in which all but 0.001 of the pairs of a cosine differ at most."""
    p = float(np.arccos(min(1.0, max(-1.0, cosine)))) / np.pi
    share, r = 0.0, -1
    while share < 0.999 and r < bits:
        r += 1
        share += comb(bits, r) * p**r * (1 - p) ** (bits - r)
    return r


def table_plan(n: int, bits: int) -> tuple[int, int]:
    """(tables, radius): of the plans that are expected to meet RECALL of the pairs at LINK_COSINE, with MOST_PROBES rows a vector at
    most, the one whose probes meet least. It follows from the code's width alone: the number of vectors n changes nothing."""
    plans = []
    for tables in range(1, bits + 1):
        for radius in range(bits // tables + 1):
            widths = np.diff(np.linspace(0, bits, tables + 1).astype(int)).tolist()
            masks = [sum(comb(w, r) for r in range(min(radius, w) + 1)) for w in widths]
            if met_share(bits, tables, radius) >= RECALL and sum(masks) <= MOST_PROBES:
                plans.append((sum(m / 2**w for m, w in zip(masks, widths, strict=True)), tables, radius))
    return min(plans)[1:]


def linked(df: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", at_least: float = 0.95) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of df."""
    spark, kind = df.sparkSession, component_type(df, vector_col)

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh3_128_digest

        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([xxh3_128_digest(v) for v in b.column(1).to_pylist()], pa.binary())], ["id", "vec", "same"])

    rows = saved(usable(df, id_col, vector_col).mapInArrow(keyed, "id long, vec binary, same binary"), "vectors")
    distinct = saved(rows.groupBy("same").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("copies"), F.min("vec").alias("vec")), "distinct-vectors")
    _, fitted = sample(distinct.select("id", "vec"), kind)
    every = df.select(F.col(id_col).cast("long").alias("vec_id"))
    if not len(fitted):
        return every.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    mean, projection = fit_rotation(fitted)
    bits = projection.shape[1]
    tables, radius = table_plan(distinct.count(), bits)
    edges, most_bits = np.linspace(0, bits, tables + 1).astype(int), widest_difference(bits, at_least)
    shared = spark.sparkContext.broadcast((mean, projection))
    spans = [(int(a), (1 << int(b - a)) - 1) for a, b in zip(edges[:-1], edges[1:], strict=True)]

    def sub(code: np.ndarray, k: int) -> np.ndarray:
        shift, mask = spans[k]
        return (code.view(np.uint64) >> np.uint64(shift) & np.uint64(mask)).astype(np.int64)

    def probes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A stored row for each table, which asks for its own bucket too, and rows that ask within the radius."""
        from chunkset.llm.simhash import flips

        for whole in batches:
            for i in range(0, whole.num_rows, 1024):
                b = whole.slice(i, 1024)
                code = binary_codes(matrix(b.column("vec"), kind), *shared.value)
                for k, (_, mask) in enumerate(spans):
                    masks = flips(int(mask).bit_length(), radius)
                    value = (sub(code, k)[:, None] ^ masks[None]).ravel()
                    who = np.repeat(np.arange(len(code)), len(masks))
                    role = np.tile(np.where(masks == 0, 2, 1).astype(np.int8), len(code))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(value), k, np.int32)), pa.array(value), *[b.column(c).take(pa.array(who)) for c in ("id", "copies", "vec")], pa.array(code[who]), pa.array(role)], ["part", "value", "id", "copies", "vec", "code", "role"])

    found = distinct.select("id", "copies", "vec").mapInArrow(probes, "part int, value long, id long, copies long, vec binary, code long, role byte")
    sizes = found.groupBy("part", "value").agg(F.count(F.lit(1)).alias("bucket_rows"))
    dealt = into_blocks(found, ["part", "value"], "id", LINK_ROWS, saved(sizes, "bucket-sizes"))
    order = ["part", "value", "lo", "hi"]
    dealt = dealt.repartition(*order).sortWithinPartitions(*order).select(*order, "block", "id", "copies", "vec", "code", "role")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in sorted_runs(batches, order, 8192):
            cols = {c: t.column(c).to_numpy() for c in (*order, "block", "id", "copies", "code", "role")}
            cuts = run_starts(*(cols[c] for c in order))
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                if b - a < 2:
                    continue
                c = {k: v[a:b] for k, v in cols.items()}
                x = matrix(t.column("vec").slice(a, b - a), kind)
                x = x / np.linalg.norm(x, axis=1, keepdims=True)
                # whole codes first: of pairs that differ in more bits almost none are near
                near = np.bitwise_count(c["code"][:, None] ^ c["code"][None]) <= most_bits
                near &= (c["role"] >= 1)[:, None] & (c["role"] != 1)[None]
                if c["lo"][0] != c["hi"][0]:
                    near &= c["block"][:, None] != c["block"][None]
                np.fill_diagonal(near, False)
                if near.mean() > 0.02:
                    near &= x @ x.T >= at_least
                    i, j = np.nonzero(near)
                else:
                    i, j = np.nonzero(near)
                    close = np.einsum("ij,ij->i", x[i], x[j]) >= at_least
                    i, j = i[close], j[close]
                met = np.full(len(i), -1)  # the first table in which the pair meets counts it
                for k in range(len(spans) - 1, -1, -1):
                    met[np.bitwise_count(sub(c["code"][i], k) ^ sub(c["code"][j], k)) <= radius] = k
                first = (met == c["part"][0]) & (c["id"][i] != c["id"][j])
                i, j = i[first], j[first]
                if not len(i):
                    continue
                links = np.bincount(i, c["copies"][j], minlength=b - a).astype(np.int64)
                nodes, low = local_components(c["id"][i], c["id"][j])
                per = dict(zip(c["id"][i].tolist(), links[i].tolist(), strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array([per.get(n, 0) for n in nodes.tolist()], pa.int64()), pa.array(low)], ["node", "links", "low"])

    met = saved(dealt.mapInArrow(verify, "node long, links long, low long"), "links-met")
    parted = components(met, "node", "low")
    counted = met.groupBy("node").agg(F.sum("links").alias("links"))
    joined = distinct.select("same", "id", "copies").join(counted, F.col("id") == F.col("node"), "left").drop("node").join(parted, F.col("id") == F.col("node"), "left")
    per_vector = joined.select("same", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    known = rows.select(F.col("id").alias("vec_id"), "same").join(per_vector, "same").select("vec_id", "n_links", "component_id")
    one_each = known.groupBy("vec_id").agg(F.max("n_links").alias("n_links"), F.min("component_id").alias("component_id"))
    out = every.join(one_each, "vec_id", "left")
    component = F.coalesce("component_id", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), (F.col("vec_id") == component).alias("kept"))


def op7_iterative_quantisation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linked(read(spark, sf_dir, "embeddings").select("vec_id", "embedding"))
