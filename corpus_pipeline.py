"""A corpus pipeline of five stages, each reading what the one before it wrote."""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chunkset.llm import byte_bpe, mixing, near_copies, privacy, quality
from chunkset.llm.common import BATCH_KEY, discard, read, saved
from chunkset.llm.privacy import either_way

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Near copies share so much of their five-word shingles.
SIMILARITY = 0.8
#: Spark keeps the workers of earlier stages for a while: the encoder's caches are small here, and dropped after each task, and Arrow batches are small too.
CACHED_BYTES, BATCH_BYTES = 8 << 20, 1 << 20


def sparing(stage: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
    """stage, for which Spark's Arrow batches hold BATCH_BYTES at most from then on."""

    @wraps(stage)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        spark.conf.set(BATCH_KEY, f"{BATCH_BYTES}b")  # small_batches leaves Spark's own default as it is
        return stage(spark, docs, sf_dir)

    return run


@sparing
def drop_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Fits on the labelled rows of docs that aren't held out; rows below a score of 0.5 go. Null and empty texts are scored as texts without words, a null
    n_chars is taken from the text, repeated rows score alike, null ids are scored too. Without labels every row scores 0.5 and stays."""
    machine = quality.train(docs.select("doc_id", "text", "n_chars"), read(spark, sf_dir, "labels"))
    return quality.score(docs.select(*COLUMNS), machine, with_text=True).filter("score >= 0.5").select(*COLUMNS)


@sparing
def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: the one with the smallest doc_id.

    Groups are what exact links of five-word similarity connect, in the groups of close fingerprints and beyond them.
    Of rows that share a doc_id the smallest stays, if one of them is the first of its group. Rows without a doc_id can't be told apart by
    it: they all stay. Null texts are empty texts, which are copies of each other. An empty table gives an empty result.
    """
    found = near_copies.near_copies(docs.select("doc_id", "text"), words=5, at_least=SIMILARITY)
    by_id = found.filter("doc_id is not null").groupBy("doc_id").agg(F.max(F.col("doc_id") == F.col("component_id")).alias("first"), F.count(F.lit(1)).alias("rows"))
    odd = saved(by_id.filter("not first or rows > 1"), "near-odd")
    rest = [c for c in COLUMNS if c != "doc_id"]
    kept = docs.select(*COLUMNS).join(either_way(odd.select("doc_id")), "doc_id", "left_anti")
    again = odd.filter("first").select("doc_id")
    if again.isEmpty():
        return kept
    one = docs.select(*COLUMNS).join(either_way(again), "doc_id").groupBy("doc_id").agg(F.min(F.struct(*rest)).alias("row"))
    return kept.unionByName(one.select("doc_id", "row.*"))


@sparing
def hide_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row of docs with its text sanitised and n_chars of the new text; a null text becomes the empty text. Repeated rows are sanitised alike,
    null ids and sources stay null."""
    return privacy.sanitise(docs.select(*COLUMNS)).withColumn("n_chars", F.length("text").cast("long"))


@sparing
def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix takes it. A null source is one of its own, the last; rows that repeat an id are documents of their own;
    a null or empty text has no words, and may be taken or not."""
    return mixing.mixed_rows(docs.select(*COLUMNS))


@sparing
def tokenise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, and the text as token ids, which decode to it; a null text has no ids. Repeated rows are encoded again."""
    coded = byte_bpe.encode_texts(docs.select("doc_id", "lang", "source", "text"), cached_bytes=CACHED_BYTES, forget=True)
    return coded.withColumn("ids_sha256", F.sha2("token_ids", 256))


STAGES = [
    ("quality classifier", drop_low_quality),
    ("simhash near-dedup", drop_near_copies),
    ("personal data", hide_personal_data),
    ("mixing", mix_sources),
    ("byte-level bpe", tokenise),
]

#: The fitted machine, the sampling and the merges aren't SQL; the tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each stage's rows are written before the next reads them."""
    docs = read(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        before, docs = docs, saved(stage(spark, docs, sf_dir), f"pipeline-{i}")
        if i:
            discard(before)
    return docs
