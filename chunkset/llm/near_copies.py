"""Near copies by exact similarity: the share of word shingles that two texts have in common, of all that either has.

Candidates are groups of fingerprints within DISTANCE bits, found by the generalised pigeonhole of simhash.py, and, as fingerprints of texts
that share 0.8 of their shingles differ in ten bits on average, texts that agree in one of several further signatures: minima
of the shingle hashes under BANDS x ROWS random functions. Texts that agree on all minima of a band meet. A pair of similarity 0.8 is
missed in all bands with probability (1 - 0.8 ** 5) ** 25 = 0.00005, a nearer one with less. Every link is verified on the whole sets
of 64-bit shingle hashes.

Texts with equal sets fall together before anything is compared, and of groups and bands in which the same texts meet only one is gone
through. Large buckets are met block by block; pairs that a task has already connected are not compared again, so what it finds is a
spanning forest. Null and empty texts, and texts without words, have the empty set and are copies of each other. Rows that repeat a
doc_id link with each other. A null doc_id gets its class, but names none unless all of the class are null. An empty table
gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chunkset.llm.common import bounded_text, components, discard, into_blocks, parts, raw, run_starts, saved, small_batches, sorted_runs, tidy
from chunkset.llm.privacy import either_way
from chunkset.llm.simhash import fingerprint, fingerprint_links, shingle_hashes

BANDS, ROWS, DISTANCE, BLOCK_ROWS, AT_ONCE = 25, 5, 3, 384, 1 << 13
_random = np.random.default_rng(11)
FACTORS = _random.integers(0, 1 << 63, BANDS * ROWS, np.uint64) * np.uint64(2) + np.uint64(1)
OFFSETS = _random.integers(0, 1 << 63, BANDS * ROWS, np.uint64)


def band_values(hashes: np.ndarray) -> np.ndarray:
    """For each band 64 bits that depend on its minima."""
    from xxhash import xxh3_64_intdigest

    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(hashes), AT_ONCE):
        least = np.minimum(least, (hashes[i : i + AT_ONCE, None] * FACTORS + OFFSETS).min(0))
    return np.array([xxh3_64_intdigest(x.tobytes()) for x in least.reshape(BANDS, ROWS)], np.uint64).view(np.int64)


def shingle_sets(texts: DataFrame, words: int, whole: bool = False) -> DataFrame:
    """(id, text_key, node, some, fp, bands) of (id, text_key, text): node stands for the set of shingles, some says that it has any, fp is
    the fingerprint. whole: (node, hashes), the sorted hashes as bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh3_64_intdigest

        for b in parts(batches, 2):
            lists = [shingle_hashes(raw(x), words) for x in b.column("text")]
            sets = [np.unique(x) for x in lists]
            nodes = pa.array(np.array([xxh3_64_intdigest(s.tobytes()) for s in sets], np.uint64).view(np.int64))
            if whole:
                yield pa.RecordBatch.from_arrays([nodes, pa.array([s.tobytes() for s in sets], pa.binary())], ["node", "hashes"])
            else:
                some, bands = pa.array([len(s) > 0 for s in sets]), pa.array([band_values(s) for s in sets], pa.list_(pa.int64()))
                fps = pa.array(np.array([fingerprint(x) for x in lists], np.uint64).view(np.int64))
                yield pa.RecordBatch.from_arrays([b.column("id"), b.column("text_key"), nodes, some, fps, bands], ["id", "text_key", "node", "some", "fp", "bands"])

    return small_batches(texts).mapInArrow(tidy(run), "node long, hashes binary" if whole else "id long, text_key long, node long, some boolean, fp long, bands array<long>")


def forest(nodes: np.ndarray, block: np.ndarray, sets: list[np.ndarray], at_least: float, across: bool) -> tuple[list[int], list[int]]:
    """Links of similarity at_least that connect what all such links of the bucket connect; across: only between two blocks."""
    size = np.fromiter(map(len, sets), np.int64, len(sets))
    label, index = np.arange(len(sets)), np.arange(len(sets))
    u, v = [], []
    for i in range(len(sets) - 1):
        small, large = np.minimum(size, size[i]), np.maximum(size, size[i])
        # a set shares at most the smaller of two sizes
        other = index[(index > i) & (label != label[i]) & (small >= at_least * large) & (not across or block != block[i])]
        if not len(other):
            continue
        pool = np.concatenate([sets[j] for j in other])
        at = np.minimum(np.searchsorted(sets[i], pool), max(size[i] - 1, 0))
        ends = np.append(0, np.cumsum(sets[i][at] == pool))[np.append(0, np.cumsum(size[other]))]
        both = np.diff(ends)
        for j in other[both >= at_least * (size[i] + size[other] - both)]:
            if label[j] != label[i]:
                u.append(int(nodes[i]))
                v.append(int(nodes[j]))
                label[label == label[j]] = label[i]
    return u, v


def fingerprint_groups(distinct: DataFrame) -> DataFrame:
    """(node, band, value): texts with one value have fingerprints that links of DISTANCE bits connect."""
    fps = saved(distinct.select("fp").distinct(), "near-fingerprints")
    parted = components(fingerprint_links(fps, DISTANCE))
    return distinct.join(parted.withColumnRenamed("node", "fp"), "fp", "left").select("node", F.lit(BANDS).alias("band"), F.coalesce("component", "fp").alias("value"))


def links_of(texts: DataFrame, distinct: DataFrame, words: int, at_least: float) -> DataFrame:
    """Links (u, v) between the nodes of (node, text_key, some, fp, bands) that connect all pairs of similarity at_least that meet.

    Only texts that meet another are made into whole sets, from texts again: sets take more room than texts.
    """
    some = distinct.filter("some")
    met = saved(some.select("node", F.posexplode("bands").alias("band", "value")).unionByName(fingerprint_groups(some)), "near-bands")
    buckets = met.groupBy("band", "value").agg(F.count(F.lit(1)).alias("bucket_rows"), F.bit_xor(F.xxhash64("node")).alias("h1"), F.bit_xor(F.xxhash64("node", F.lit(1))).alias("h2")).filter("bucket_rows > 1")
    first = buckets.groupBy("bucket_rows", "h1", "h2").agg(F.min(F.struct("band", "value")).alias("b"))
    sizes = saved(first.select("b.band", "b.value", "bucket_rows"), "near-buckets")
    asked = saved(met.join(sizes.select("band", "value"), ["band", "value"]), "near-asked")
    discard(met)
    wanted = saved(asked.select("node").distinct().join(distinct.select("node", "text_key"), "node").select("text_key").distinct(), "near-wanted")
    sets = saved(shingle_sets(texts.join(either_way(wanted), "text_key").dropDuplicates(["text_key"]), words, whole=True), "near-sets").dropDuplicates(["node"])
    order = ["band", "value", "lo", "hi"]
    placed = into_blocks(asked, ["band", "value"], "node", BLOCK_ROWS, sizes).select(*order, "block", "node")
    dealt = placed.join(sets, "node").repartition(*order).sortWithinPartitions(*order)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in sorted_runs(batches, order, 4 * BLOCK_ROWS):
            cols = {c: t.column(c).to_numpy() for c in (*order, "block", "node")}
            cuts = run_starts(*(cols[c] for c in order))
            u, v = [], []
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                sets = [np.frombuffer(x, np.uint64) for x in t.column("hashes").slice(a, b - a).to_pylist()]
                x, y = forest(cols["node"][a:b], cols["block"][a:b], sets, at_least, cols["lo"][a] != cols["hi"][a])
                u += x
                v += y
            yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

    return dealt.select(*order, "block", "node", "hashes").mapInArrow(tidy(run), "u long, v long")


def near_copies(docs: DataFrame, words: int = 5, at_least: float = 0.8) -> DataFrame:
    """(doc_id, component_id) for each row of (doc_id, text): the smallest doc_id reachable by links."""
    text = bounded_text("text")
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), F.xxhash64(text).alias("text_key"), text)
    rows = saved(shingle_sets(texts, words), "near-rows")
    distinct = rows.groupBy("node").agg(F.min("id").alias("first_id"), F.min("text_key").alias("text_key"), F.first("some").alias("some"), F.min("fp").alias("fp"), F.first("bands").alias("bands"))
    distinct = saved(distinct, "near-distinct")
    parted = components(links_of(texts, distinct, words, at_least))
    first = distinct.select("node", "first_id").join(parted, "node", "left").select("node", "first_id", F.coalesce("component", "node").alias("component"))
    smallest = first.groupBy("component").agg(F.min("first_id").alias("component_id"))
    whole = first.join(smallest, "component").select("node", "component_id")
    return rows.select("id", "node").join(whole, "node").select(F.col("id").alias("doc_id"), "component_id")
