"""SimHash near-duplicates by the generalised pigeonhole principle.

A text's fingerprint has a bit where over half of its shingle hashes have it. Distinct fingerprints (copies fall
together before anything is compared) link at a small Hamming distance. Correlated bits are grouped into partitions;
each fingerprint allots the distance over the partitions, unequally and with some left out, by a dynamic program
over the number of candidates that its value in a partition would meet at each radius. Thresholds that sum to the
distance less the number of partitions plus one lose no link. Probes meet the stored values in buckets; every pair
of a bucket is verified on the whole fingerprint.

Large buckets are met block by block, so that no task gets more than two blocks, and what a task finds leaves it
as a spanning forest, never as all pairs. Null and empty texts, and texts without words, have fingerprint zero and link
as any other. Rows that repeat a doc_id link with each other. A null doc_id
gets its class, but names none unless all of the class are null. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chunkset.llm.common import bounded_text, components, into_blocks, parts, raw, read, run_starts, saved, small_batches, sorted_runs, star_links, tidy

BITS, SEED, BLOCK_ROWS, PAIRS_AT_ONCE = 64, 42, 192, 400_000


def shingle_hashes(text: bytes, words: int) -> np.ndarray:
    """XXH64 of each run of so many lower-cased words, joined by spaces; of all words if there are fewer."""
    from xxhash import xxh64_intdigest

    found = text.lower().split()  # bytes: A-Z only, and ASCII white space only
    if not found:
        return np.empty(0, np.uint64)
    joined = b" ".join(found)
    if len(found) <= words:
        return np.array([xxh64_intdigest(joined, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, found), np.int64, len(found)) + 1) - 1
    starts = np.append(0, ends[:-1] + 1)
    return np.array([xxh64_intdigest(joined[a:b], SEED) for a, b in zip(starts[: len(found) - words + 1].tolist(), ends[words - 1 :].tolist(), strict=True)], np.uint64)


def fingerprint(hashes: np.ndarray) -> int:
    if not len(hashes):
        return 0
    ones = np.zeros(BITS, np.int64)
    for i in range(0, len(hashes), 1 << 16):
        part = hashes[i : i + (1 << 16)].astype("<u8")
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5) -> DataFrame:
    """(id, fp): the 64 bits as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in parts(batches, 1):
            fps = np.fromiter((fingerprint(shingle_hashes(raw(x), words)) for x in b.column(1)), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64))], ["id", "fp"])

    return small_batches(df).select(F.col(id_col).cast("long").alias("id"), bounded_text(text_col)).mapInArrow(tidy(run), "id long, fp long")


# -- the plan: partitions of bits, and what a probe of each radius would meet ---------------------------------------


def bit_statistics(fps: DataFrame) -> np.ndarray:
    """Over all fingerprints: how many have bits i and j both set. 64 x 64 sums leave each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((BITS, BITS))
        for b in batches:
            x = unpacked(b.column(0).to_numpy()).astype(np.float64)
            total += x.T @ x
        at = np.arange(BITS * BITS)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total.ravel().astype(np.int64))], ["at", "n"])

    rows = fps.select("fp").mapInArrow(run, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).collect()
    out = np.zeros(BITS * BITS)
    for r in rows:
        out[r["at"]] = r["n"]
    return out.reshape(BITS, BITS)


def unpacked(fps: np.ndarray) -> np.ndarray:
    return np.unpackbits(np.ascontiguousarray(fps).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")


def group_bits(both: np.ndarray, n: int, parts: int) -> list[list[int]]:
    """Deals the bits into equal partitions, each time adding the bit that correlates most with those of the partition."""
    p = np.diag(both) / max(n, 1)
    cov = both / max(n, 1) - np.outer(p, p)
    sd = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    corr = np.abs(cov / np.outer(sd, sd))
    np.fill_diagonal(corr, 0)
    free, groups = set(range(BITS)), []
    for k in range(parts):
        size = (BITS - sum(map(len, groups))) // (parts - k)
        seed = max(free, key=lambda i: (corr[i, sorted(free)].sum(), -i))
        group = [seed]
        free.discard(seed)
        while len(group) < size:
            best = max(sorted(free), key=lambda i: corr[i, group].sum())
            group.append(best)
            free.discard(best)
        groups.append(sorted(group))
    return groups


def part_values(fps: np.ndarray, groups: list[list[int]]) -> np.ndarray:
    """Column k: the bits of partition k as a number."""
    bits = unpacked(fps)
    return np.stack([bits[:, g].astype(np.int64) @ (1 << np.arange(len(g))) for g in groups], axis=1)


def value_counts(fps: DataFrame, groups: list[list[int]]) -> list[np.ndarray]:
    """How many fingerprints have each value in each partition: 2^width counters a partition, whatever the data."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals = [np.zeros(1 << len(g), np.int64) for g in groups]
        for b in batches:
            values = part_values(b.column(0).to_numpy(), groups)
            for k, t in enumerate(totals):
                t += np.bincount(values[:, k], minlength=len(t))
        for k, t in enumerate(totals):
            at = np.flatnonzero(t)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), k, np.int32)), pa.array(at), pa.array(t[at])], ["part", "value", "n"])

    rows = fps.select("fp").mapInArrow(run, "part int, value long, n long").groupBy("part", "value").agg(F.sum("n").cast("int").alias("n")).toArrow()
    out = [np.zeros(1 << len(g), np.int64) for g in groups]
    part, value, n = (rows.column(c).to_numpy() for c in ("part", "value", "n"))
    for k, t in enumerate(out):
        t[value[part == k]] = n[part == k]
    return out


def met_at_radius(counts: np.ndarray, most: int) -> np.ndarray:
    """Row r: for each value, how many fingerprints lie within r bits of it. Row 0 of the result is radius -1."""
    width = int(np.log2(len(counts)))
    shells = [counts.astype(np.float64)]
    at = np.arange(len(counts))
    moved = [sum(shells[0][at ^ (1 << i)] for i in range(width))] if most >= 1 else []
    shells += moved
    for r in range(2, most + 1):  # each shell r is met r times from shell r-1, less what steps back
        back = sum(shells[r - 1][at ^ (1 << i)] for i in range(width))
        shells.append((back - (width - r + 2) * shells[r - 2]) / r)
    return np.vstack([np.zeros(len(counts)), np.cumsum(shells, axis=0)])


PROBE_COST = 2.0  # a probe weighs as much as verifying so many candidates


def allot(values: np.ndarray, met: list[np.ndarray], distance: int) -> np.ndarray:
    """Radius of each partition (-1: not probed) for each row of values, so that they sum to distance - partitions + 1
    at the least cost, by a dynamic program over the partitions."""
    rows, parts = values.shape
    goal = distance - parts + 1
    radii = range(-1, met[0].shape[0] - 1)
    low, high = -parts, max(goal + parts, 0)
    cost = {0: np.zeros(rows)}
    came: list[dict[int, np.ndarray]] = []
    for k in range(parts):
        width = int(np.log2(met[k].shape[1]))
        probes, total = [0.0], 0.0
        for r in range(met[k].shape[0] - 1):
            total += np.prod([(width - i) / (i + 1) for i in range(r)]) if r else 1.0
            probes.append(total)
        new: dict[int, np.ndarray] = {}
        chosen: dict[int, np.ndarray] = {}
        for s, c in cost.items():
            for r in radii:
                t = s + r
                if not low <= t <= high:
                    continue
                price = c + met[k][r + 1][values[:, k]] + PROBE_COST * probes[r + 1]
                if t not in new:
                    new[t], chosen[t] = price, np.full(rows, r, np.int8)
                else:
                    better = price < new[t]
                    new[t] = np.where(better, price, new[t])
                    chosen[t] = np.where(better, np.int8(r), chosen[t])
        cost = new
        came.append(chosen)
    out = np.empty((rows, parts), np.int8)
    at = np.full(rows, goal)
    for k in range(parts - 1, -1, -1):
        for t in np.unique(at):
            mask = at == t
            out[mask, k] = came[k][int(t)][mask]
        at = at - out[:, k]
    return out


def flips(width: int, radius: int) -> np.ndarray:
    """Masks of at most radius bits."""
    masks = [np.zeros(1, np.int64)]
    for _ in range(radius):
        masks.append(np.unique((masks[-1][:, None] ^ (1 << np.arange(width))[None]).ravel()))
    return np.unique(np.concatenate(masks))


# -- probing and verifying ------------------------------------------------------------------------------------------


def keys(fps: DataFrame, groups: list[list[int]], counts: list[np.ndarray], distance: int) -> DataFrame:
    """(part, value, fp, probe): a stored row for each partition, and the probe rows. A probe at radius 0 is its stored row."""
    goal = distance - len(groups) + 1
    most = max(min(distance + 1, 2), -(-goal // len(groups)))  # radii of 2 do, unless the goal asks for more of every partition
    met = [met_at_radius(c, most) for c in counts]
    shared = fps.sparkSession.sparkContext.broadcast((groups, met))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        groups, met = shared.value
        masks = {(k, r): flips(len(g), r) for k, g in enumerate(groups) for r in range(met[k].shape[0] - 1)}
        for b in batches:
            for i in range(0, b.num_rows, 8192):
                fp = b.column(0).to_numpy()[i : i + 8192]
                values = part_values(fp, groups)
                radius = allot(values, met, distance)
                for k in range(len(groups)):
                    out = [(values[:, k], fp, np.where(radius[:, k] >= 0, 2, 0))]
                    for r in range(1, met[k].shape[0] - 1):
                        rows = np.flatnonzero(radius[:, k] == r)
                        probe = (values[rows, k][:, None] ^ masks[k, r][None]).ravel()
                        who = np.repeat(fp[rows], len(masks[k, r]))
                        there = (met[k][1][probe] > 0) & (probe != np.repeat(values[rows, k], len(masks[k, r])))
                        out.append((probe[there], who[there], np.ones(int(there.sum()), np.int64)))
                    v, f, p = (np.concatenate(x) for x in zip(*out, strict=True))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(v), k, np.int32)), pa.array(v.astype(np.int64)), pa.array(f), pa.array(p.astype(np.int8))], ["part", "value", "fp", "probe"])

    return fps.select("fp").mapInArrow(tidy(run), "part int, value long, fp long, probe byte")


def close_pairs(fp: np.ndarray, block: np.ndarray, lo: np.ndarray, hi: np.ndarray, probe: np.ndarray, cuts: np.ndarray, distance: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Verified links of each bucket, a bounded number of pairs at a time. Row i meets row i + lag of the same bucket."""
    n = len(fp)
    length = np.diff(cuts)
    end = np.repeat(cuts[1:], length)
    rows, lag = np.arange(n), 1
    held_u, held_v, held = [], [], 0
    u64 = fp.view(np.uint64)
    while True:
        rows = rows[rows + lag < end[rows]]
        if not len(rows):
            break
        other = rows + lag
        near = np.bitwise_count(u64[rows] ^ u64[other]) <= distance
        # blocks meet once; one of two must probe and one must be stored (0: stored, 1: probe, 2: both)
        near &= (lo[rows] == hi[rows]) | (block[rows] != block[other])
        near &= probe[rows] + probe[other] > 0
        near &= ~((probe[rows] == 1) & (probe[other] == 1))
        if near.any():
            held_u.append(fp[rows[near]])
            held_v.append(fp[other[near]])
            held += int(near.sum())
            if held > PAIRS_AT_ONCE:
                yield np.concatenate(held_u), np.concatenate(held_v)
                held_u, held_v, held = [], [], 0
        lag += 1
    if held:
        yield np.concatenate(held_u), np.concatenate(held_v)


def fingerprint_links(fps: DataFrame, distance: int = 3, parts: int = 4) -> DataFrame:
    """Spanning links (u, v) between the distinct fingerprints of the column fp that lie within distance."""
    n = fps.count()
    groups = group_bits(bit_statistics(fps), n, parts)
    counts = value_counts(fps, groups)
    found = saved(keys(fps, groups, counts, distance), "simhash-keys")
    sizes = found.groupBy("part", "value").agg(F.count(F.lit(1)).alias("bucket_rows")).filter("bucket_rows > 1")
    meeting = into_blocks(found, ["part", "value"], "fp", BLOCK_ROWS, sizes)
    dealt = meeting.repartition("part", "value", "lo", "hi").sortWithinPartitions("part", "value", "lo", "hi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in sorted_runs(batches, ["part", "value", "lo", "hi"]):
            part, value, lo, hi, block, fp, probe = (t.column(c).to_numpy() for c in ("part", "value", "lo", "hi", "block", "fp", "probe"))
            cuts = run_starts(part, value, lo, hi)
            for u, v in close_pairs(fp, block, lo, hi, probe, cuts, distance):
                a, b = star_links(u, v)
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["u", "v"])

    return dealt.select("part", "value", "lo", "hi", "block", "fp", "probe").mapInArrow(tidy(run), "u long, v long")


def near_duplicates(docs: DataFrame, words: int = 5, distance: int = 3, parts: int = 4) -> DataFrame:
    """(doc_id, fp, component_id) for each row of (doc_id, text): the smallest doc_id reachable by links."""
    fps = saved(fingerprints(docs, words=words), "fingerprints")
    distinct = saved(fps.groupBy("fp").agg(F.min("id").alias("first_id")), "distinct-fingerprints")
    links = fingerprint_links(distinct, distance, parts)
    parted = components(links)
    first = distinct.join(parted.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "first_id", F.coalesce("component", "fp").alias("component"))
    smallest = first.groupBy("component").agg(F.min("first_id").alias("component_id"))
    whole = first.join(smallest, "component").select("fp", "component_id")
    return fps.join(whole, "fp").select(F.col("id").alias("doc_id"), "fp", "component_id")


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(read(spark, sf_dir, "documents").select("doc_id", "text"), words=3)
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")

