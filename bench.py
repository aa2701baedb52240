"""Times the headline queries over $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

queries: seconds of each query, counted to its last row. kernels_us: AND and OR of pairs of sets in memory in each scheme, after a warm-up
that isn't counted, the mean of up to 100 rounds over all pairs (fewer where a round is long; the number is given). real*: the
experiment's 100 sampled pairs of each stand-in for a real data set (real1_wide: 20 of them, rows spread 64 apart); factors are sums over the pairs, a scheme's over the hybrid's.
density_*: two sets of 100,000 draws for each density. point: one append of a new maximum, one removal of a random member.
work: what the step-by-step operations count on the first pairs.
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

import numpy as np

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession  # noqa: E402

from chunkset.functions import batch as K  # noqa: E402
from chunkset.functions import containers as C  # noqa: E402
from chunkset.functions import runs as R  # noqa: E402
from chunkset.plans import catalog, workloads  # noqa: E402
from chunkset.sources import tables  # noqa: E402
from chunkset.sources.storage import saved  # noqa: E402

HEADLINE = ("container_census", "and_pairs", "or_pairs", "and_card", "union_all_heap", "union_all_words", "threshold_t_of_k", "real1_and", "real1_or", "real2_and", "real3_and", "real4_and", "real4_or", "real5_and", "star_filter", "inverted_and", "bits_per_int_table", "table2_expansion_1", "table2_expansion_3", "distinct_users_rollup")
ROUNDS, SECONDS, PLAIN_MB, WIDE_PAIRS = 100, 0.4, 2000, 20
CODECS = ("posfill", "fillrun")
SCHEMES = ("hybrid", *CODECS, "plain")


def encoders() -> dict:
    return {"hybrid": K.Packed.of, "plain": R.plain_encode} | {c: (lambda ids, c=c: R.encode(ids, c)) for c in CODECS}


def operation(scheme: str, op: str):
    if scheme == "hybrid":
        return K.intersect_sets if op == "and" else K.unite_sets
    return (lambda a, b: R.plain_combine(a, b, op)) if scheme == "plain" else lambda a, b: R.combine(a, b, scheme, op)


def mean_round(f, seconds: float = SECONDS) -> tuple[float, int]:
    """Microseconds of f after one call that isn't counted, and the number of calls that are: ROUNDS, or what the time allows."""
    began = time.perf_counter()
    f()
    rounds = max(3, min(ROUNDS, int(seconds / max(time.perf_counter() - began, 1e-9))))
    began = time.perf_counter()
    for _ in range(rounds):
        f()
    return (time.perf_counter() - began) / rounds * 1e6, rounds


def compared(pairs: list[tuple[np.ndarray, np.ndarray]]) -> dict:
    """For AND and OR: microseconds a pair in each scheme, and factors over the hybrid. Plain bitsets of over PLAIN_MB in all aren't made."""
    out: dict = {}
    plain_mb = sum(int(x[-1]) for pair in pairs for x in pair if len(x)) / 8e6
    schemes = [s for s in SCHEMES if s != "plain" or plain_mb < PLAIN_MB]
    made = {s: [(encoders()[s](a), encoders()[s](b)) for a, b in pairs] for s in schemes}
    for op in ("and", "or"):
        row, least = {}, ROUNDS
        for s in schemes:
            f = operation(s, op)
            us, rounds = mean_round(lambda s=s, f=f: [f(a, b) for a, b in made[s]])
            row[s], least = round(us / max(len(pairs), 1), 1), min(least, rounds)
        out[op] = row | {f"factor_{s}": round(row[s] / row["hybrid"], 2) for s in schemes[1:]} | {"rounds": least} | ({} if "plain" in schemes else {"plain_mb": round(plain_mb)})
    return out


def real_pairs(spark: SparkSession, sf_dir: str, which: int, stretch: int = 1) -> list[tuple[np.ndarray, np.ndarray]]:
    """The sampled pairs' ids, in the driver: two hundred sets. stretch spreads the rows of the first stand-in over a wider universe."""
    pairs = saved(workloads.sample_pairs(workloads.set_names(spark, sf_dir, which), catalog.N_PAIRS), "bench-pairs")
    found = workloads.of_pairs(workloads.real_sets(spark, sf_dir, which) if stretch == 1 else tables.lineitem_rows(spark, sf_dir, stretch), pairs).distinct().orderBy("set_id", "id").toArrow()
    names = found.column("set_id").combine_chunks().dictionary_encode()
    ids, cuts = found.column("id").to_numpy(), np.append(np.flatnonzero(np.diff(names.indices.to_numpy(), prepend=-1)), found.num_rows)
    sets = {names.dictionary[names.indices[int(a)].as_py()].as_py(): ids[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)}
    return [(sets[r["left_set"]], sets[r["right_set"]]) for r in pairs.orderBy("pair_id").collect()]


def draws(rng: np.random.Generator, e: int, dist: str) -> np.ndarray:
    x = rng.random(100_000)
    return np.unique(((x if dist == "uniform" else x * x) * (100_000 << e)).astype(np.int64))


def points(rng: np.random.Generator, e: int) -> dict:
    """Microseconds of one append and of one removal, the mean of 100 in a row on a set of the density. The codecs rewrite on a removal."""
    ids = draws(rng, e, "uniform")
    new, old = ids[-1] + 1 + np.cumsum(rng.integers(1, 2 << e, 100)), rng.choice(ids, 100, replace=False)

    def each(first, change, xs) -> float:
        state = first()
        change(state, int(xs[0]))  # warm-up, on a state of its own
        state = first()
        began = time.perf_counter()
        for x in xs.tolist():
            state = change(state, x)
        return round((time.perf_counter() - began) / len(xs) * 1e6, 1)

    packed = {int(k): C.from_values(ids[ids >> 16 == k] & 65535) for k in np.unique(ids >> 16)}
    mutable = lambda name: lambda s, x: (getattr(s, name)(x), s)[1]
    out = {"append": {"hybrid": each(lambda: C.MutableSet(packed), mutable("add"), new)}, "remove": {"hybrid": each(lambda: C.MutableSet(packed), mutable("remove"), old)}}
    plain = R.plain_encode(ids)
    out["append"]["plain"], out["remove"]["plain"] = each(plain.copy, R.plain_set, new), each(plain.copy, R.plain_clear, old)
    for c in CODECS:
        stream = R.encode(ids, c)
        out["append"][c], out["remove"][c] = each(lambda s=stream: s, lambda s, x, c=c: R.append(s, c, x), new), each(lambda s=stream: s, lambda s, x, c=c: R.remove(s, c, x), old[:10])
    return out


def work(pairs: list[tuple[np.ndarray, np.ndarray]]) -> dict:
    """Steps of the hybrid and words that the codecs read, summed over the pairs."""
    counted, words = C.Work(), dict.fromkeys(CODECS, 0)
    for a, b in pairs:
        x, y = ({int(k): C.from_values(s[s >> 16 == k] & 65535) for k in np.unique(s >> 16)} for s in (a, b))
        for k in x.keys() & y.keys():
            C.intersection(x[k], y[k], counted)
        for c in CODECS:
            words[c] += R.combine(R.encode(a, c), R.encode(b, c), c, "and")[1]
    steps = counted.as_dict()
    return {"hybrid_steps": sum(steps[n] for n in ("words_touched", "comparisons", "gallop_probes", "binary_steps")), "plain_words": sum(min(int(a[-1]), int(b[-1])) // 64 + 1 for a, b in pairs if len(a) and len(b))} | {f"{c}_words": n for c, n in words.items()}


def kernels(spark: SparkSession, sf_dir: str) -> dict:
    rng = np.random.default_rng(42)
    n = 4_277_807
    dense, sparse = np.flatnonzero(rng.random(n) < 0.4), np.sort(rng.choice(n, 30, replace=False))
    runs_a, runs_b = (np.unique((rng.integers(0, n, 300)[:, None] + np.arange(60)[None]).ravel()) for _ in range(2))
    half_a, half_b = (np.flatnonzero(rng.random(199_523) < 0.17) for _ in range(2))
    out: dict = {"dense_sparse": compared([(dense, sparse)]), "runs": compared([(runs_a, runs_b)]), "dense_dense": compared([(half_a, half_b)])}
    for which in workloads.REAL:
        pairs = real_pairs(spark, sf_dir, which)
        out[f"real{which}"] = compared(pairs) | {"work": work(pairs[:10])}
    out["real1_wide"] = compared(real_pairs(spark, sf_dir, 1, 64)[:WIDE_PAIRS])
    for dist in ("uniform", "beta"):
        out[f"density_{dist}"] = {f"2^-{e}": compared([(draws(rng, e, dist), draws(rng, e, dist))]) for e in (1, 2, 3, 4, 5, 6, 8, 10)}
    out["point_us"] = {f"2^-{e}": points(rng, e) for e in (1, 4, 7, 10)}
    words = [np.ascontiguousarray(rng.integers(0, 1 << 63, 1 << 20, dtype=np.uint64)) for _ in range(2)]
    buffer, ones = np.empty(1 << 13, np.uint64), np.empty(1 << 13, np.uint8)

    def union_all(count: bool) -> int:
        total = 0
        for i in range(0, 1 << 20, 1 << 13):  # pieces that stay in the cache, as containers do
            np.bitwise_or(words[0][i : i + (1 << 13)], words[1][i : i + (1 << 13)], out=buffer)
            if count:
                total += int(np.bitwise_count(buffer, out=ones).sum(dtype=np.uint32))
        return total

    bare, counted = mean_round(lambda: union_all(False))[0], mean_round(lambda: union_all(True))[0]
    out["or_mwords_per_s"] = {"without_count": round((1 << 20) / bare), "with_count": round((1 << 20) / counted)}
    return out


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench")
        .config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    catalog.QUERIES["and_pairs"](spark, sf_dir.replace("sf0.1", "sf0.001") if sf_dir.endswith("sf0.1") else sf_dir).collect()
    seconds = {}
    for name in HEADLINE:
        began = time.perf_counter()
        catalog.QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)
    found = kernels(spark, sf_dir)
    spark.stop()
    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": sf_dir, "kernels_us": found}))


if __name__ == "__main__":
    main()
