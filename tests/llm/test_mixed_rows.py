"""The mix as rows: ids that repeat, in several sources, null ids, rows that can't be told apart, clashing names."""

from collections import Counter

from pyspark.sql import functions as F

from chunkset.llm import mixing

SCHEMA = "doc_id long, text string, source string, n_chars long"


def words_by_source(rows):
    out = Counter()
    for r in rows:
        out[r["source"]] += len((r["text"] or "").split())
    return out


def check(df):
    mixed, rows = mixing.mix(df).collect(), mixing.mixed_rows(df)
    taken = Counter()
    for (source,), got in ((k, v) for k, v in _by_source(df, mixed).items()):
        taken[source] = got
    assert rows.columns == df.columns
    got = words_by_source(rows.collect())
    assert {s: n for s, n in got.items() if n} == {s: n for s, n in taken.items() if n}
    return rows


def _by_source(df, mixed):
    key = {(r["a"], r["b"]): r["source"] for r in df.select("source", mixing.row_key().alias("k")).select("source", "k.*").collect()}
    out = Counter()
    for m in mixed:
        out[(key[m["row_key"]["a"], m["row_key"]["b"]],)] += m["taken"]
    return out


def test_ids_that_repeat_in_two_sources(spark):
    rows = [(i, "w " * 50, "p", i) for i in range(200)] + [(i, "w " * 500, "q", i) for i in range(200)]
    check(spark.createDataFrame(rows, SCHEMA))


def test_null_ids_and_rows_alike(spark):
    rows = [(None, "same words here", "p", 1)] * 5000 + [(None, f"other {i}", "q", None) for i in range(300)] + [(7, None, None, None)] * 3 + [(i, "x " * (i % 90), None, 0) for i in range(800)]
    df = spark.createDataFrame(rows, SCHEMA)
    first = Counter(map(tuple, check(df).collect()))
    assert first == Counter(map(tuple, mixing.mixed_rows(df.repartition(5)).collect()))  # reruns agree
    assert mixing.mix(df).count() == len(rows)


def test_clashing_names(spark):
    df = spark.createDataFrame([(i, "a b c", "p", 0) for i in range(50)], SCHEMA)
    for name in ("row", "row_key", "copy_no", "row_of_id", "number", "piece", "least", "extra"):
        df = df.withColumn(name, F.lit("mine"))
    rows = check(df).collect()
    assert rows and all(r["row_key"] == r["number"] == r["copy_no"] == "mine" for r in rows)


def test_alike_beyond_one_piece(spark):
    df = spark.createDataFrame([(1, "a b", "p", 0), (2, "c", "p", 0)], SCHEMA)
    many = df.select(mixing.row_key().alias("row_key")).withColumn("alike", F.lit(25_001))
    got = mixing.numbered(many, "alike").groupBy("row_key").agg(F.countDistinct("number").alias("d"), F.count("*").alias("n"), F.max("number").alias("m")).collect()
    assert [(r["d"], r["n"], r["m"]) for r in got] == [(25_001, 25_001, 25_000)] * 2
