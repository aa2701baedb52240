"""All queries, each with the SQL that must give the same rows where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chunkset.functions import containers as C
from chunkset.functions import udfs
from chunkset.operators import access, baselines, index, manyway, pairwise
from chunkset.operators import build as B
from chunkset.plans import measures, workloads
from chunkset.sources import tables
from chunkset.sources.storage import saved, shared_dir
from chunkset.streaming import users

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


# -- SQL that several oracles share ------------------------------------------------------------------------------------

SLOT_IDS = """ids AS (SELECT DISTINCT set_id, id FROM (
 SELECT 'flag='||l_returnflag AS set_id, l_orderkey*8+l_linenumber AS id FROM lineitem
 UNION ALL SELECT 'status='||l_linestatus, l_orderkey*8+l_linenumber FROM lineitem
 UNION ALL SELECT 'qty='||CAST(l_quantity AS INT), l_orderkey*8+l_linenumber FROM lineitem
 UNION ALL SELECT 'disc='||CAST(round(l_discount*100) AS INT), l_orderkey*8+l_linenumber FROM lineitem
 UNION ALL SELECT 'tax='||CAST(round(l_tax*100) AS INT), l_orderkey*8+l_linenumber FROM lineitem
 UNION ALL SELECT 'year='||year(l_shipdate), l_orderkey*8+l_linenumber FROM lineitem
 UNION ALL SELECT 'part='||l_partkey, l_orderkey*8+l_linenumber FROM lineitem))"""
ROW_IDS = """nums AS (SELECT *, row_number() OVER (ORDER BY l_orderkey,l_linenumber,l_partkey,l_suppkey)-1 AS id FROM lineitem),
ids AS (SELECT DISTINCT set_id, id FROM (
 SELECT 'flag='||l_returnflag AS set_id, id FROM nums UNION ALL SELECT 'status='||l_linestatus, id FROM nums
 UNION ALL SELECT 'qty='||CAST(l_quantity AS INT), id FROM nums
 UNION ALL SELECT 'disc='||CAST(round(l_discount*100) AS INT), id FROM nums
 UNION ALL SELECT 'tax='||CAST(round(l_tax*100) AS INT), id FROM nums
 UNION ALL SELECT 'part='||l_partkey, id FROM nums UNION ALL SELECT 'supp='||l_suppkey, id FROM nums
 UNION ALL SELECT 'day='||CAST(CAST(l_shipdate AS DATE) AS VARCHAR), id FROM nums))"""
ORDER_IDS = """ids AS (SELECT DISTINCT set_id, id FROM (SELECT 'ostatus='||o_orderstatus AS set_id, o_orderkey AS id FROM orders
 UNION ALL SELECT 'oprio='||o_orderpriority, o_orderkey FROM orders))"""
EVENT_IDS = """ids AS (SELECT DISTINCT set_id, id FROM (SELECT 'day='||CAST(CAST(ts AS DATE) AS VARCHAR) AS set_id, event_id AS id FROM events
 UNION ALL SELECT 'hour='||hour(ts), event_id FROM events))"""
NUMBERED = "nums AS (SELECT row_number() OVER (ORDER BY l_orderkey)-1 AS id FROM lineitem)"
USER_MS_IDS = "ids AS (SELECT DISTINCT 'user='||user_id AS set_id, datediff('millisecond', TIMESTAMP '2024-01-01', ts) AS id FROM events)"
TERM_IDS = "ids AS (SELECT DISTINCT set_id, id FROM (SELECT unnest(string_split(lower(text),' ')) AS set_id, doc_id AS id FROM documents) WHERE set_id<>'')"
REAL_IDS = {1: ROW_IDS, 2: ORDER_IDS, 3: EVENT_IDS, 4: SLOT_IDS, 5: USER_MS_IDS}

PAIRS = [(1, "flag=A", "disc=5"), (2, "qty=1", "disc=5"), (3, "disc=5", "part=5"), (4, "disc=5", "disc=6"), (5, "flag=A", "flag=R"), (6, "qty=1", "part=5"), (7, "flag=A", "status=F"), (8, "year=1996", "tax=3")]
EXAMPLE_IDS = f"""{NUMBERED}, ids AS (SELECT 'example' AS set_id, b*196608 + CASE WHEN j<1000 THEN 62*j WHEN j<1100 THEN 65536+j-1000 ELSE 131072+2*(j-1100) END AS id
 FROM (SELECT id//33868 AS b, id%33868 AS j FROM nums))"""


def values(pairs: list[tuple]) -> str:
    return "pairs AS (SELECT * FROM (VALUES " + ",".join(f"({i},'{a}','{b}')" for i, a, b in pairs) + ") t(pair_id,left_set,right_set))"


SQL_OP = {
    "and": "SELECT * FROM l INTERSECT SELECT * FROM r",
    "or": "SELECT * FROM l UNION SELECT * FROM r",
    "andnot": "SELECT * FROM l EXCEPT SELECT * FROM r",
    "xor": "(SELECT * FROM l UNION SELECT * FROM r) EXCEPT (SELECT * FROM l INTERSECT SELECT * FROM r)",
}
SIDES = "l AS (SELECT pair_id,id FROM pairs JOIN ids ON set_id=left_set), r AS (SELECT pair_id,id FROM pairs JOIN ids ON set_id=right_set)"
SHAPE = "CAST(id>>16 AS BIGINT) AS key, CAST(CASE WHEN count(*)>4096 THEN 1 ELSE 0 END AS BIGINT) AS kind, CAST(count(*) AS BIGINT) AS card"


def pair_sql(ids: str, pairs: str, op: str, out: str = f"SELECT CAST(pair_id AS VARCHAR) AS pair, {SHAPE} FROM res GROUP BY pair_id, id>>16") -> str:
    return f"WITH {ids}, {pairs}, {SIDES}, res AS ({SQL_OP[op]}) {out}"


#: The set-up of workloads.sample_pairs.
SAMPLE = """sets AS (SELECT DISTINCT set_id, split_part(set_id,'=',1) AS attr FROM ids),
 known AS (SELECT *, row_number() OVER (PARTITION BY attr ORDER BY set_id)-1 AS v, count(*) OVER (PARTITION BY attr) AS n, dense_rank() OVER (ORDER BY attr)-1 AS a FROM sets),
 h0 AS (SELECT i, ((i+1)*1103515245+{seed}*12345) % 2147483648 AS h FROM range({twice}) t(i)),
 h1 AS (SELECT i, (xor(h, h>>13)*48271) % 2147483647 AS h FROM h0),
 drawn AS (SELECT i, h % (SELECT count(DISTINCT attr) FROM sets) AS a, h // 97 AS k FROM h1),
 chosen AS (SELECT i, set_id FROM drawn JOIN known USING (a) WHERE v = k % n),
 pairs AS (SELECT CAST(i//2 AS INT) AS pair_id, max(CASE WHEN i%2=0 THEN set_id END) AS left_set, max(CASE WHEN i%2=1 THEN set_id END) AS right_set FROM chosen GROUP BY i//2)"""

RUN_SQL = """g AS (SELECT set_id, id//31 AS g, bit_or(CAST(1 AS BIGINT) << CAST(id%31 AS INT)) AS bits FROM ids GROUP BY 1,2),
 nr AS (SELECT *, row_number() OVER (PARTITION BY set_id,bits ORDER BY g) AS rn FROM g),
 isl AS (SELECT set_id, bits, min(g) AS fg, count(*) AS len FROM nr GROUP BY set_id, bits, CASE WHEN bits=2147483647 THEN g-rn ELSE -1-g END),
 gap AS (SELECT *, coalesce(lag(fg+len) OVER (PARTITION BY set_id ORDER BY fg),0) AS aft FROM isl),
 runs AS (SELECT set_id,fg,len,bits FROM isl UNION ALL SELECT set_id,aft,fg-aft,0 FROM gap WHERE fg>aft),
 led AS (SELECT *, lead(CASE WHEN bits IN (0,2147483647) THEN bits END) OVER (PARTITION BY set_id ORDER BY fg) AS nxt FROM runs),
 fr AS (SELECT set_id, CAST(sum(CAST(ceil(len/1073741823.0) AS BIGINT)) AS BIGINT) AS words FROM runs GROUP BY 1),
 pf AS (SELECT set_id, CAST(sum(CASE WHEN bits NOT IN (0,2147483647) AND coalesce(bit_count(xor(bits,nxt))=1,false) THEN 0 ELSE CAST(ceil(len/33554432.0) AS BIGINT) END) AS BIGINT) AS words FROM led GROUP BY 1)"""
SIZE_SQL = (
    RUN_SQL
    + """,
 hc AS (SELECT set_id, id>>16 AS key, count(*) AS c FROM ids GROUP BY 1,2),
 hy AS (SELECT set_id, sum(c) AS card, sum(CASE WHEN c<=4096 THEN 2*c ELSE 8192 END+4)*8 AS bits FROM hc GROUP BY 1),
 pl AS (SELECT set_id, (max(id)>>6)+1 AS words FROM ids GROUP BY 1),
 sz AS (SELECT set_id, CAST(card AS BIGINT) AS card, CAST(hy.bits AS BIGINT) AS hybrid, pf.words*32 AS posfill, fr.words*32 AS fillrun, pl.words*64 AS plain FROM hy JOIN pf USING (set_id) JOIN fr USING (set_id) JOIN pl USING (set_id))"""
)
PER_ID_SQL = "SELECT set_id, card, round(hybrid/card,6) AS hybrid, round(posfill/card,6) AS posfill, round(fillrun/card,6) AS fillrun, round(plain/card,6) AS plain FROM sz"


def slots(spark: SparkSession, sf_dir: str, *sets: str) -> DataFrame:
    """Ids may repeat: whatever is made of them, words, runs or containers, counts an id once."""
    ids = tables.lineitem_slots(spark, sf_dir)
    return ids.filter(F.col("set_id").isin(*sets)) if sets else ids


def pairs_of(spark: SparkSession, pairs: list[tuple] = PAIRS) -> DataFrame:
    return spark.createDataFrame(pairs, "pair_id int, left_set string, right_set string")


def names_in(pairs: list[tuple]) -> list[str]:
    return sorted({s for _, a, b in pairs for s in (a, b)})


def listed(names) -> str:
    return "(" + ",".join(f"'{n}'" for n in names) + ")"


def shape(containers: DataFrame, name: str = "pair") -> DataFrame:
    return containers.select(F.col("set_id").alias(name), *[F.col(c).cast("long").alias(c) for c in ("key", "kind", "card")])


def longs(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("long") for c in cols})


# -- layout ------------------------------------------------------------------------------------------------------------


@query("SELECT o_orderkey AS id, CAST(o_orderkey>>16 AS BIGINT) AS key, CAST(o_orderkey & 65535 AS BIGINT) AS low FROM orders")
def split_ids(spark, sf_dir):
    key, low = B.split_id(F.col("o_orderkey"))
    return tables.read_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), key.cast("long").alias("key"), low.cast("long").alias("low"))


CENSUS_SQL = f"""WITH {SLOT_IDS}, c AS (SELECT set_id, id>>16 AS key, count(*) AS c FROM ids GROUP BY 1,2)
SELECT set_id, CAST(sum(CASE WHEN c<=4096 THEN 1 ELSE 0 END) AS BIGINT) AS arrays, CAST(sum(CASE WHEN c>4096 THEN 1 ELSE 0 END) AS BIGINT) AS bitmaps, CAST(sum(c) AS BIGINT) AS card, CAST(sum(CASE WHEN c<=4096 THEN 2*c ELSE 8192 END) AS BIGINT) AS payload_bytes FROM c GROUP BY 1"""


@query(CENSUS_SQL)
def container_census(spark, sf_dir):
    return B.census_of_ids(slots(spark, sf_dir))


def numbered(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.row_numbers(spark, sf_dir, "lineitem", "l_orderkey")


BOUNDARIES = (1, 4095, 4096, 4097, 65535, 65536)


@query(f"WITH {NUMBERED} SELECT 'b'||n AS pair, {SHAPE} FROM nums, (VALUES {','.join(f'({n})' for n in BOUNDARIES)}) t(n) WHERE id%65536<n GROUP BY n, id>>16")
def container_kind_boundary(spark, sf_dir):
    """The first n line items of each chunk of their row numbers."""
    ids = numbered(spark, sf_dir).select("id", F.explode(F.array(*map(F.lit, BOUNDARIES))).alias("n"))
    return shape(B.build(ids.filter("id % 65536 < n").select(F.concat(F.lit("b"), F.col("n").cast("string")).alias("set_id"), "id")))


CARD_SQL = f"WITH {SLOT_IDS} SELECT set_id, CAST(count(*) AS BIGINT) AS card FROM ids GROUP BY 1"


@query(CARD_SQL)
def build_words_card(spark, sf_dir):
    return B.words(slots(spark, sf_dir)).groupBy("set_id").agg(F.sum(F.bit_count("word")).cast("long").alias("card"))


@query(f"WITH {SLOT_IDS} SELECT set_id AS pair, {SHAPE} FROM ids GROUP BY set_id, id>>16")
def build_kernel(spark, sf_dir):
    return shape(B.build_kernel(slots(spark, sf_dir)))


@query(CARD_SQL)
def build_halves_card(spark, sf_dir):
    return B.build_halves(slots(spark, sf_dir)).groupBy("set_id").agg(F.sum("card").alias("card"))


@query(f"WITH {SLOT_IDS} SELECT set_id, id FROM ids WHERE set_id IN ('flag=A','qty=1','part=5')")
def decode_roundtrip(spark, sf_dir):
    return B.to_ids(B.build(slots(spark, sf_dir, "flag=A", "qty=1", "part=5")))


FIRST_SQL = f"WITH {SLOT_IDS} SELECT set_id, CAST(id>>16 AS BIGINT) AS key, CAST(count(*) AS BIGINT) AS card, CAST(row_number() OVER (PARTITION BY set_id ORDER BY id>>16)-1 AS BIGINT) AS pos FROM ids GROUP BY set_id, id>>16"


@query(FIRST_SQL)
def first_level_index(spark, sf_dir):
    packed = B.pack(B.build(slots(spark, sf_dir)))
    return packed.select("set_id", F.posexplode("containers").alias("pos", "c")).select("set_id", F.col("c.key").cast("long").alias("key"), F.col("c.card").cast("long").alias("card"), F.col("pos").cast("long").alias("pos"))


@query(f"WITH {SLOT_IDS} SELECT set_id AS pair, {SHAPE} FROM ids GROUP BY set_id, id>>16")
def pack_unpack(spark, sf_dir):
    return shape(B.unpack(B.pack(B.build(slots(spark, sf_dir)))))


@query(f"WITH {EXAMPLE_IDS} SELECT set_id AS pair, {SHAPE} FROM ids GROUP BY set_id, id>>16")
def example_layout(spark, sf_dir):
    return shape(B.build(tables.example_set(spark, sf_dir)))


@query(f"WITH {EXAMPLE_IDS} SELECT CAST(sum(id) AS BIGINT) AS total, CAST(count(*) AS BIGINT) AS members FROM ids")
def example_decode_sum(spark, sf_dir):
    return B.to_ids(B.build(tables.example_set(spark, sf_dir))).agg(F.sum("id").alias("total"), F.count(F.lit(1)).alias("members"))


TOY = {"a": (3, 4, 7), "b": (4, 5, 7)}
TOY_SQL = ", ".join(f"{s} AS (SELECT DISTINCT o_orderkey AS id FROM orders WHERE o_orderkey%8 IN {v})" for s, v in TOY.items())


@query(f"WITH {TOY_SQL} SELECT 'or' AS op, id FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'and', id FROM (SELECT * FROM a INTERSECT SELECT * FROM b)")
def toy_and_or(spark, sf_dir):
    """The toy sets in every eight order keys."""
    keys = tables.read_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"))
    parts = [keys.filter((F.col("id") % 8).isin(*v)).select(F.lit(s).alias("set_id"), "id") for s, v in TOY.items()]
    c = B.build(parts[0].union(parts[1]))
    pairs = pairs_of(spark, [(1, "a", "b")])
    one = lambda op: B.to_ids(pairwise.pair_op(c, pairs, op)).select(F.lit(op).alias("op"), "id")
    return one("or").union(one("and"))


@query("SELECT 'x' AS set_id, CAST(0 AS BIGINT) AS key, 'x' AS problem WHERE false")
def validate_clean(spark, sf_dir):
    return longs(B.violations(B.build(slots(spark, sf_dir))), "key")


@query(f"WITH {ORDER_IDS} SELECT set_id, CAST(count(*) AS BIGINT) AS card, count(*)*64>n AS dense, count(*)*10000>n AND count(*)*64<=n AS moderate, count(*)*1000<n AS doubtful FROM ids, (SELECT max(o_orderkey)+1 AS n FROM orders) GROUP BY set_id, n")
def suitability_bands(spark, sf_dir):
    ids = tables.order_sets(spark, sf_dir)
    return B.suitability(ids, (ids.agg(F.max("id")).first()[0] or 0) + 1)


BITS_SQL = f"""WITH {ORDER_IDS}, w AS (SELECT set_id, id>>6 AS w, bit_or(CAST(1 AS UBIGINT) << CAST(id & 63 AS INT)) AS word FROM ids WHERE set_id='ostatus=P' GROUP BY 1,2)
SELECT CAST(w AS BIGINT) AS w, CAST(b AS BIGINT) AS bit FROM w, range(64) t(b) WHERE (word >> CAST(b AS UBIGINT)) & 1 = 1"""


@query(BITS_SQL)
def extract_bits(spark, sf_dir):
    w = baselines.plain_words(tables.order_sets(spark, sf_dir).filter("set_id = 'ostatus=P'"))
    return w.select(F.col("widx").cast("long").alias("w"), F.explode(udfs.hb_lowest_bits("word")).alias("bit")).withColumn("bit", F.col("bit").cast("long"))


@query(BITS_SQL)
def extract_bits_native(spark, sf_dir):
    w = baselines.plain_words(tables.order_sets(spark, sf_dir).filter("set_id = 'ostatus=P'"))
    return w.select(F.col("widx").cast("long").alias("w"), F.explode(F.filter(F.sequence(F.lit(0), F.lit(63)), lambda i: F.bit_get("word", i) == 1)).alias("bit")).withColumn("bit", F.col("bit").cast("long"))


# -- access ------------------------------------------------------------------------------------------------------------

ACCESS = ("flag=A", "qty=1", "disc=5")


@query(f"WITH {SLOT_IDS} SELECT set_id, id FROM ids WHERE set_id IN {listed(ACCESS)} AND id%37=5")
def contains_many(spark, sf_dir):
    probes = slots(spark, sf_dir).select("id").distinct().filter("id % 37 = 5")
    return access.contains_many(B.build(slots(spark, sf_dir, *ACCESS)), probes)


@query(f"WITH {SLOT_IDS} SELECT CAST(p.id AS BIGINT) AS id, EXISTS(SELECT 1 FROM ids WHERE set_id='flag=A' AND ids.id=p.id) AS inside FROM (VALUES (1),(4),(36),(65536),(119997),(500000)) p(id)")
def contains_single(spark, sf_dir):
    c = saved(B.build(slots(spark, sf_dir, "flag=A")), "one")
    return spark.createDataFrame([(x, access.contains(c, "flag=A", x)) for x in (1, 4, 36, 65536, 119997, 500000)], "id long, inside boolean")


@query(f"WITH {SLOT_IDS}, res AS (SELECT id FROM ids WHERE set_id='qty=1' UNION SELECT i*3 FROM range(40000) t(i)) SELECT 'qty=1' AS pair, {SHAPE} FROM res GROUP BY id>>16")
def add_many(spark, sf_dir):
    return shape(access.add_many(B.build(slots(spark, sf_dir, "qty=1")), tables.range_set(spark, 0, 120000, 3, "qty=1")))


@query(f"WITH {SLOT_IDS}, res AS (SELECT id FROM ids WHERE set_id='flag=A' EXCEPT SELECT i*3 FROM range(400000) t(i)) SELECT 'flag=A' AS pair, {SHAPE} FROM res GROUP BY id>>16")
def remove_many(spark, sf_dir):
    return shape(access.remove_many(B.build(slots(spark, sf_dir, "flag=A")), tables.range_set(spark, 0, 1200000, 3, "flag=A")))


@query(f"WITH {NUMBERED}, res AS (SELECT id FROM nums WHERE id%65536<4096 UNION SELECT id FROM nums WHERE id%65536=9000) SELECT 's' AS pair, {SHAPE} FROM res GROUP BY id>>16")
def crossing_up(spark, sf_dir):
    """The first 4,096 line items of each chunk of their row numbers, and one more."""
    ids = numbered(spark, sf_dir).select(F.lit("s").alias("set_id"), "id")
    return shape(access.add_many(B.build(ids.filter("id % 65536 < 4096")), ids.filter("id % 65536 = 9000")))


@query(f"WITH {NUMBERED}, res AS (SELECT id FROM nums WHERE id%65536<4097 EXCEPT SELECT id FROM nums WHERE id%65536=7) SELECT 's' AS pair, {SHAPE} FROM res GROUP BY id>>16")
def crossing_down(spark, sf_dir):
    """The first 4,097 line items of each chunk of their row numbers, without the eighth."""
    ids = numbered(spark, sf_dir).select(F.lit("s").alias("set_id"), "id")
    return shape(access.remove_many(B.build(ids.filter("id % 65536 < 4097")), ids.filter("id % 65536 = 7")))


@query(CARD_SQL)
def cardinality(spark, sf_dir):
    return access.cardinality(B.build(slots(spark, sf_dir)))


POINTS = (0, 5, 4095, 65535, 65536, 70000, 119999, 2000000)


@query(f"WITH {SLOT_IDS} SELECT s.set_id, CAST(q.id AS BIGINT) AS id, CAST(count(i.id) AS BIGINT) AS rank FROM (SELECT DISTINCT set_id FROM ids WHERE set_id IN {listed(ACCESS)}) s CROSS JOIN (VALUES {','.join(f'({p})' for p in POINTS)}) q(id) LEFT JOIN ids i ON i.set_id=s.set_id AND i.id<=q.id GROUP BY 1,2")
def rank(spark, sf_dir):
    q = spark.createDataFrame([(s, p) for s in ACCESS for p in POINTS], "set_id string, id long")
    return access.rank(B.build(slots(spark, sf_dir, *ACCESS)), q)


@query(f"WITH {SLOT_IDS}, n AS (SELECT set_id, id, row_number() OVER (PARTITION BY set_id ORDER BY id)-1 AS j FROM ids WHERE set_id IN {listed(ACCESS)}) SELECT s.set_id, CAST(q.j AS BIGINT) AS j, n.id FROM (SELECT DISTINCT set_id FROM n) s CROSS JOIN (VALUES (0),(1),(503),(1000),(5000),(100000000)) q(j) LEFT JOIN n ON n.set_id=s.set_id AND n.j=q.j")
def select(spark, sf_dir):
    q = spark.createDataFrame([(s, j) for s in ACCESS for j in (0, 1, 503, 1000, 5000, 100000000)], "set_id string, j long")
    return access.select(B.build(slots(spark, sf_dir, *ACCESS)), q)


@query(f"WITH {SLOT_IDS} SELECT set_id, CAST(a AS BIGINT) AS low, CAST(b AS BIGINT) AS high, CAST(count(*) FILTER (id>=a AND id<b) AS BIGINT) AS members FROM ids CROSS JOIN (VALUES (0,10),(100,70000),(65536,65537),(60000,5000000)) q(a,b) WHERE set_id IN {listed(ACCESS)} GROUP BY 1,2,3")
def range_count(spark, sf_dir):
    q = spark.createDataFrame([(s, a, b) for s in ACCESS for a, b in ((0, 10), (100, 70000), (65536, 65537), (60000, 5000000))], "set_id string, low long, high long")
    return access.range_count(B.build(slots(spark, sf_dir, *ACCESS)), q)


@query(f"WITH {SLOT_IDS} SELECT set_id, min(id) AS least, max(id) AS most FROM ids GROUP BY 1")
def min_max(spark, sf_dir):
    return access.min_max(B.build(slots(spark, sf_dir)))


@query(f"WITH {SLOT_IDS}, n AS (SELECT *, row_number() OVER (PARTITION BY set_id ORDER BY id) AS k FROM ids WHERE set_id IN {listed(ACCESS)}) SELECT set_id, id FROM n WHERE k<=10")
def first_members(spark, sf_dir):
    return access.first_members(B.build(slots(spark, sf_dir, *ACCESS)), 10)


# -- pairs --------------------------------------------------------------------------------------------------------------


def register_pairs(name: str, op: str, pairs: list[tuple], make: Callable[..., DataFrame], ids: str = SLOT_IDS, **how) -> None:
    QUERIES[name] = lambda spark, sf_dir: shape(pairwise.pair_op(B.build(make(spark, sf_dir, *names_in(pairs))), pairs_of(spark, pairs), op, **how))
    ORACLES[name] = pair_sql(ids, values(pairs), op)


def row_sets(spark, sf_dir, *sets):
    return tables.lineitem_rows(spark, sf_dir).filter(F.col("set_id").isin(*sets))


for _name, _op in (("and_pairs", "and"), ("or_pairs", "or"), ("andnot_pairs", "andnot"), ("xor_pairs", "xor")):
    register_pairs(_name, _op, PAIRS, slots)
for _op in ("and", "or"):
    register_pairs(f"{_op}_bb", _op, [(1, "flag=A", "status=F")], row_sets, ROW_IDS)
    register_pairs(f"{_op}_ba", _op, [PAIRS[0]], slots)
    register_pairs(f"{_op}_inplace", _op, PAIRS, slots, inplace=True)
    register_pairs(f"{_op}_hash_join", _op, PAIRS, slots, hint="shuffle_hash")
    register_pairs(f"{_op}_merge_join", _op, PAIRS, slots, hint="merge")
register_pairs("and_pruned", "and", PAIRS, slots, prune=True)
register_pairs("and_aa_merge", "and", [PAIRS[1], PAIRS[5]], slots, method="merge")
register_pairs("and_aa_gallop", "and", [PAIRS[2]], slots)
register_pairs("or_aa_small", "or", [PAIRS[1]], slots)
register_pairs("or_aa_predicted", "or", [PAIRS[3]], slots)
register_pairs("ancestor_linear_and", "and", PAIRS, slots, method="merge")
register_pairs("ancestor_convert_after_or", "or", PAIRS, slots, predict=False)

COUNT_SQL = f"""WITH {SLOT_IDS}, {values(PAIRS)}, {SIDES}, n AS (SELECT pair_id, (SELECT count(*) FROM l WHERE l.pair_id=p.pair_id) AS a, (SELECT count(*) FROM r WHERE r.pair_id=p.pair_id) AS b,
 (SELECT count(*) FROM l JOIN r ON l.pair_id=r.pair_id AND l.id=r.id WHERE l.pair_id=p.pair_id) AS c FROM pairs p)"""


@query(f"{COUNT_SQL} SELECT pair_id, CAST(c AS BIGINT) AS shared FROM n")
def and_card(spark, sf_dir):
    return pairwise.shared(B.build(slots(spark, sf_dir, *names_in(PAIRS))), pairs_of(spark))


@query(f"{COUNT_SQL} SELECT pair_id, CAST(a+b-c AS BIGINT) AS card_or FROM n")
def or_card(spark, sf_dir):
    return pairwise.pair_counts(B.build(slots(spark, sf_dir, *names_in(PAIRS))), pairs_of(spark)).select("pair_id", "card_or")


@query(f"{COUNT_SQL} SELECT pair_id, c=a AS subset, a+b-c=c AS equal, c=0 AS disjoint FROM n")
def subset_pairs(spark, sf_dir):
    return pairwise.pair_counts(B.build(slots(spark, sf_dir, *names_in(PAIRS))), pairs_of(spark)).select("pair_id", "subset", "equal", "disjoint")


@query(f"{COUNT_SQL} SELECT pair_id, CAST(c*1000000//greatest(a+b-c,1) AS BIGINT) AS jaccard_ppm FROM n")
def jaccard_pairs(spark, sf_dir):
    return pairwise.pair_counts(B.build(slots(spark, sf_dir, *names_in(PAIRS))), pairs_of(spark)).select("pair_id", "jaccard_ppm")


@query(f"WITH {SLOT_IDS}, s AS (SELECT DISTINCT set_id FROM ids WHERE set_id IN {listed(ACCESS)}), res AS (SELECT set_id, i AS id FROM s, (SELECT unnest(range((SELECT max(id)+1 FROM ids))) AS i) EXCEPT SELECT set_id, id FROM ids) SELECT set_id AS pair, {SHAPE} FROM res GROUP BY set_id, id>>16")
def complement(spark, sf_dir):
    n = (slots(spark, sf_dir).agg(F.max("id")).first()[0] or 0) + 1
    return shape(pairwise.complement(B.build(slots(spark, sf_dir, *ACCESS)), n))


@query(pair_sql(SLOT_IDS, values(PAIRS), "and", "SELECT pair_id, id FROM res"))
def reference_and(spark, sf_dir):
    return baselines.reference_pairs(slots(spark, sf_dir, *names_in(PAIRS)), pairs_of(spark), "and")


# -- many sets ------------------------------------------------------------------------------------------------------------

MANY_SQL = f"WITH {ROW_IDS}, res AS (SELECT DISTINCT id FROM ids WHERE set_id LIKE 'day=1996-%') SELECT 'y' AS pair, {SHAPE} FROM res GROUP BY id>>16"


def many(strategy: str):
    def run(spark, sf_dir):
        ids = tables.lineitem_rows(spark, sf_dir).filter("set_id like 'day=1996-%'")
        c = B.build(ids)
        groups = ids.select("set_id").distinct().withColumn("group_id", F.lit("y"))
        return shape(manyway.union_all(c, groups, strategy))

    return run


for _s, _n in (("buffer", "union_all_heap"), ("pairwise", "union_all_pairwise"), ("words", "union_all_words"), ("builtin", "union_all_builtin")):
    QUERIES[_n], ORACLES[_n] = many(_s), MANY_SQL

@query(f"WITH {ROW_IDS}, res AS (SELECT DISTINCT id FROM ids WHERE split_part(set_id,'=',1)='part' AND CAST(split_part(set_id,'=',2) AS INT)<200) SELECT 'p' AS pair, {SHAPE} FROM res GROUP BY id>>16")
def union_200_parts(spark, sf_dir):
    names = [f"part={i}" for i in range(200)]
    c = B.build(row_sets(spark, sf_dir, *names))
    return shape(manyway.union_all(c, spark.createDataFrame([("p", n) for n in names], "group_id string, set_id string")))


GROUPS = [("g1", "flag=A"), ("g1", "status=F"), ("g1", "disc=5"), ("g2", "flag=R"), ("g2", "qty=7"), ("g2", "tax=3")]
GROUP_SQL = "gr AS (SELECT * FROM (VALUES " + ",".join(f"('{g}','{s}')" for g, s in GROUPS) + ") t(group_id,set_id)), m AS (SELECT group_id, id, count(*) AS n FROM gr JOIN ids USING (set_id) GROUP BY 1,2)"


def groups_of(spark):
    return spark.createDataFrame(GROUPS, "group_id string, set_id string")


@query(f"WITH {SLOT_IDS}, {GROUP_SQL} SELECT group_id AS pair, {SHAPE} FROM m WHERE n=3 GROUP BY group_id, id>>16")
def intersect_all(spark, sf_dir):
    return shape(manyway.intersect_all(B.build(slots(spark, sf_dir, *[s for _, s in GROUPS])), groups_of(spark)))


@query(f"WITH {SLOT_IDS}, {GROUP_SQL} SELECT group_id AS set_id, id FROM m WHERE n>=2")
def threshold_t_of_k(spark, sf_dir):
    return manyway.threshold(B.build(slots(spark, sf_dir, *[s for _, s in GROUPS])), groups_of(spark), 2)


@query(f"WITH {SLOT_IDS}, {GROUP_SQL} SELECT group_id AS set_id, id FROM m WHERE n>=2")
def threshold_by_rows(spark, sf_dir):
    return manyway.threshold(B.build(slots(spark, sf_dir, *[s for _, s in GROUPS])), groups_of(spark), 2, "rows")


WORD_SQL = "w AS (SELECT set_id, id>>6 AS w, bit_or(CAST(1 AS UBIGINT) << CAST(id & 63 AS INT)) AS word FROM ids GROUP BY 1,2)"


@query(f"WITH {SLOT_IDS}, {WORD_SQL} SELECT set_id, CAST(bit_count(bit_or(word)) AS BIGINT) AS any_bits, CAST(bit_count(bit_and(word)) AS BIGINT) AS all_bits, CAST(bit_count(bit_xor(word)) AS BIGINT) AS odd_bits, CAST(sum(bit_count(word)) AS BIGINT) AS ones FROM w GROUP BY 1")
def word_aggregates(spark, sf_dir):
    return longs(manyway.word_aggregate(slots(spark, sf_dir)), "any_bits", "all_bits", "odd_bits", "ones")


# -- baselines ---------------------------------------------------------------------------------------------------------


@query(f"WITH {SLOT_IDS} SELECT set_id, CAST((max(id)>>6)+1 AS BIGINT) AS words FROM ids GROUP BY 1")
def plain_encode_size(spark, sf_dir):
    return baselines.plain_sizes(slots(spark, sf_dir))


@query(f"""WITH {SLOT_IDS}, w AS (SELECT DISTINCT set_id, (id>>6)+1 AS w FROM ids)
SELECT set_id, CAST(list_reduce(list_prepend(CAST(1 AS BIGINT), list(CAST(w AS BIGINT) ORDER BY w)), lambda a, x: CASE WHEN x>a THEN greatest(2*a, x) ELSE a END) AS BIGINT) AS words FROM w GROUP BY 1""")
def plain_doubling_size(spark, sf_dir):
    return baselines.doubled_capacity(slots(spark, sf_dir))


def _plain(op):
    def run(spark, sf_dir):
        words = baselines.plain_pairs(slots(spark, sf_dir, *names_in(PAIRS)), pairs_of(spark), op)
        return words.groupBy("pair_id").agg(F.count(F.lit(1)).alias("words"), F.sum(F.bit_count("word")).cast("long").alias("card"))

    return run


for _op in ("and", "or"):
    QUERIES[f"plain_{_op}"] = _plain(_op)
    ORACLES[f"plain_{_op}"] = pair_sql(SLOT_IDS, values(PAIRS), _op, "SELECT pair_id, CAST(count(DISTINCT id>>6) AS BIGINT) AS words, CAST(count(*) AS BIGINT) AS card FROM res GROUP BY 1")


@query(CARD_SQL)
def builtin_bitmap_count(spark, sf_dir):
    ids = slots(spark, sf_dir)
    halves = ids.groupBy("set_id", F.expr("id div 32768").alias("h")).agg(F.bitmap_construct_agg(F.col("id") % 32768).alias("b"))
    return halves.groupBy("set_id").agg(F.sum(F.bitmap_count("b")).alias("card"))


SIZED = ("flag=A", "qty=1", "disc=5", "part=5", "year=1996", "status=F")


@query(f"WITH {SLOT_IDS}, {RUN_SQL} SELECT set_id, words FROM fr")
def fillrun_words(spark, sf_dir):
    return baselines.word_counts(slots(spark, sf_dir), "fillrun")


@query(f"WITH {SLOT_IDS}, {RUN_SQL} SELECT set_id, words FROM pf")
def posfill_words(spark, sf_dir):
    return baselines.word_counts(slots(spark, sf_dir), "posfill")


@query(f"WITH {EVENT_IDS}, {RUN_SQL} SELECT set_id, CAST(fg AS BIGINT) AS first_group, CAST(len AS BIGINT) AS length, CAST(bits AS BIGINT) AS bits FROM runs")
def fillrun_runs(spark, sf_dir):
    return longs(baselines.run_rows(workloads.real_sets(spark, sf_dir, 3)), "first_group", "length", "bits")


@query(f"WITH {EVENT_IDS} SELECT set_id, id FROM ids WHERE set_id LIKE 'day=%'")
def run_rows_decode(spark, sf_dir):
    return baselines.run_ids(baselines.run_rows(workloads.real_sets(spark, sf_dir, 3).filter("set_id like 'day=%'")))


def _codec(codec):
    def encoded(spark, sf_dir):
        return baselines.encode_streams(slots(spark, sf_dir, *SIZED), codec).select("set_id", "words")

    def round_trip(spark, sf_dir):
        return baselines.decode_streams(baselines.encode_streams(slots(spark, sf_dir, *SIZED), codec), codec)

    def op(which):
        def run(spark, sf_dir):
            streams = baselines.encode_streams(slots(spark, sf_dir, *names_in(PAIRS)), codec)
            out = baselines.stream_pairs(streams, pairs_of(spark), codec, which)
            return baselines.decode_streams(out.withColumn("set_id", F.col("pair_id").cast("string")), codec).groupBy(F.col("set_id").alias("pair")).agg(F.count(F.lit(1)).alias("card"), F.sum("id").alias("total"))

        return run

    cte = {"fillrun": "fr", "posfill": "pf"}[codec]
    QUERIES[f"{codec}_stream_words"], ORACLES[f"{codec}_stream_words"] = encoded, f"WITH {SLOT_IDS}, {RUN_SQL} SELECT set_id, words FROM {cte} WHERE set_id IN {listed(SIZED)}"
    QUERIES[f"{codec}_roundtrip"], ORACLES[f"{codec}_roundtrip"] = round_trip, f"WITH {SLOT_IDS} SELECT set_id, id FROM ids WHERE set_id IN {listed(SIZED)}"
    for which in ("and", "or"):
        QUERIES[f"{codec}_{which}"] = op(which)
        ORACLES[f"{codec}_{which}"] = pair_sql(SLOT_IDS, values(PAIRS), which, "SELECT CAST(pair_id AS VARCHAR) AS pair, CAST(count(*) AS BIGINT) AS card, CAST(sum(id) AS BIGINT) AS total FROM res GROUP BY 1")


for _c in ("fillrun", "posfill"):
    _codec(_c)


def _run_pairs(op):
    def run(spark, sf_dir):
        out = baselines.run_pairs(slots(spark, sf_dir, *names_in(PAIRS)), pairs_of(spark), op)
        return out.groupBy("pair_id").agg(F.sum(F.bit_count("bits") * F.col("length")).cast("long").alias("card"))

    return run


for _op in ("and", "or"):
    QUERIES[f"run_rows_{_op}"] = _run_pairs(_op)
    ORACLES[f"run_rows_{_op}"] = pair_sql(SLOT_IDS, values(PAIRS), _op, "SELECT pair_id, CAST(count(*) AS BIGINT) AS card FROM res GROUP BY 1")

# -- measures and workloads ----------------------------------------------------------------------------------------------


@query(f"WITH {SLOT_IDS}, {SIZE_SQL} {PER_ID_SQL}")
def bits_per_int_table(spark, sf_dir):
    return measures.bits_per_id(measures.sizes(slots(spark, sf_dir)))


EXPANSION_SQL = "long AS (SELECT 'posfill' AS scheme, posfill AS b, hybrid FROM sz UNION ALL SELECT 'fillrun', fillrun, hybrid FROM sz UNION ALL SELECT 'plain', plain, hybrid FROM sz) SELECT scheme, round(sum(b)/sum(hybrid),6) AS of_sums, round(avg(b/hybrid),6) AS mean_of_ratios FROM long GROUP BY 1"


@query(f"WITH {SLOT_IDS}, {SIZE_SQL}, {EXPANSION_SQL}")
def size_expansion(spark, sf_dir):
    return measures.expansion(measures.sizes(slots(spark, sf_dir)))


@query("SELECT 'x' AS set_id, CAST(0 AS BIGINT) AS key, CAST(0 AS BIGINT) AS card WHERE false")
def bound_check(spark, sf_dir):
    return measures.bounds(slots(spark, sf_dir))


@query(f"WITH {ORDER_IDS} SELECT set_id, round(count(*)/(SELECT count(*) FROM orders),8) AS density FROM ids GROUP BY 1")
def density_profile(spark, sf_dir):
    n = tables.read_table(spark, sf_dir, "orders").count()
    return tables.order_sets(spark, sf_dir).groupBy("set_id").agg(F.round(F.countDistinct("id") / F.lit(n), 8).alias("density"))


G1 = """tot AS (SELECT count(o_orderkey) AS n, greatest(1, (count(o_orderkey)+99999)//100000) AS k FROM orders),
 g0 AS (SELECT s, o_orderkey % k AS part, greatest(1, n//k) AS draws, ((o_orderkey % 2147483648)*1103515245+s*12345) % 2147483648 AS a FROM orders, tot, (VALUES {seeds}) u(s) WHERE o_orderkey IS NOT NULL),
 g1 AS (SELECT s, part, draws, (xor(a,a>>15)*48271) % 2147483647 AS b FROM g0), g2 AS (SELECT s, part, draws, (xor(b,b>>13)*69621) % 2147483647 AS y FROM g1)"""
EXPONENTS = (1, 2, 3, 4, 5, 6, 8, 10)


def synthetic_sql(dist: str, exponents, seeds=(42,)) -> str:
    value = "y*(draws*{m}) // 2147483647" if dist == "uniform" else "((y*y) // 2147483648)*(draws*{m}) // 2147483648"
    parts = " UNION ".join(f"SELECT '{dist}-{e}-'||s||'-'||part AS set_id, {value.format(m=1 << e)} AS id FROM g2" for e in exponents)
    return G1.format(seeds=",".join(f"({s})" for s in seeds)) + f", ids AS (SELECT DISTINCT set_id, id FROM ({parts}))"


for _d in ("uniform", "beta"):
    QUERIES[f"syn_{_d}_sizes"] = lambda spark, sf_dir, d=_d: measures.bits_per_id(measures.sizes(tables.synthetic(spark, sf_dir, EXPONENTS, d)))
    ORACLES[f"syn_{_d}_sizes"] = f"WITH {synthetic_sql(_d, EXPONENTS)}, {SIZE_SQL} {PER_ID_SQL}"

SYN_EXPONENTS = (1, 4, 6)
SYN_PAIRS_SQL = "pairs AS (SELECT part*16+e AS pair_id, 'beta-'||e||'-1-'||part AS left_set, 'beta-'||e||'-2-'||part AS right_set FROM (VALUES (1),(4),(6)) t(e), (SELECT DISTINCT part FROM g2))"


def synthetic_pairs(spark, sf_dir):
    """Of each part and exponent, the sets by both seeds."""
    e = spark.range(tables.draw_parts(spark, sf_dir)[0]).select(F.col("id").alias("part"), F.explode(F.array(*map(F.lit, SYN_EXPONENTS))).alias("e"))
    name = lambda s: F.format_string(f"beta-%d-{s}-%d", "e", "part")
    return e.select((F.col("part") * 16 + F.col("e")).cast("int").alias("pair_id"), name(1).alias("left_set"), name(2).alias("right_set"))


for _op in ("and", "or"):
    QUERIES[f"syn_{_op}"] = lambda spark, sf_dir, op=_op: shape(pairwise.pair_op(B.build(tables.synthetic(spark, sf_dir, SYN_EXPONENTS, "beta", (1, 2))), synthetic_pairs(spark, sf_dir), op))
    ORACLES[f"syn_{_op}"] = pair_sql(synthetic_sql("beta", SYN_EXPONENTS, (1, 2)), SYN_PAIRS_SQL, _op)

N_PAIRS = 100


def sample_sql(which: int, pairs: int = N_PAIRS) -> str:
    named = {1: REAL_IDS[1], 4: REAL_IDS[4]}.get(which, REAL_IDS[which])
    keep = "ids0 AS"
    ids = named.replace("ids AS", keep, 1) + f", ids AS (SELECT * FROM ids0 WHERE split_part(set_id,'=',1) IN {listed(workloads.REAL[which])})"
    return ids + ", " + SAMPLE.format(seed=42, twice=2 * pairs)


@query(f"WITH {sample_sql(4)} SELECT * FROM pairs")
def sample_pairs(spark, sf_dir):
    return workloads.sample_pairs(workloads.set_names(spark, sf_dir, 4), N_PAIRS)


def _real(which: int, op: str):
    def run(spark, sf_dir):
        pairs = saved(workloads.sample_pairs(workloads.set_names(spark, sf_dir, which), N_PAIRS), "pairs")
        out = pairwise.pair_op(B.build(workloads.of_pairs(workloads.real_sets(spark, sf_dir, which), pairs)), pairs, op)
        return out.groupBy(F.col("set_id").alias("pair")).agg(F.sum("card").alias("card"))

    return run


for _w in workloads.REAL:
    for _op in ("and", "or"):
        QUERIES[f"real{_w}_{_op}"] = _real(_w, _op)
        ORACLES[f"real{_w}_{_op}"] = f"WITH {sample_sql(_w)}, {SIDES}, res AS ({SQL_OP[_op]}) SELECT CAST(pair_id AS VARCHAR) AS pair, CAST(count(*) AS BIGINT) AS card FROM res GROUP BY 1"

SAMPLED = "used AS (SELECT * FROM ids WHERE set_id IN (SELECT left_set FROM pairs UNION SELECT right_set FROM pairs))"


def _table(which: int, what: str):
    def run(spark, sf_dir):
        pairs = saved(workloads.sample_pairs(workloads.set_names(spark, sf_dir, which), N_PAIRS), "pairs")
        used = workloads.of_pairs(workloads.real_sets(spark, sf_dir, which), pairs)
        if what == "expansion":
            return measures.expansion(measures.sizes(used))
        n = {1: "lineitem", 2: "orders", 3: "events", 4: "lineitem"}[which]
        return measures.profile(used, tables.read_table(spark, sf_dir, n).count())

    return run


for _w in (1, 2, 3, 4):
    _n = {1: "lineitem", 2: "orders", 3: "events", 4: "lineitem"}[_w]
    QUERIES[f"table1_profile_{_w}"], QUERIES[f"table2_expansion_{_w}"] = _table(_w, "profile"), _table(_w, "expansion")
    ORACLES[f"table1_profile_{_w}"] = f"""WITH {sample_sql(_w)}, {SAMPLED}, hc AS (SELECT set_id, id>>16 AS key, count(*) AS c FROM used GROUP BY 1,2), hy AS (SELECT set_id, sum(c) AS card, sum(CASE WHEN c<=4096 THEN 2*c ELSE 8192 END+4)*8 AS bits FROM hc GROUP BY 1)
 SELECT CAST((SELECT count(*) FROM {_n}) AS BIGINT) AS n_rows, CAST(count(*) AS BIGINT) AS sets, round(avg(card/(SELECT count(*) FROM {_n})),8) AS density, round(sum(bits)/sum(card),6) AS bits_per_item FROM hy"""
    ORACLES[f"table2_expansion_{_w}"] = f"WITH {sample_sql(_w)}, {SAMPLED}, " + SIZE_SQL.replace("FROM ids", "FROM used") + f", {EXPANSION_SQL}"


@query(f"WITH {USER_MS_IDS}, {SIZE_SQL}, {EXPANSION_SQL}")
def table2_expansion_5(spark, sf_dir):
    """The data that the hybrid doesn't suit: few ids in a wide universe."""
    return measures.expansion(measures.sizes(workloads.real_sets(spark, sf_dir, 5)))


@query(f"WITH nums AS (SELECT row_number() OVER (ORDER BY o_orderkey)-1 AS i FROM orders), ids AS (SELECT 'period=62' AS set_id, 62*i AS id FROM nums UNION ALL SELECT 'period=31', 31*i FROM nums), {SIZE_SQL} {PER_ID_SQL}")
def period_sizes(spark, sf_dir):
    """Row numbers of the orders, spread by 62 and by 31."""
    rows = tables.row_numbers(spark, sf_dir, "orders", "o_orderkey")
    spread = [rows.select(F.lit(f"period={p}").alias("set_id"), (F.col("id") * p).alias("id")) for p in (62, 31)]
    return measures.bits_per_id(measures.sizes(spread[0].union(spread[1])))


PACKED_SQL = f"""WITH {SLOT_IDS}, v AS (SELECT set_id, id>>16 AS key, id, lead(id) OVER (PARTITION BY set_id, id>>16 ORDER BY id)-id-1 AS gap FROM ids),
 c AS (SELECT set_id, key, count(*) AS n, greatest(1, length(ltrim(bin(coalesce(max(gap),0)),'0'))) AS width FROM v GROUP BY 1,2)
 SELECT set_id, CAST(sum(CASE WHEN n=1 THEN 21 ELSE 21+(n-1)*width END) AS BIGINT) AS packed_bits, CAST(sum(16*n) AS BIGINT) AS array_bits FROM c WHERE n<=4096 GROUP BY 1"""


@query(PACKED_SQL)
def packed_arrays(spark, sf_dir):
    """Array containers with their gaps packed at one width each; every one is unpacked again, and raises if it differs."""

    def work(r: dict):
        box = C.from_payload(r["kind"], r["payload"])
        if C.unpack_gaps(C.pack_gaps(box), box.card).payload != box.payload:
            raise ValueError("a packed container differs from its values")
        yield r["set_id"], C.packed_bits(box), 16 * box.card

    arrays = B.build(slots(spark, sf_dir)).filter(F.col("kind") == C.ARRAY).select("set_id", "kind", "payload")
    bits = B.kernel(arrays, "set_id string, packed long, plain long", work)
    return bits.groupBy("set_id").agg(F.sum("packed").alias("packed_bits"), F.sum("plain").alias("array_bits"))


SORT_SQL = "nums AS (SELECT l_returnflag, row_number() OVER (ORDER BY {order})-1 AS id FROM lineitem), ids AS (SELECT '{tag}flag='||l_returnflag AS set_id, id FROM nums)"


@query(f"WITH {SORT_SQL.format(order='l_orderkey,l_linenumber,l_partkey,l_suppkey', tag='as-is ')}, {SIZE_SQL} {PER_ID_SQL} UNION ALL (WITH {SORT_SQL.format(order='l_returnflag,l_shipdate,l_orderkey,l_linenumber,l_partkey,l_suppkey', tag='sorted ')}, {SIZE_SQL} {PER_ID_SQL})")
def sort_ablation_sizes(spark, sf_dir):
    t = tables.read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag", "l_shipdate")
    key = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    one = lambda order, tag: tables.to_id_sets(tables.dense_row_ids(t, order), F.col("id"), {f"{tag} flag": F.col("l_returnflag")})
    return measures.bits_per_id(measures.sizes(one(key, "as-is").union(one(["l_returnflag", "l_shipdate", *key], "sorted"))))


STAR_SQL = """SELECT CAST(count(*) AS BIGINT) AS n, round(sum(l_extendedprice),2) AS price FROM lineitem WHERE l_returnflag='R' AND CAST(l_quantity AS INT)<10 AND CAST(round(l_discount*100) AS INT)<>0"""


@query(STAR_SQL)
def star_filter(spark, sf_dir):
    t = tables.read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag", "l_quantity", "l_discount", "l_extendedprice")
    rows = saved(tables.dense_row_ids(t, ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]), "rows")
    named = {k: v for k, v in tables.lineitem_attributes().items() if k in ("flag", "qty", "disc")}
    idx = saved(B.build(tables.to_id_sets(rows, F.col("id"), named)), "index")
    p = index.And((index.Eq("flag", "R"), index.Between("qty", None, 9), index.Not(index.Eq("disc", 0))))
    return index.rows_where(rows, "id", idx, p).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@query("SELECT o_orderkey AS id FROM orders WHERE o_orderpriority IN ('1-URGENT','2-HIGH') OR o_orderstatus='P'")
def predicate_or_in(spark, sf_dir):
    idx = saved(B.build(tables.order_sets(spark, sf_dir)), "index")
    return index.ids_where(idx, index.Or((index.In("oprio", ("1-URGENT", "2-HIGH")), index.Eq("ostatus", "P"))))


@query("SELECT o_orderkey AS id FROM orders WHERE NOT (o_orderstatus='F')")
def predicate_not(spark, sf_dir):
    return index.ids_where(saved(B.build(tables.order_sets(spark, sf_dir)), "index"), index.Not(index.Eq("ostatus", "F")))


@query("SELECT n_nationkey AS id FROM (SELECT n_nationkey, CASE WHEN n_nationkey%3=0 THEN NULL ELSE n_regionkey END AS r FROM nation) WHERE NOT (r=1)")
def predicate_not_null(spark, sf_dir):
    t = tables.read_table(spark, sf_dir, "nation").select("n_nationkey", F.when(F.col("n_nationkey") % 3 != 0, F.col("n_regionkey")).alias("r"))
    return index.ids_where(B.build(tables.to_id_sets(t, F.col("n_nationkey"), {"r": F.col("r")})), index.Not(index.Eq("r", 1)))


TERMS = [(1, "the", "and"), (2, "the", "of"), (3, "de", "le")]


def posting_lists(spark, sf_dir, *words):
    return tables.terms(spark, sf_dir).filter(F.col("set_id").isin(*words))


for _op in ("and", "or"):
    register_pairs(f"inverted_{_op}", _op, TERMS, posting_lists, TERM_IDS)


@query(f"WITH {TERM_IDS} SELECT 'q' AS set_id, id FROM ids WHERE set_id IN ('the','and','of','de','que') GROUP BY id HAVING count(*)>=3")
def inverted_t_of_k(spark, sf_dir):
    words = ("the", "and", "of", "de", "que")
    return manyway.threshold(B.build(posting_lists(spark, sf_dir, *words)), spark.createDataFrame([("q", w) for w in words], "group_id string, set_id string"), 3)


@query(f"WITH {TERM_IDS}, n AS (SELECT set_id, count(*) AS card FROM ids GROUP BY 1) SELECT set_id, CAST(card AS BIGINT) AS card, CAST(rk AS BIGINT) AS rk FROM (SELECT *, rank() OVER (ORDER BY card DESC) AS rk FROM n) WHERE rk<=20")
def top_sets(spark, sf_dir):
    counts = saved(access.cardinality(B.build(tables.terms(spark, sf_dir))), "term-counts")
    least = counts.orderBy(F.desc("card")).limit(20).agg(F.min("card").alias("least"))
    return counts.join(F.broadcast(least), F.col("card") >= F.col("least")).drop("least").withColumn("rk", F.rank().over(W.orderBy(F.desc("card"))).cast("long")).filter("rk <= 20")


@query("SELECT 'quality='||quality AS set_id, CAST(count(DISTINCT doc_id) AS BIGINT) AS card FROM labels GROUP BY 1 UNION ALL SELECT 'toxic='||toxic, CAST(count(DISTINCT doc_id) AS BIGINT) FROM labels GROUP BY 1")
def label_sets(spark, sf_dir):
    t = tables.read_table(spark, sf_dir, "labels")
    return access.cardinality(B.build(tables.to_id_sets(t, F.col("doc_id"), {"quality": F.col("quality"), "toxic": F.col("toxic")})))


@query("SELECT 'scheme='||split_part(url,':',1) AS set_id, CAST(count(DISTINCT page_id) AS BIGINT) AS card FROM pages WHERE url LIKE '%:%' GROUP BY 1")
def page_sets(spark, sf_dir):
    t = tables.read_table(spark, sf_dir, "pages").filter("url like '%:%'")
    return access.cardinality(B.build(tables.to_id_sets(t, F.col("page_id"), {"scheme": F.substring_index("url", ":", 1)})))


@query("SELECT 'role='||role AS set_id, CAST(count(DISTINCT conv_id*16+turn) AS BIGINT) AS card FROM conversations GROUP BY 1")
def conversation_sets(spark, sf_dir):
    t = tables.read_table(spark, sf_dir, "conversations")
    return access.cardinality(B.build(tables.to_id_sets(t, F.col("conv_id") * 16 + F.col("turn"), {"role": F.col("role")})))


@query("SELECT 'label='||label AS set_id, CAST(count(DISTINCT vec_id) AS BIGINT) AS card FROM embeddings GROUP BY 1")
def embedding_sets(spark, sf_dir):
    t = tables.read_table(spark, sf_dir, "embeddings")
    return access.cardinality(B.build(tables.to_id_sets(t, F.col("vec_id"), {"label": F.col("label")})))


# -- the surface around the sets --------------------------------------------------------------------------------------


def user_words(spark, sf_dir):
    """Finest distinct-user sets, by day and type: words of 64 users."""
    e = tables.read_table(spark, sf_dir, "events").select(F.to_date("ts").cast("string").alias("day"), "event_type", "user_id")
    return e.groupBy("day", "event_type", F.expr("user_id div 64").alias("w")).agg(F.expr("bit_or(shiftleft(1L, cast(user_id % 64 as int)))").alias("word"))


def _levels(how: str):
    def run(spark, sf_dir):
        w = user_words(spark, sf_dir)
        merged = getattr(w, how)("day", "event_type", "w").agg(F.bit_or("word").alias("word"), F.grouping("w").alias("gw")).filter("gw = 0")
        return merged.groupBy("day", "event_type").agg(F.sum(F.bit_count("word")).cast("long").alias("users"))

    return run


QUERIES["distinct_cube"] = _levels("cube")
ORACLES["distinct_cube"] = "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type, CAST(count(DISTINCT user_id) AS BIGINT) AS users FROM events GROUP BY CUBE (CAST(ts AS DATE), event_type)"


@query("SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type, CAST(count(DISTINCT user_id) AS BIGINT) AS users FROM events GROUP BY ROLLUP (CAST(ts AS DATE), event_type)")
def distinct_users_rollup(spark, sf_dir):
    w = user_words(spark, sf_dir)
    levels = w.select("w", "word", F.explode(F.array(*[F.struct(d.alias("day"), t.alias("event_type")) for d, t in ((F.col("day"), F.col("event_type")), (F.col("day"), F.lit(None).cast("string")), (F.lit(None).cast("string"), F.lit(None).cast("string")))])).alias("k"))
    merged = levels.groupBy("k.day", "k.event_type", "w").agg(F.bit_or("word").alias("word"))
    return merged.groupBy("day", "event_type").agg(F.sum(F.bit_count("word")).cast("long").alias("users"))


@query("SELECT CAST(count(DISTINCT user_id) AS BIGINT) AS users FROM events")
def distinct_exact(spark, sf_dir):
    e = tables.read_table(spark, sf_dir, "events").select(F.lit("u").alias("set_id"), F.col("user_id").alias("id"))
    return access.cardinality(B.build(e)).select(F.col("card").alias("users"))


@query()
def distinct_approximate(spark, sf_dir):
    e = tables.read_table(spark, sf_dir, "events")
    both = e.agg(F.countDistinct("user_id").alias("exact"), F.approx_count_distinct("user_id", 0.02).alias("approximate"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("sketch"))
    return both.withColumn("error", F.abs(F.col("approximate") - F.col("exact")) / F.col("exact"))


@query("WITH f AS (SELECT user_id, min(CAST(ts AS DATE)) AS d FROM events GROUP BY 1), n AS (SELECT d, count(*) AS c FROM f GROUP BY 1), days AS (SELECT DISTINCT CAST(ts AS DATE) AS d FROM events) SELECT CAST(days.d AS VARCHAR) AS day, CAST(coalesce(c,0) AS BIGINT) AS new_users, CAST(sum(coalesce(c,0)) OVER (ORDER BY days.d) AS BIGINT) AS users FROM days LEFT JOIN n USING (d)")
def cumulative_users(spark, sf_dir):
    e = tables.read_table(spark, sf_dir, "events").select(F.to_date("ts").alias("d"), "user_id")
    first = e.groupBy("user_id").agg(F.min("d").alias("d")).groupBy("d").agg(F.count(F.lit(1)).alias("c"))
    days = e.select("d").distinct().join(first, "d", "left").select("d", F.coalesce("c", F.lit(0)).alias("new_users"))
    return days.select(F.col("d").cast("string").alias("day"), "new_users", F.sum("new_users").over(W.orderBy("d")).alias("users"))


SEMI = "o_orderkey, o_custkey FROM orders WHERE"


@query(f"SELECT {SEMI} o_orderstatus='P'")
def semi_by_set(spark, sf_dir):
    c = B.build(tables.order_sets(spark, sf_dir).filter("set_id = 'ostatus=P'"))
    return pairwise.rows_in(tables.read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), "o_orderkey", c)


@query(f"SELECT {SEMI} o_orderstatus<>'P'")
def anti_by_set(spark, sf_dir):
    c = B.build(tables.order_sets(spark, sf_dir).filter("set_id = 'ostatus=P'"))
    return pairwise.rows_not_in(tables.read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), "o_orderkey", c)


@query("SELECT 'k='||json_extract_string(props,'$.k') AS set_id, CAST(count(DISTINCT event_id) AS BIGINT) AS card FROM events WHERE json_extract_string(props,'$.k') IS NOT NULL GROUP BY 1")
def props_sets(spark, sf_dir):
    t = tables.read_table(spark, sf_dir, "events")
    return access.cardinality(B.build(tables.to_id_sets(t, F.col("event_id"), {"k": F.get_json_object("props", "$.k")})))


@query(f"WITH {ORDER_IDS} SELECT split_part(set_id,'=',1) AS attr, split_part(set_id,'=',2) AS value, CAST(count(*) AS BIGINT) AS card FROM ids GROUP BY 1,2")
def value_summary(spark, sf_dir):
    c = access.cardinality(B.build(tables.order_sets(spark, sf_dir))).withColumn("attr", F.substring_index("set_id", "=", 1))
    maps = c.groupBy("attr").agg(F.map_from_entries(F.collect_list(F.struct(F.substring_index("set_id", "=", -1), "card"))).alias("m"))
    return maps.select("attr", F.explode("m").alias("value", "card"))


@query("SELECT o_orderkey AS id FROM orders WHERE o_orderstatus='P'")
def udtf_explode(spark, sf_dir):
    udfs.register(spark)
    B.build(tables.order_sets(spark, sf_dir).filter("set_id = 'ostatus=P'")).createOrReplaceTempView("chunkset_containers")
    return spark.sql("SELECT e.id FROM chunkset_containers c, LATERAL hb_explode(c.key, CAST(c.kind AS INT), c.payload) e")


@query(f"WITH {SLOT_IDS}, a AS (SELECT id FROM ids WHERE set_id='flag=A'), b AS (SELECT id FROM ids WHERE set_id='disc=5') SELECT CAST(id>>16 AS BIGINT) AS key, CAST(count(*) FILTER (x AND y) AS BIGINT) AS n_and, CAST(count(*) AS BIGINT) AS n_or, CAST(count(*) FILTER (x AND NOT y) AS BIGINT) AS n_andnot FROM (SELECT id, bool_or(s='a') AS x, bool_or(s='b') AS y FROM (SELECT id,'a' AS s FROM a UNION ALL SELECT id,'b' FROM b) GROUP BY id) GROUP BY id>>16")
def sql_functions(spark, sf_dir):
    udfs.register(spark)
    B.build(slots(spark, sf_dir, "flag=A", "disc=5")).createOrReplaceTempView("chunkset_two")
    return spark.sql(
        """SELECT CAST(a.key AS BIGINT) AS key, CAST(hb_and(a.kind, a.payload, b.kind, b.payload).card AS BIGINT) AS n_and,
        CAST(hb_or(a.kind, a.payload, b.kind, b.payload).card AS BIGINT) AS n_or, CAST(hb_andnot(a.kind, a.payload, b.kind, b.payload).card AS BIGINT) AS n_andnot
        FROM (SELECT * FROM chunkset_two WHERE set_id = 'flag=A') a JOIN (SELECT * FROM chunkset_two WHERE set_id = 'disc=5') b ON a.key = b.key"""
    )


POINT_SQL = f"""WITH {SLOT_IDS}, x AS (SELECT id>>16 AS key, id & 65535 AS low FROM ids WHERE set_id='flag=A'), n AS (SELECT *, row_number() OVER (PARTITION BY key ORDER BY low)-1 AS j FROM x)
SELECT CAST(key AS BIGINT) AS key, CAST(count(*) AS BIGINT) AS card, CAST(count(*) FILTER (low<=5000) AS BIGINT) AS up_to_5000, CAST(max(CASE WHEN j=7 THEN low END) AS BIGINT) AS eighth, coalesce(bool_or(low=36),false) AS has_36 FROM n GROUP BY key"""


@query(POINT_SQL)
def sql_point_functions(spark, sf_dir):
    udfs.register(spark)
    B.build(slots(spark, sf_dir, "flag=A")).createOrReplaceTempView("chunkset_one")
    return spark.sql(
        """SELECT CAST(key AS BIGINT) AS key, CAST(hb_card(kind, payload) AS BIGINT) AS card, CAST(hb_rank(kind, payload, 5000) AS BIGINT) AS up_to_5000,
        CAST(hb_select(kind, payload, 7) AS BIGINT) AS eighth, hb_contains(kind, payload, 36) AS has_36 FROM chunkset_one"""
    )


@query(f"WITH {SLOT_IDS}, a AS (SELECT id FROM ids WHERE set_id='flag=A'), b AS (SELECT id FROM ids WHERE set_id='disc=5'), n AS (SELECT id, count(*) AS c FROM (SELECT id FROM a UNION ALL SELECT id FROM b) GROUP BY id) SELECT CAST(id>>16 AS BIGINT) AS key, CAST(count(*) FILTER (c=1) AS BIGINT) AS n_xor, CAST(count(*) FILTER (c=2) AS BIGINT) AS n_both FROM n GROUP BY id>>16 HAVING count(*) FILTER (c=2)>0")
def sql_xor_and_aggregate(spark, sf_dir):
    udfs.register(spark)
    c = B.build(slots(spark, sf_dir, "flag=A", "disc=5"))
    c.createOrReplaceTempView("chunkset_pair")
    x = spark.sql("SELECT a.key, CAST(hb_xor(a.kind, a.payload, b.kind, b.payload).card AS BIGINT) AS n_xor FROM (SELECT * FROM chunkset_pair WHERE set_id = 'flag=A') a JOIN (SELECT * FROM chunkset_pair WHERE set_id = 'disc=5') b ON a.key = b.key")
    both = c.groupBy("key").agg(udfs.hb_intersect_card("kind", "payload").alias("n_both")).filter("n_both > 0")
    return x.join(both, "key").select(F.col("key").cast("long").alias("key"), "n_xor", "n_both")


@query(f"WITH ids AS (SELECT DISTINCT 'type='||event_type AS set_id, datediff('second', TIMESTAMP '2024-01-01', ts) AS id FROM events) SELECT set_id AS pair, {SHAPE} FROM ids GROUP BY set_id, id>>16")
def event_seconds(spark, sf_dir):
    return shape(B.build(tables.event_sets(spark, sf_dir, "ev_sec").filter("set_id like 'type=%'")))


@query("WITH x AS (SELECT o_orderkey AS id FROM orders WHERE o_orderstatus IN ('P','F')) SELECT CAST(id>>16 AS BIGINT) AS key, CAST(count(*) AS BIGINT) AS n FROM x GROUP BY id>>16")
def udaf_union(spark, sf_dir):
    c = B.build(tables.order_sets(spark, sf_dir).filter("set_id in ('ostatus=P', 'ostatus=F')"))
    return c.groupBy(F.col("key").cast("long").alias("key")).agg(udfs.hb_union_card("kind", "payload").alias("n"))


@query(f"WITH {ORDER_IDS} SELECT set_id AS pair, {SHAPE} FROM ids GROUP BY set_id, id>>16")
def index_roundtrip(spark, sf_dir):
    import uuid

    path = f"{shared_dir(spark)}/index-{uuid.uuid4().hex}"
    tables.write_index(B.build(tables.order_sets(spark, sf_dir)), path)
    return shape(tables.read_index(spark, path))


@query(f"WITH {EVENT_IDS}, d AS (SELECT * FROM ids WHERE set_id LIKE 'day=%'), hc AS (SELECT set_id, id>>16 AS key, count(*) AS c FROM d GROUP BY 1,2) SELECT set_id, CAST(sum(c) AS BIGINT) AS card FROM hc GROUP BY 1")
def run_kind_card(spark, sf_dir):
    c = B.build(workloads.real_sets(spark, sf_dir, 3).filter("set_id like 'day=%'"))
    return access.cardinality(B.with_kinds(c, (C.ARRAY, C.BITMAP, C.RUNS)))


@query(f"WITH {SLOT_IDS} SELECT set_id, id FROM ids WHERE set_id IN ('flag=A','part=5')")
def further_kinds_roundtrip(spark, sf_dir):
    c = B.build(slots(spark, sf_dir, "flag=A", "part=5"))
    return B.to_ids(B.with_kinds(c, (C.ARRAY, C.BITMAP, C.COMPLEMENT, C.RUNS)))


@query("WITH w AS (SELECT date_trunc('day',ts) AS s, count(DISTINCT user_id) AS u FROM events GROUP BY 1) SELECT CAST(s AS VARCHAR) AS start, CAST(u AS BIGINT) AS users FROM w WHERE s + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 DAY FROM events)")
def stream_tumbling(spark, sf_dir):
    out = users.run_to_end(users.window_halves(users.stream(spark, sf_dir), "1 day"))
    return users.window_users(out).select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "users")


@query("WITH w AS (SELECT date_trunc('day',ts) - k*INTERVAL 1 DAY AS s, count(DISTINCT user_id) AS u FROM events, range(2) t(k) GROUP BY 1) SELECT CAST(s AS VARCHAR) AS start, CAST(u AS BIGINT) AS users FROM w WHERE s + INTERVAL 2 DAY <= (SELECT max(ts) - INTERVAL 1 DAY FROM events)")
def stream_sliding(spark, sf_dir):
    out = users.run_to_end(users.window_halves(users.stream(spark, sf_dir), "2 days", "1 day"))
    return users.window_users(out).select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "users")


@query("WITH a AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS brk FROM events), b AS (SELECT *, sum(brk) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM a), c AS (SELECT user_id, s, min(ts) AS st, max(ts) AS en, count(*) AS n FROM b GROUP BY 1,2) SELECT user_id, CAST(epoch_us(st) AS BIGINT) AS start_us, CAST(n AS BIGINT) AS events FROM c WHERE en + INTERVAL 6 HOUR <= (SELECT max(ts) - INTERVAL 1 DAY FROM events)")
def stream_session(spark, sf_dir):
    out = users.run_to_end(users.sessions(users.stream(spark, sf_dir)))
    return out.select("user_id", F.unix_micros("start").alias("start_us"), "events")


@query("WITH r AS (SELECT *, CAST(ts AS DATE) AS d, (CAST(ts AS DATE) <= DATE '2024-01-20' AND event_id%10<>0) AS early FROM events), k AS (SELECT * FROM r WHERE early OR d + INTERVAL 1 DAY > (SELECT max(ts) - INTERVAL 1 DAY FROM r WHERE early)) SELECT CAST(d AS VARCHAR) AS day, CAST(count(*) AS BIGINT) AS rows_kept FROM k WHERE d + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 DAY FROM events) GROUP BY 1")
def stream_late(spark, sf_dir):
    """Rows that come in a later batch behind the watermark are dropped, the others counted."""
    import uuid

    e = tables.read_table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    early = (F.to_date("ts") <= F.lit("2024-01-20").cast("date")) & (F.col("event_id") % 10 != 0)
    base = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    # what is late is judged by the watermark before the last one, so a batch stands between
    between = ~early & (F.to_date("ts") > F.lit("2024-01-20").cast("date")) & (F.col("event_id") % 2 == 0)
    for i, part in enumerate((e.filter(early), e.filter(between), e.filter(~early & ~between))):
        part.select("ts").coalesce(1).write.parquet(f"{base}/batch={i}")
    rows = spark.readStream.schema("ts timestamp, batch int").option("maxFilesPerTrigger", 1).parquet(base)
    counted = rows.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("rows_kept"))
    return users.run_to_end(counted).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "rows_kept")


@query("SELECT event_type AS set_id, CAST(event_id>>16 AS BIGINT) AS key, CAST(count(*) AS BIGINT) AS card FROM events GROUP BY event_type, event_id>>16")
def stream_containers(spark, sf_dir):
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass", None)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        out = users.run_to_end(users.maintained(users.stream(spark, sf_dir), "event_type", "event_id"), "update")
    finally:
        if before:
            spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)
        else:
            spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    return out.groupBy("set_id", F.col("key").cast("long").alias("key")).agg(F.max_by("card", "batch").cast("long").alias("card"))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """AND of sampled pairs of line-item sets."""
    pairs = saved(workloads.sample_pairs(workloads.set_names(spark, sf_dir, 4), 20), "entry-pairs")
    return shape(pairwise.intersect_pairs(B.build(workloads.of_pairs(workloads.real_sets(spark, sf_dir, 4), pairs)), pairs))


