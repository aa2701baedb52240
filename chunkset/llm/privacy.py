"""Sanitising personal data: patterns for direct identifiers, information theory for terms that give them away.

The direct kinds (email, ip, card, phone) are the protected entities. How much a term tells of an entity is the
pointwise mutual information of the two over all documents, as a share of the entity's information content: 1 if the
term never stands without the entity. A term above a first share is generalised to its shape, above a second removed,
wherever it stands. What stands right before and after an entity is its context. Contexts that share either side come from one
passage: an entity's documents count as the fewer of their different left and right sides, so that copies of a passage, edited ones
too, are no evidence. A pair needs CONTEXTS contexts, and so many bits beyond chance that MARGIN_BITS remain after all pairs of the
corpus had their chance: some 0.001 pairs are expected to pass by accident, in a corpus of any size.

DataFrame functions only. Null text: the empty text, no spans. Ties in start: the kind listed first. Repeated rows get the same
spans. Null ids stay null. Extra columns pass through sanitise() unless they carry a name that it adds.
Empty tables give empty results. Positions are code points, ends exclusive. Time is close to linear in a text's length and matches:
sums along an array are made in blocks within blocks, and pieces of a text are cut from chunks of it.
"""

from __future__ import annotations

from functools import reduce
from math import log2

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from chunkset.llm.common import read, saved

KINDS = ("email", "ip", "card", "phone")
#: Fixed by the contract, but for two changes that keep the matches: repetition is possessive where nothing can be given back,
#: and a match starts at the front of its first run or at the end of the last match, as later starts in a run fail alike.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
BYTE = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
CONTEXT_CHARS, CONTEXTS, MARGIN_BITS = 24, 3, 10.0
GENERALISE, REMOVE = 0.8, 0.95
BROADCAST_BYTES = 8 << 20
BLOCK, CHUNK_CHARS = 64, 1024


def let(value: Column, use) -> Column:
    """use(value), where value is computed once however often it is used."""
    return F.element_at(F.transform(F.array(value), use), 1)


def larger(a: Column, b: Column) -> Column:
    return F.greatest(a, b)


def before(values: Column, op, depth: int = 2) -> Column:
    """For each element of an array what op (a sum or a maximum of numbers from 0 on) makes of all earlier ones. Blocks within blocks: no
    array longer than a block grows element by element, but for the outermost."""
    zero = F.lit(0)

    def along(block: Column, start: Column) -> Column:
        step = lambda acc, x: F.struct(op(acc["at"], x).alias("at"), F.concat(acc["out"], F.array(acc["at"])).alias("out"))
        return F.aggregate(block, F.struct(start.alias("at"), F.array().cast("array<int>").alias("out")), step, lambda acc: acc["out"])

    if not depth:
        return along(values, zero)

    def in_blocks(v: Column) -> Column:
        starts = F.when(F.size(v) > 0, F.sequence(zero, F.size(v) - 1, F.lit(BLOCK))).otherwise(F.array().cast("array<int>"))
        blocks = F.transform(starts, lambda i: F.slice(v, i + 1, F.lit(BLOCK)))
        return let(blocks, lambda bs: F.flatten(F.zip_with(bs, before(F.transform(bs, lambda b: F.aggregate(b, zero, op)), op, depth - 1), along)))

    return let(values, in_blocks)


def chunks(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(rf"(?s).{{1,{CHUNK_CHARS}}}"), F.lit(0))


def piece(parts: Column, start: Column, end: Column) -> Column:
    """The text from start to end, of a text that is given as its chunks."""
    first = F.floor(start / CHUNK_CHARS).cast("int")
    last = F.floor(F.greatest(start, end - 1) / CHUNK_CHARS).cast("int")
    held = F.array_join(F.slice(parts, first + 1, last - first + 1), "")
    return F.substr(held, start - first * CHUNK_CHARS + 1, F.greatest(F.lit(0), end - start))


def holds(kind: str, text: Column) -> Column:
    """A cheap test that must hold where the kind matches."""
    sign = {"email": "@", "phone": "+"}.get(kind)
    return F.contains(text, F.lit(sign)) if sign else text.rlike(r"[0-9]\.[0-9]+\.[0-9]+\.[0-9]" if kind == "ip" else r"[0-9](?:[\x20-]?[0-9]){13}")


def digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def luhn(number: Column) -> Column:
    doubled = lambda d: F.when(d > 4, d * 2 - 9).otherwise(d * 2)
    n = F.length(number)
    digit = lambda i: F.substr(number, n - i, F.lit(1)).cast("int")  # noqa: E731  i from the right
    total = F.aggregate(F.sequence(F.lit(0), n - 1), F.lit(0), lambda acc, i: acc + F.when(i % 2 == 1, doubled(digit(i))).otherwise(digit(i)))
    return F.pmod(total, F.lit(10)) == 0


def passes(kind: str, value: Column) -> Column:
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        return value.rlike(rf"^{BYTE}(?:\.{BYTE}){{3}}$")
    n = F.length(digits(value))
    if kind == "card":
        return F.when((n >= 14) & (n <= 19), luhn(digits(value))).otherwise(F.lit(False))
    return (n >= 10) & (n <= 15)


def placed(text: Column, pattern: str | Column) -> Column:
    """array<struct<start, end, value>> of all matches: between them stand the pieces that a split gives."""
    pattern = F.lit(pattern) if isinstance(pattern, str) else pattern

    def spans(pairs: Column) -> Column:
        at = before(F.transform(pairs, lambda x: x["gap"] + F.length(x["value"])), lambda a, b: a + b)
        return F.zip_with(pairs, at, lambda x, a: F.struct((a + x["gap"]).alias("start"), (a + x["gap"] + F.length(x["value"])).alias("end"), x["value"].alias("value")))

    gaps = lambda found: F.slice(F.split(text, pattern, -1), F.lit(1), F.size(found))
    pairs = let(F.regexp_extract_all(text, pattern, F.lit(0)), lambda found: F.zip_with(gaps(found), found, lambda g, v: F.struct(F.length(g).alias("gap"), v.alias("value"))))
    return let(pairs, spans)


SPAN = "struct<start:int,ord:int,kind:string,end:int,value:string>"


def spans_of(kind: str, text: Column) -> Column:
    good = F.filter(placed(text, PATTERNS[kind]), lambda s: passes(kind, s["value"]))
    return F.transform(good, lambda s: F.struct(s["start"].alias("start"), F.lit(KINDS.index(kind)).alias("ord"), F.lit(kind).alias("kind"), s["end"].alias("end"), s["value"].alias("value")))


def count_of(kind: str) -> Column:
    return F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long")


def base_spans(text: Column) -> Column:
    """The direct identifiers, by start and then kind."""
    none = F.array().cast(f"array<{SPAN}>")
    each = []
    for kind in KINDS:
        each.append(F.when(holds(kind, text), spans_of(kind, text)).otherwise(none))
    return F.sort_array(F.concat(*each))


def digest(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """docs with text free of nulls, and keys k1, k2 that rows share only if id and text are the same."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.withColumn(text_col, text).withColumns({"k1": F.coalesce(F.col(id_col).cast("long"), F.lit(-1)), "k2": F.xxhash64(F.col(text_col), F.length(text_col))})


def without_matches(text: Column) -> Column:
    def without(kind: str, text: Column) -> Column:
        return let(text, lambda t: F.when(holds(kind, t), F.regexp_replace(t, PATTERNS[kind], " ")).otherwise(t))

    return reduce(lambda t, kind: without(kind, t), KINDS, text)


def entities_of(text: Column, spans: Column) -> Column:
    """array<struct<entity, left, right>>: each entity once, with hashes of what stands close before and after one of its places. A side that
    the text's end cuts short says no more than the other."""

    def found(parts: Column) -> Column:
        def sides(s: Column) -> Column:
            left, right = piece(parts, F.greatest(F.lit(0), s["start"] - CONTEXT_CHARS), s["start"]), piece(parts, s["end"], s["end"] + CONTEXT_CHARS)
            whole = lambda side, other: F.xxhash64(F.when((F.length(side) < CONTEXT_CHARS) & (F.length(other) >= CONTEXT_CHARS), other).otherwise(side))
            name = F.concat_ws(":", s["kind"], F.lower(F.when(s["kind"] == "email", s["value"]).otherwise(digits(s["value"]))))
            return F.struct(name.alias("entity"), whole(left, right).alias("left"), whole(right, left).alias("right"))

        every = F.sort_array(F.transform(spans, sides))
        return let(every, lambda es: F.filter(es, lambda e, i: (i == 0) | (F.get(es, i - 1)["entity"] != e["entity"])))

    return let(chunks(text), found)


def found_in(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(k1, k2, id, spans, entities, terms): terms only where there are entities, without what the patterns match."""
    text = F.col(text_col)
    spans = keyed(docs, id_col, text_col).select("k1", "k2", F.col(id_col).alias("id"), text_col, base_spans(text).alias("spans"))
    some = F.size("spans") > 0
    return spans.select("k1", "k2", "id", "spans", F.when(some, entities_of(text, F.col("spans"))).alias("entities"), F.when(some, terms_of(without_matches(text))).alias("terms"))


def terms_of(text: Column) -> Column:
    return F.array_distinct(F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != ""))


def either_way(small: DataFrame) -> DataFrame:
    """Marks a table for broadcast if the files that it is read from are small; else joins shuffle."""
    size = int(small._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    return F.broadcast(small) if size <= BROADCAST_BYTES else small


def telling_terms(docs: DataFrame, found: DataFrame, id_col: str, text_col: str) -> DataFrame | None:
    """(term, share) of the terms that tell of an entity; None if no entity has contexts enough.

    Documents of an entity count by context: n_e and n_et are contexts, and of all documents those of the entity are replaced by its
    contexts. d_e, d_et and d_t are plain numbers of documents.
    """
    hosts = found.filter("entities is not null").select(F.explode("entities").alias("e"), "terms").select("e.*", "terms")
    contexts = F.least(F.countDistinct("left"), F.countDistinct("right"))
    frequent = hosts.groupBy("entity").agg(contexts.alias("n_e"), F.count(F.lit(1)).alias("d_e"))
    frequent = saved(frequent.filter(F.col("n_e") >= CONTEXTS), "entities")
    if frequent.isEmpty():
        return None
    n = found.count()
    pairs = hosts.join(either_way(frequent), "entity").select("entity", "left", "right", "n_e", "d_e", F.explode("terms").alias("term"))
    pairs = pairs.groupBy("entity", "n_e", "d_e", "term").agg(contexts.alias("n_et"), F.count(F.lit(1)).alias("d_et"))
    pairs = saved(pairs.filter(F.col("n_et") >= CONTEXTS), "entity-terms")
    bits = F.lit(log2(max(pairs.count(), 1)) + MARGIN_BITS)
    others = F.lit(n) - F.col("d_e")
    content = F.log2((others + F.col("n_e")) / F.col("n_e"))

    def share(d_t: Column) -> Column:
        n_t = F.col("n_et") + d_t - F.col("d_et")
        pmi = F.log2(F.col("n_et") * (others + F.col("n_e")) / (F.col("n_e") * n_t))
        return F.when((content > 0) & (F.col("n_et") * pmi >= bits), pmi / content).otherwise(F.lit(0.0))

    # frequencies are counted term by term before they meet a pair; documents with entities bound them from below, and so the shares from above
    among = found.filter("terms is not null").select(F.explode("terms").alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("d_t"))
    bounded = pairs.filter(F.col("n_et") * content >= bits).join(among, "term").filter(share(F.col("d_t")) >= GENERALISE).drop("d_t")
    bounded = saved(bounded, "terms-bounded")
    if bounded.isEmpty():
        return None
    everywhere = docs.select(F.explode(terms_of(without_matches(F.coalesce(F.col(text_col), F.lit(""))))).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("d_t"))
    exact = bounded.join(everywhere, "term").withColumn("share", share(F.col("d_t"))).filter(F.col("share") >= GENERALISE)
    return saved(exact.groupBy("term").agg(F.max("share").alias("share")), "telling")


def term_spans(docs: DataFrame, found: DataFrame, telling: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(k1, k2, term_spans): where the telling terms stand, outside the direct identifiers. Each document is searched for its own
    terms, which are letters and digits only, so that they make up a pattern as they are."""
    hits = keyed(docs, id_col, text_col).select("k1", "k2", F.explode(terms_of(without_matches(F.col(text_col)))).alias("term")).join(either_way(telling), "term")
    per_doc = hits.groupBy("k1", "k2").agg(F.map_from_entries(F.sort_array(F.collect_set(F.struct("term", "share")))).alias("telling"))
    base = found.filter(F.size("spans") > 0).select("k1", "k2", "spans").dropDuplicates(["k1", "k2"])
    per_doc = saved(per_doc.join(base, ["k1", "k2"], "left"), "telling-documents")
    rows = keyed(docs, id_col, text_col).select("k1", "k2", text_col).join(either_way(per_doc), ["k1", "k2"]).dropDuplicates(["k1", "k2"])
    pattern = F.concat(F.lit(r"(?iu)(?<![\p{L}\p{N}])(?:"), F.array_join(F.map_keys("telling"), "|"), F.lit(r")(?![\p{L}\p{N}])"))
    share = lambda w: F.element_at("telling", F.lower(w["value"]))
    words = F.filter(placed(F.col(text_col), pattern), lambda w: share(w).isNotNull())
    base_or_none = F.coalesce(F.col("spans"), F.array().cast(f"array<{SPAN}>"))
    spans = F.transform(outside(words, base_or_none), lambda w: F.struct(w["start"].alias("start"), F.lit(len(KINDS)).alias("ord"), F.when(share(w) >= REMOVE, "removed").otherwise("term").alias("kind"), w["end"].alias("end"), w["value"].alias("value")))
    return saved(rows.select("k1", "k2", spans.alias("term_spans")), "term-spans")


def outside(words: Column, spans: Column) -> Column:
    """The words that overlap none of the spans: no span that starts before a word's end reaches past its start."""
    stop = lambda s: F.struct(s["start"].alias("key"), F.lit(0).alias("word"), s["start"].alias("start"), s["end"].alias("end"), F.lit("").alias("value"))
    each = lambda w: F.struct((w["end"] - 1).alias("key"), F.lit(1).alias("word"), w["start"].alias("start"), w["end"].alias("end"), w["value"].alias("value"))
    both = F.sort_array(F.concat(F.transform(spans, stop), F.transform(words, each)))

    def free(rows: Column) -> Column:
        reached = before(F.transform(rows, lambda r: F.when(r["word"] == 0, r["end"]).otherwise(0)), larger)
        marked = F.zip_with(rows, reached, lambda r, m: F.struct(r["start"].alias("start"), r["end"].alias("end"), r["value"].alias("value"), ((r["word"] == 1) & (m <= r["start"])).alias("free")))
        return F.filter(marked, lambda r: r["free"])

    return let(both, free)


def all_term_spans(docs: DataFrame, found: DataFrame, id_col: str, text_col: str) -> DataFrame | None:
    telling = telling_terms(docs, found, id_col, text_col)
    return None if telling is None or telling.isEmpty() else term_spans(docs, found, telling, id_col, text_col)


def joined(rows: DataFrame, terms: DataFrame | None, spans: Column) -> DataFrame:
    if terms is None:
        return rows.withColumn("all_spans", spans)
    out = rows.join(either_way(terms), ["k1", "k2"], "left")
    none = F.array().cast(f"array<{SPAN}>")
    return out.withColumn("all_spans", F.sort_array(F.concat(spans, F.coalesce("term_spans", none)))).drop("term_spans")


def generalised(span: Column) -> Column:
    """What stands for a span: its kind; a telling term's shape; nothing for a removed one."""
    shape = F.when(span["value"].rlike(r"^[0-9]+$"), "[NUMBER]").when(span["value"].rlike(r"[0-9]"), "[CODE]").when(span["value"].rlike(r"^\p{Lu}"), "[NAME]").otherwise("[WORD]")
    return F.when(span["kind"] == "removed", "").when(span["kind"] == "term", shape).otherwise(F.concat(F.lit("["), F.upper(span["kind"]), F.lit("]")))


def masked(text: Column, spans: Column) -> Column:
    """text with each span replaced; overlapping spans become one, with the first one's stand-in."""

    def build(parts: Column, spans: Column) -> Column:
        def with_gaps(reached: Column) -> Column:
            out = F.zip_with(spans, reached, lambda s, r: F.when(s["start"] >= r, F.concat(piece(parts, r, s["start"]), generalised(s))).otherwise(""))
            return F.concat(F.array_join(out, ""), piece(parts, F.array_max(F.transform(spans, lambda s: s["end"])), F.length(text)))

        return let(before(F.transform(spans, lambda s: s["end"]), larger), with_gaps)

    return let(spans, lambda ss: F.when(F.size(ss) == 0, text).otherwise(let(chunks(text), lambda parts: build(parts, ss))))


def detect(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_email, n_ip, n_card, n_phone, base_spans, all_spans) for each row."""
    docs = docs.select(id_col, text_col)
    found = saved(found_in(docs, id_col, text_col), "personal-data")
    out = joined(found.select("k1", "k2", "id", "spans"), all_term_spans(docs, found, id_col, text_col), F.col("spans"))
    return out.select(F.col("id").alias(id_col), *[count_of(k).alias(f"n_{k}") for k in KINDS], F.col("spans").alias("base_spans"), "all_spans")


def sanitise(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with the text sanitised, its other columns unchanged."""
    narrow = docs.select(id_col, text_col)
    found = saved(found_in(narrow, id_col, text_col), "personal-data")
    terms = all_term_spans(narrow, found, id_col, text_col)
    rows = keyed(docs.withColumnsRenamed({c: f"own_{c}" for c in docs.columns if c in ("k1", "k2", "term_spans", "all_spans")}), id_col, text_col)
    out = joined(rows, terms, base_spans(F.col(text_col))).withColumn(text_col, masked(F.col(text_col), F.col("all_spans")))
    return out.drop("k1", "k2", "all_spans").withColumnsRenamed({f"own_{c}": c for c in docs.columns}).select(*[F.col(f"`{c}`") for c in docs.columns])


def op1_privacy(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = detect(read(spark, sf_dir, "documents"))
    return found.select("doc_id", *[f"n_{k}" for k in KINDS], F.sha2(digest(F.col("base_spans")), 256).alias("base_sha256"), digest(F.col("all_spans")).alias("spans"))
