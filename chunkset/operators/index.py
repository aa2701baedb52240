"""Attribute indexes: predicates as set algebra over the sets of a table's values, then the table's rows."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chunkset.operators import manyway, pairwise
from chunkset.operators.build import to_ids


@dataclass(frozen=True)
class Eq:
    attribute: str
    value: object


@dataclass(frozen=True)
class In:
    attribute: str
    values: tuple


@dataclass(frozen=True)
class Between:
    """low <= value <= high, on an attribute whose values are numbers; either end may be None."""

    attribute: str
    low: float | None
    high: float | None


@dataclass(frozen=True)
class And:
    parts: tuple


@dataclass(frozen=True)
class Or:
    parts: tuple


@dataclass(frozen=True)
class Not:
    """Ids of the attribute's sets without those of part: rows whose value is null belong to neither."""

    part: object


def attributes(p) -> set[str]:
    if isinstance(p, (And, Or)):
        return set().union(*map(attributes, p.parts))
    return attributes(p.part) if isinstance(p, Not) else {p.attribute}


def one_set(rows: DataFrame) -> DataFrame:
    """The union of all sets in rows, named p."""
    groups = rows.select("set_id").distinct().withColumn("group_id", F.lit("p"))
    return manyway.union_all(rows, groups)


def leaf(index: DataFrame, p) -> DataFrame:
    value = F.substring_index("set_id", "=", -1)
    named = index.filter(F.substring_index("set_id", "=", 1) == p.attribute)
    if isinstance(p, Eq):
        return index.filter(F.col("set_id") == f"{p.attribute}={p.value}").withColumn("set_id", F.lit("p"))
    if isinstance(p, In):
        return one_set(index.filter(F.col("set_id").isin([f"{p.attribute}={v}" for v in p.values])))
    low = F.lit(True) if p.low is None else value.cast("double") >= p.low
    high = F.lit(True) if p.high is None else value.cast("double") <= p.high
    return one_set(named.filter(low & high))


def known(index: DataFrame, names: set[str]) -> DataFrame:
    """Ids that have a value in all of the attributes."""
    out = None
    for n in sorted(names):
        s = one_set(index.filter(F.substring_index("set_id", "=", 1) == n))
        out = s if out is None else pairwise.same_sets(out, s, "and")
    return out


def solve(index: DataFrame, p) -> DataFrame:
    """Containers of the predicate's ids, as the one set p. A negation under AND becomes a difference; the conjunction starts
    with its positive parts. Negations elsewhere are taken within the rows that have a value."""
    if isinstance(p, Or):
        out = solve(index, p.parts[0])
        for q in p.parts[1:]:
            out = pairwise.same_sets(out, solve(index, q), "or")
        return out
    if isinstance(p, And):
        positive, negative = [q for q in p.parts if not isinstance(q, Not)], [q for q in p.parts if isinstance(q, Not)]
        out = solve(index, positive[0]) if positive else solve(index, negative.pop(0))
        for q in positive[1:]:
            out = pairwise.same_sets(out, solve(index, q), "and")
        for q in negative:
            out = pairwise.same_sets(pairwise.same_sets(out, known(index, attributes(q)), "and"), solve(index, q.part), "andnot")
        return out
    if isinstance(p, Not):
        return pairwise.same_sets(known(index, attributes(p)), solve(index, p.part), "andnot")
    return leaf(index, p)


def ids_where(index: DataFrame, p) -> DataFrame:
    return to_ids(solve(index, p)).select("id")


def rows_where(table: DataFrame, id_col: str, index: DataFrame, p) -> DataFrame:
    """The rows of table that the predicate holds for, found through the index."""
    return pairwise.rows_in(table, id_col, solve(index, p))
