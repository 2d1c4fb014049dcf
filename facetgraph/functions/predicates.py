"""Predicates over entity attributes: one tree, lowered to a Column, to SQL, and to packed bits.

Nothing about a predicate is known when an index is built. A null attribute fails.
"""

from __future__ import annotations

from dataclasses import dataclass
from datetime import datetime
from typing import Any

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class UnsupportedPredicate(ValueError):
    """A method cannot answer this kind of predicate."""


@dataclass(frozen=True)
class Predicate:
    op: str
    field: str = ""
    value: Any = None
    children: tuple[Predicate, ...] = ()

    def __and__(self, other: Predicate) -> Predicate:
        return Predicate("and", children=(self, other))

    def __or__(self, other: Predicate) -> Predicate:
        return Predicate("or", children=(self, other))

    def __invert__(self) -> Predicate:
        return Predicate("not", children=(self,))


def eq(f: str, v: Any) -> Predicate:
    return Predicate("eq", f, v)


def ne(f: str, v: Any) -> Predicate:
    return Predicate("ne", f, v)


def in_(f: str, vs: list) -> Predicate:
    return Predicate("in", f, tuple(vs))


def between(f: str, low: Any, high: Any) -> Predicate:
    return Predicate("between", f, (low, high))


def lt(f: str, v: Any) -> Predicate:
    return Predicate("lt", f, v)


def gt(f: str, v: Any) -> Predicate:
    return Predicate("gt", f, v)


def like(f: str, v: str) -> Predicate:
    return Predicate("like", f, v)


def regex(f: str, v: str) -> Predicate:
    return Predicate("regex", f, v)


def contains_any(f: str, vs: list) -> Predicate:
    return Predicate("any", f, tuple(vs))


def contains_all(f: str, vs: list) -> Predicate:
    return Predicate("all", f, tuple(vs))


def json_eq(f: str, key: str, v: Any) -> Predicate:
    return Predicate("json_eq", f, (key, v))


def is_null(f: str) -> Predicate:
    return Predicate("is_null", f)


def always() -> Predicate:
    return Predicate("true")


def never() -> Predicate:
    return Predicate("false")


def _raw(p: Predicate) -> Column:
    c, v = (F.col(p.field) if p.field else None), p.value
    match p.op:
        case "true":
            return F.lit(True)
        case "false":
            return F.lit(False)
        case "eq":
            return c == v
        case "ne":
            return c != v
        case "in":
            return c.isin(list(v))
        case "between":
            return c.between(*v)
        case "lt":
            return c < v
        case "gt":
            return c > v
        case "like":
            return c.like(v)
        case "regex":
            return c.rlike(v)
        case "any":
            return F.arrays_overlap(c, F.array(*[F.lit(x) for x in v]))
        case "all":
            out = F.lit(True)
            for x in v:
                out = out & F.array_contains(c, x)
            return out
        case "json_eq":
            return F.get_json_object(c, f"$.{v[0]}") == str(v[1])
        case "is_null":
            return c.isNull()
        case "and":
            return _raw(p.children[0]) & _raw(p.children[1])
        case "or":
            return _raw(p.children[0]) | _raw(p.children[1])
        case "not":
            return ~_raw(p.children[0])
    raise UnsupportedPredicate(p.op)


def to_column(p: Predicate) -> Column:
    """Boolean without nulls, for plans that use it as a value; in a filter the raw form is pushed down as it is."""
    return F.coalesce(_raw(p), F.lit(False))


def to_filter(p: Predicate) -> Column:
    return _raw(p)


def _literal(v: Any) -> str:
    if isinstance(v, str):
        return "'" + v.replace("'", "''") + "'"
    if isinstance(v, datetime):
        return f"TIMESTAMP '{v:%Y-%m-%d %H:%M:%S}'"
    return repr(v)


def _sql(p: Predicate) -> str:
    f, v = p.field, p.value
    match p.op:
        case "true" | "false":
            return p.op.upper()
        case "eq" | "ne" | "lt" | "gt":
            return f"{f} {dict(eq='=', ne='<>', lt='<', gt='>')[p.op]} {_literal(v)}"
        case "in":
            return f"{f} IN ({', '.join(map(_literal, v))})"
        case "between":
            return f"{f} BETWEEN {_literal(v[0])} AND {_literal(v[1])}"
        case "like":
            return f"{f} LIKE {_literal(v)}"
        case "regex":
            return f"regexp_matches({f}, {_literal(v)})"
        case "any":
            return f"list_has_any({f}, [{', '.join(map(_literal, v))}])"
        case "all":
            return f"list_has_all({f}, [{', '.join(map(_literal, v))}])"
        case "json_eq":
            return f"json_extract_string({f}, '$.{v[0]}') = '{v[1]}'"
        case "is_null":
            return f"{f} IS NULL"
        case "and" | "or":
            return f"(({_sql(p.children[0])}) {p.op.upper()} ({_sql(p.children[1])}))"
        case "not":
            return f"NOT ({_sql(p.children[0])})"
    raise UnsupportedPredicate(p.op)


def to_sql(p: Predicate) -> str:
    return f"coalesce({_sql(p)}, FALSE)"


def passes(predicates: list[Predicate]) -> Column:
    """Array of the numbers of the predicates that a row passes."""
    if not predicates:
        return F.array().cast("array<int>")
    return F.array_compact(F.array(*[F.when(to_column(p), F.lit(i)) for i, p in enumerate(predicates)]))


def sql_passes(predicates: list[Predicate]) -> str:
    return "list_filter([" + ", ".join(f"CASE WHEN {to_sql(p)} THEN {i} END" for i, p in enumerate(predicates)) + "], lambda x: x IS NOT NULL)"


def apply(entities: DataFrame, p: Predicate) -> DataFrame:
    return entities.where(to_filter(p))


def to_bitset(passing: np.ndarray, n: int) -> np.ndarray:
    """Packed bits of a shard's passing positions."""
    flags = np.zeros(n, bool)
    flags[passing] = True
    return np.packbits(flags)


def keyword_mask(column: Column, values: list) -> Column:
    """A list attribute over at most 64 values as a bit mask: any-of is then one bitwise test."""
    if len(values) > 63:
        raise UnsupportedPredicate("more than 63 values: use bitmaps by bucket")
    one = lambda x: F.coalesce(F.element_at(F.create_map(*[y for i, v in enumerate(values) for y in (F.lit(v), F.lit(1 << i))]), x).cast("long"), F.lit(0).cast("long"))
    return F.aggregate(F.coalesce(column, F.array()), F.lit(0).cast("long"), lambda s, x: s.bitwiseOR(one(x)))


def contains_bits(mask: Column, values: list, wanted: list) -> Column:
    bits = sum(1 << values.index(v) for v in set(wanted) if v in values)
    return mask.bitwiseAND(F.lit(bits).cast("long")) != 0


def equality_label(p: Predicate) -> tuple[str, Any]:
    """(field, value) of an equality; label graphs can answer no other predicate."""
    if p.op != "eq":
        raise UnsupportedPredicate(f"{p.op}: only equality on one label")
    return p.field, p.value
