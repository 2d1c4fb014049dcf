"""Distances between array columns, summed left to right in double, and their SQL."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

METRICS = ("l2_squared", "l2", "inner_product", "cosine", "l1")


def _fold(a: Column, b: Column, term) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: term(x.cast("double"), y.cast("double"))), F.lit(0.0), lambda s, v: s + v)


def l2_squared(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: (x - y) * (x - y))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2_squared(a, b))


def inner_product(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: x * y)


def norm(a: Column) -> Column:
    return F.sqrt(inner_product(a, a))


def cosine(a: Column, b: Column) -> Column:
    return inner_product(a, b) / (norm(a) * norm(b))


def l1(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: F.abs(x - y))


def dims(a: Column) -> Column:
    return F.size(a)


def normalize(a: Column) -> Column:
    return F.transform(a, lambda x: x.cast("double") / norm(a))


def quantize_sq8(a: Column, low: Column, high: Column) -> Column:
    """8-bit codes of a vector between per-dimension bounds."""
    return F.transform(F.arrays_zip(a.alias("x"), low.alias("l"), high.alias("h")), lambda z: F.greatest(F.lit(0), F.least(F.lit(255), F.round((z["x"] - z["l"]) / F.greatest(z["h"] - z["l"], F.lit(1e-12)) * 255))).cast("int"))


def distance(metric: str, a: Column, b: Column) -> Column:
    """Smaller is nearer for every metric: inner product and cosine are negated."""
    if metric not in METRICS:
        raise ValueError(f"metric must be one of {METRICS}")
    value = globals()[metric](a, b)
    return -value if metric in ("inner_product", "cosine") else value


def sql_fold(a: str, b: str, term: str) -> str:
    return f"list_reduce(list_prepend(0.0::DOUBLE, list_transform(list_zip({a}, {b}), lambda z: {term})), lambda s, v: s + v)"


def sql_distance(metric: str, a: str, b: str) -> str:
    ip = lambda x, y: sql_fold(x, y, "z[1] * z[2]")
    square = sql_fold(a, b, "(z[1] - z[2]) * (z[1] - z[2])")
    return {
        "l2_squared": square,
        "l2": f"sqrt({square})",
        "inner_product": f"-({ip(a, b)})",
        "cosine": f"-({ip(a, b)} / (sqrt({ip(a, a)}) * sqrt({ip(b, b)})))",
        "l1": sql_fold(a, b, "abs(z[1] - z[2])"),
    }[metric]
