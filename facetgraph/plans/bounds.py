"""Degree, connectivity and cost formulas as Columns over (n, d, s, k, m, gamma, m_beta, delta)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def expected_degree():
    """Passing neighbours of a node without clustering; above m exactly when s is above 1 / gamma."""
    return F.col("gamma") * F.col("m") * F.col("s")


def low_degree():
    """Bound on the chance that some node of the path has a (1 - delta) share of m passing neighbours or fewer."""
    return F.log("n") * F.exp(-F.col("delta") * F.col("delta") * F.col("gamma") * F.col("m") * F.col("s") / 2)


def disconnect():
    return F.log("n") * F.pow(1 - F.col("s"), F.col("m") * F.col("gamma"))


def path_factor():
    """Expected steps on a level, 1 / (1 - e^-m_L) with m_L = 1 / ln m."""
    return 1 / (1 - F.exp(-1 / F.log("m")))


def cost_model(params: DataFrame) -> DataFrame:
    """Adds expected costs of the methods and entries of a node's lists."""
    n, d, s, k, m, g, b = (F.col(c).cast("double") for c in ("n", "d", "s", "k", "m", "gamma", "m_beta"))
    ml = 1 / F.log(m)
    out = {
        "degree": expected_degree(),
        "low_degree_bound": low_degree(),
        "disconnect_bound": disconnect(),
        "path": path_factor(),
        "prefilter": s * n + k,
        "postfilter_near": F.log(n) + k,
        "postfilter_uniform": F.log(n) + k / s,
        "postfilter_worst": n,
        "oracle": F.log(s * n) + k,
        "dense": (d + g) * F.log(s * n) + F.log(1 / s),
        "build_hnsw": n * F.log(n),
        "build_dense": n * g * F.log(n) * F.log(g),
        "list_entries_dense": b + m + ml * m * g,
        "list_entries_hnsw": m + ml * m,
    }
    return params.select(*params.columns, *[F.round(v, 6).alias(c) for c, v in out.items()])


SQL_COST = """SELECT p.*, round(gamma * m * s, 6) AS degree, round(ln(n) * exp(-delta * delta * gamma * m * s / 2), 6) AS low_degree_bound,
 round(ln(n) * pow(1 - s, m * gamma), 6) AS disconnect_bound, round(1 / (1 - exp(-1 / ln(m))), 6) AS path, round(s * n + k, 6) AS prefilter,
 round(ln(n) + k, 6) AS postfilter_near, round(ln(n) + k / s, 6) AS postfilter_uniform, round(n::DOUBLE, 6) AS postfilter_worst, round(ln(s * n) + k, 6) AS oracle,
 round((d + gamma) * ln(s * n) + ln(1 / s), 6) AS dense, round(n * ln(n), 6) AS build_hnsw, round(n * gamma * ln(n) * ln(gamma), 6) AS build_dense,
 round(m_beta + m + m * gamma / ln(m), 6) AS list_entries_dense, round(m + m / ln(m), 6) AS list_entries_hnsw FROM params p"""
