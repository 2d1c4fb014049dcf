"""Selectivity estimates, the choice between graph and pre-filter, and the choice of build parameters."""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetgraph.functions import predicates as P
from facetgraph.operators import index as I
from facetgraph.operators import kernel as K
from facetgraph.operators.exact import merge, prefilter
from facetgraph.plans import metrics


def estimate(entities: DataFrame, predicates: list[P.Predicate], method: str = "exact", fraction: float = 0.01, seed: int = 5) -> DataFrame:
    """pred_id, s_est. method: exact; sample (a share of rows by id hash); histogram (KLL sketch, ranges only); bitmap (per-value counts, equality and any-of)."""
    if method == "exact":
        return metrics.selectivity(entities, predicates).select("pred_id", F.col("selectivity").alias("s_est"))
    if method == "sample":
        drawn = F.conv(F.substring(F.md5(F.concat_ws("-", F.lit(seed), F.col("id").cast("string"))), 1, 8), 16, 10).cast("long")
        kept = entities.where(drawn < int(fraction * (1 << 32)))
        return metrics.selectivity(kept, predicates).select("pred_id", F.coalesce("selectivity", F.lit(0.0)).alias("s_est"))
    if method == "histogram":
        return _histogram(entities, predicates)
    if method == "bitmap":
        return _bitmap(entities, predicates)
    raise ValueError("method must be exact, sample, histogram or bitmap")


def _histogram(entities: DataFrame, predicates: list[P.Predicate]) -> DataFrame:
    if any(p.op != "between" for p in predicates):
        raise P.UnsupportedPredicate("histograms estimate ranges")
    fields = sorted({p.field for p in predicates})
    kinds = dict(entities.dtypes)
    number = lambda f: F.unix_micros(F.col(f).cast("timestamp")).cast("double") if kinds[f].startswith(("timestamp", "date")) else F.col(f).cast("double")
    sketches = entities.agg(*[F.kll_sketch_agg_double(number(f)).alias(f"k_{f}") for f in fields], *[(F.count(f) / F.count("*")).alias(f"n_{f}") for f in fields])

    def rank(p: P.Predicate, end: int):
        # the sketch's default rank counts what is at most the value, so a range's lower end is counted as outside: for values that
        # hardly repeat that is within the sketch's error, and it makes the estimate of a range of one value 0
        value = F.lit(p.value[end])
        value = F.unix_micros(value.cast("timestamp")).cast("double") if kinds[p.field].startswith(("timestamp", "date")) else value.cast("double")
        return F.kll_sketch_get_rank_double(F.col(f"k_{p.field}"), value)

    parts = [F.struct(F.lit(i).alias("pred_id"), (F.greatest(F.lit(0.0), rank(p, 1) - rank(p, 0)) * F.col(f"n_{p.field}")).alias("s_est")) for i, p in enumerate(predicates)]
    return sketches.select(F.inline(F.array(*parts)))


def _bitmap(entities: DataFrame, predicates: list[P.Predicate]) -> DataFrame:
    """Any-of by the union of per-value row bitmaps: rows with several of the values count once."""
    if any(p.op not in ("eq", "any") for p in predicates):
        raise P.UnsupportedPredicate("bitmaps estimate equality and any-of")
    n = entities.count()
    out = None
    for i, p in enumerate(predicates):
        values = [p.value] if p.op == "eq" else list(p.value)
        value = F.explode(p.field) if p.op == "any" else F.col(p.field)
        rows = entities.select(F.col("id"), value.alias("v")).where(F.col("v").isin(values))
        bits = rows.groupBy(F.bitmap_bucket_number("id").alias("b")).agg(F.bitmap_count(F.bitmap_construct_agg(F.bitmap_bit_position("id"))).alias("c"))
        one = bits.agg(F.lit(i).alias("pred_id"), (F.coalesce(F.sum("c"), F.lit(0)) / F.lit(n)).alias("s_est"))
        out = one if out is None else out.union(one)
    return out


def route(queries: DataFrame, estimates: DataFrame, gamma: int) -> DataFrame:
    """Adds s_est and route: graph when s_est is above 1 / gamma, else prefilter."""
    return queries.join(F.broadcast(estimates), "pred_id").withColumn("route", F.when(F.col("s_est") * gamma > 1, "graph").otherwise("prefilter"))


def routed_search(index: DataFrame, entities: DataFrame, queries: DataFrame, predicates: list[P.Predicate], params: K.Params, estimates: DataFrame, k: int = 10, efs: int = 40, exclude_self: bool = True) -> DataFrame:
    """Both branches over their queries, united: (query_id, rank, id, dist, route)."""
    routed = route(queries, estimates, params.gamma)
    graph = I.topk(I.search(index, entities, routed.where("route = 'graph'"), predicates, params, k, efs, exclude_self=exclude_self), k)
    exact = prefilter(entities, routed.where("route = 'prefilter'"), predicates, k, exclude_self)
    return merge([graph, exact], k).join(routed.select("query_id", "route"), "query_id")


def s_min(workload: DataFrame, pct: float) -> float:
    """The selectivity that a share ``pct`` of the workload's queries stays below."""
    return workload.agg(F.expr(f"percentile(s_est, {pct})")).first()[0]


def gamma_from_selectivity(s: float) -> int:
    return max(1, round(1 / s))


def raise_gamma(entities: DataFrame, queries: DataFrame, predicates: list[P.Predicate], truth: DataFrame, m: int, start: int, most: int, efs: int = 40, k: int = 10, gap: float = 0.02) -> list[tuple[int, float]]:
    """Raises gamma stepwise while the hybrid recall lags plain search's at the same m and efc; (gamma, recall) of each step."""
    everything = [P.always()]
    plain = queries.withColumn("pred_id", F.lit(0))
    base = I.build_hnsw(entities, m=m)
    goal = metrics.mean_recall(merge([prefilter(entities, plain, everything, k)], k), I.topk(I.search(base, entities, plain, everything, K.hnsw(m=m), k, efs), k), k)
    steps, gamma = [], start
    while gamma <= most:
        params = K.dense(m=m, gamma=gamma, m_beta=2 * m)
        got = I.topk(I.search(I.build(entities, params), entities, queries, predicates, params, k, efs), k)
        steps.append((gamma, metrics.mean_recall(truth, got, k)))
        if steps[-1][1] >= goal - gap:
            break
        gamma = gamma + max(1, start // 2)
    return steps


def best_at(curve: DataFrame, target: float = 0.9) -> tuple[str, float] | None:
    """The method with the highest pace at a recall, and the pace; None if none comes there."""
    row = metrics.qps_at_recall(curve, target).orderBy(F.col("qps").desc(), "method").first()
    return (row["method"], row["qps"]) if row else None


def united(parts: list[tuple[str, DataFrame]]) -> DataFrame:
    out = None
    for name, c in parts:
        one = c.select(F.lit(name).alias("method"), "efs", "recall", "n_dist", "qps")
        out = one if out is None else out.union(one)
    return out


def grid(entities: DataFrame, queries: DataFrame, truth: DataFrame, ms=(32, 64, 128), efcs=(40, 80, 120, 160, 200), widths=(10, 40, 80, 160), k: int = 10) -> DataFrame:
    """Curves of plain graphs over a grid of m and efc; ``best_at`` names the pair to take."""
    plain, parts = queries.withColumn("pred_id", F.lit(0)), []
    for m, efc in itertools.product(ms, efcs):
        params = K.hnsw(m=m, efc=efc)
        found = I.search(I.build(entities, params), entities, plain, [P.always()], params, k, tuple(widths))
        parts.append((f"m={m} efc={efc}", metrics.curve_of(found, truth, k)))
    return united(parts)


def choose_m_beta(entities: DataFrame, queries: DataFrame, predicates: list[P.Predicate], truth: DataFrame, m: int, gamma: int, budget_bytes: int, widths=(10, 40, 80, 160), k: int = 10) -> DataFrame:
    """Curves of m_beta = m and 2 m, of those whose index stays within the budget; ``best_at`` names the one to take."""
    parts = []
    for m_beta in (m, 2 * m):
        params = K.dense(m=m, gamma=gamma, m_beta=m_beta)
        index = I.build(entities, params)
        if sum(I.index_size(index).first()) <= budget_bytes:
            parts.append((f"m_beta={m_beta}", metrics.curve_of(I.search(index, entities, queries, predicates, params, k, tuple(widths)), truth, k)))
    return united(parts) if parts else entities.sparkSession.createDataFrame([], "method string, efs int, recall double, n_dist double, qps double")
