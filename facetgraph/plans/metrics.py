"""Accuracy and cost measures."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from facetgraph.functions import predicates as P
from facetgraph.operators import blocks, exact
from facetgraph.operators.index import edges
from facetgraph.sources.tables import cut

#: Bytes of distances that a part of the queries keeps.
KEPT_BYTES = 24 << 20


def recall(truth: DataFrame, got: DataFrame, k: int) -> DataFrame:
    """query_id, recall (of k) and recall_adj (of the true neighbours there are)."""
    both = truth.select("query_id", "id").join(got.select("query_id", "id", F.lit(1).alias("hit")), ["query_id", "id"], "left")
    each = both.groupBy("query_id").agg(F.count("*").alias("n"), F.count("hit").alias("hits"))
    return each.select("query_id", (F.col("hits") / k).alias("recall"), (F.col("hits") / F.col("n")).alias("recall_adj"))


def mean_recall(truth: DataFrame, got: DataFrame, k: int) -> float:
    return recall(truth, got, k).agg(F.avg("recall_adj")).first()[0] or 0.0


def read_offs(curve: DataFrame, recall_for_distances: float = 0.8, recall_for_qps: float = 0.9, baseline: str = "oracle", pace: str = "dense") -> DataFrame:
    """(measure, method, value, over_baseline) read from a curve of several methods: distances at one recall, queries a second at another, recall at
    the pace that ``pace`` has there, and whether a point is on its method's frontier, as a count. ``over_baseline``: value over the baseline's, less 1."""
    speed = qps_at_recall(curve, recall_for_qps)
    at = speed.where(F.col("method") == pace).first()
    parts = [distances_at_recall(curve, recall_for_distances).select(F.lit(f"distances at recall {recall_for_distances}").alias("measure"), "method", F.col("n_dist").alias("value"))]
    parts.append(speed.select(F.lit(f"queries a second at recall {recall_for_qps}"), "method", "qps"))
    if at is not None:
        parts.append(recall_at_qps(curve, at["qps"]).select(F.lit(f"recall at the pace of {pace}"), "method", "recall"))
    parts.append(pareto(curve).groupBy("method").agg(F.count("*").cast("double").alias("value")).select(F.lit("points on the frontier"), "method", "value"))
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    base = out.where(F.col("method") == baseline).select("measure", F.col("value").alias("base"))
    return out.join(base, "measure", "left").select("measure", "method", "value", (F.col("value") / F.col("base") - 1).alias("over_baseline"))


def recall_by_distance(truth: DataFrame, got: DataFrame, k: int) -> DataFrame:
    """Recall that counts a result as right when it is no farther than the k-th true neighbour."""
    last = truth.groupBy("query_id").agg(F.max("dist").alias("bound"), F.count("*").alias("n"))
    near = got.join(last, "query_id").where("dist <= bound + 1e-12").groupBy("query_id").agg(F.count("*").alias("hits"))
    return last.join(near, "query_id", "left").select("query_id", (F.least(F.coalesce("hits", F.lit(0)), "n") / F.col("n")).alias("recall"))


def qps(run: Callable[[], DataFrame], n_queries: int, trials: int = 3) -> float:
    """Mean queries a second of ``trials`` runs into a sink that keeps nothing."""
    spent = []
    for _ in range(trials):
        t = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        spent.append(time.perf_counter() - t)
    return n_queries * trials / sum(spent)


def tti(build: Callable[[], DataFrame], path: str) -> float:
    """Seconds to build and write an index."""
    t = time.perf_counter()
    build().write.mode("overwrite").parquet(path)
    return time.perf_counter() - t


def curve_of(found: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """efs, recall, n_dist, n_pred_eval, pass_share, fallback_share, qps of raw search results at one or more beam widths.

    Recall is of the true neighbours there are. Queries a second are of one thread, a query's shards one after another.
    """
    by = Window.partitionBy("efs", "query_id").orderBy("dist", "id")
    got = found.where("id is not null").withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k)
    hits = got.join(truth.select("query_id", "id"), ["query_id", "id"]).groupBy("efs", "query_id").agg(F.count("*").alias("hits"))
    true = truth.groupBy("query_id").agg(F.count("*").alias("n"))
    counters = ["n_dist", "n_visited", "n_pred_eval", "n_passed", "seconds"]
    shard = found.groupBy("efs", "query_id", "shard").agg(*[F.first(c).alias(c) for c in counters], F.first("route").alias("route"))
    each = shard.groupBy("efs", "query_id").agg(*[F.sum(c).alias(c) for c in counters], F.max(F.col("route").contains("fallback").cast("int")).alias("fell"))
    joined = each.join(true, "query_id", "left").join(hits, ["efs", "query_id"], "left")
    return joined.groupBy("efs").agg(
        F.avg(F.when(F.col("n") > 0, F.coalesce("hits", F.lit(0)) / F.col("n"))).alias("recall"),
        F.avg("n_dist").alias("n_dist"),
        F.avg("n_pred_eval").alias("n_pred_eval"),
        (F.sum("n_passed") / F.greatest(F.sum("n_visited"), F.lit(1))).alias("pass_share"),
        F.avg("fell").alias("fallback_share"),
        (F.lit(1.0) / F.avg("seconds")).alias("qps"),
    )


def pareto(curve: DataFrame) -> DataFrame:
    """Points (method, recall, qps) of a method that no other of it beats on both."""
    w = Window.partitionBy("method").orderBy(F.col("recall").desc(), F.col("qps").desc()).rowsBetween(Window.unboundedPreceding, -1)
    return curve.withColumn("best", F.max("qps").over(w)).where("best is null or qps > best").drop("best")


def at_target(curve: DataFrame, x: str, y: str, target: float) -> DataFrame:
    """y where x reaches ``target``, on the line between the last point below and the first not below; a method without either gives none."""
    w = Window.partitionBy("method").orderBy(x, y)
    pairs = curve.withColumn("x0", F.lag(x).over(w)).withColumn("y0", F.lag(y).over(w))
    hit = pairs.where((F.col(x) >= target) & (F.col("x0").isNull() | (F.col("x0") < target)))
    line = F.when(F.col("x0").isNull(), F.col(y)).otherwise(F.col("y0") + (F.col(y) - F.col("y0")) * (F.lit(target) - F.col("x0")) / (F.col(x) - F.col("x0")))
    return hit.withColumn("first", F.row_number().over(w)).where("first = 1").select("method", line.alias(y))


def qps_at_recall(curve: DataFrame, target: float = 0.9) -> DataFrame:
    return at_target(curve, "recall", "qps", target)


def recall_at_qps(curve: DataFrame, target: float = 20_000.0) -> DataFrame:
    return at_target(curve, "qps", "recall", target)


def distances_at_recall(curve: DataFrame, target: float = 0.8) -> DataFrame:
    return at_target(curve, "recall", "n_dist", target)


def selectivity(entities: DataFrame, predicates: list[P.Predicate]) -> DataFrame:
    """pred_id, passing, selectivity."""
    n = F.count("*")
    row = entities.agg(n.alias("n"), *[F.count_if(P.to_column(p)).alias(f"p{i}") for i, p in enumerate(predicates)])
    parts = F.array(*[F.struct(F.lit(i).alias("pred_id"), F.col(f"p{i}").alias("passing"), (F.col(f"p{i}") / F.col("n")).alias("selectivity")) for i in range(len(predicates))])
    return row.select(F.inline(parts))


def selectivity_profile(entities: DataFrame, predicates: list[P.Predicate], points=(0.01, 0.25, 0.5, 0.75, 0.99)) -> DataFrame:
    s = selectivity(entities, predicates)
    return s.agg(*[F.expr(f"percentile(selectivity, {p})").alias(f"p{int(p * 100):02d}") for p in points], F.avg("selectivity").alias("mean"))


def predicate_cardinality(entities: DataFrame, column: str) -> DataFrame:
    return entities.agg(F.count_distinct(column).alias("cardinality"), F.approx_count_distinct(column).alias("approximate"))


#: Weights below it are left out; as many as there are rows add up to less than a double can tell beside 1.
LEAST_WEIGHT = 1e-25


def subset_weights(n: int, k: int, t: int = 1, step: int = 1 << 16) -> np.ndarray:
    """The chance that the i-th of n sorted rows is among the nearest t of a random subset of k, for i from 1 to the last that is not below LEAST_WEIGHT."""
    log_choose = lambda x, y: np.where((y >= 0) & (y <= x), lgamma(np.maximum(x, 0) + 1) - lgamma(np.maximum(y, 0) + 1) - lgamma(np.maximum(x - y, 0) + 1), -np.inf)
    out, before = [], 0.0
    for first in range(1, n + 1, step):
        i = np.arange(first, min(n, first + step - 1) + 1, dtype=np.float64)
        if t == 1:
            # running products: no subset row before
            with np.errstate(divide="ignore", invalid="ignore"):
                logs = np.where(n - i - k + 1 > 0, np.log(np.maximum(n - i - k + 1, 0) / (n - i)), -np.inf)
            sums = before + np.concatenate([np.zeros(1), np.cumsum(logs)])
            w, before = k / n * np.exp(sums[:-1]), sums[-1]
        else:
            w = sum(np.exp(log_choose(i - 1, np.float64(j - 1)) + log_choose(n - i, np.float64(k - j)) - log_choose(np.float64(n), np.float64(k))) for j in range(1, min(t, k) + 1))
        last = np.flatnonzero(w >= LEAST_WEIGHT)
        # weights fall once i is beyond t subset rows' mean place
        if len(last) < len(w) and first + len(last) > t * (n + 1) / (k + 1):
            out.append(w[: last[-1] + 1] if len(last) else w[:0])
            break
        out.append(w)
    return np.concatenate(out)


def lgamma(x) -> np.ndarray:
    return np.vectorize(math.lgamma, otypes=[np.float64])(x)


def query_correlation(entities: DataFrame, queries: DataFrame, predicates: list[P.Predicate], rank: bool = False, k_targets: int = 1) -> DataFrame:
    """query_id, passing, expected, nearest, correlation.

    ``expected`` is the mean distance of a query to the nearest of a random subset as large as the passing set, in closed
    form: with the distances sorted, the chance that the i-th is the subset's nearest falls by the share of subsets
    that avoid the ones before. ``rank``: nearest-neighbour ranks in place of distances. ``k_targets``: the nearest several, summed.
    Every row is compared with every query, by blocks.
    """
    rows = cut(entities.select("id", "vec", P.passes(predicates).alias("tags")))
    asked = cut(queries.select("query_id", "qvec", "pred_id").join(rows.select(F.col("id").alias("query_id"), F.col("tags").alias("own")), "query_id", "left"))
    total = rows.count()
    passing = list(rows.agg(*[F.count_if(F.array_contains("tags", i)) for i in range(len(predicates))]).first())
    # a query that is itself an entity is not compared with itself: its rows, and what of them passes, are one less
    inside, passes = F.col("own").isNotNull().cast("int"), F.coalesce(F.array_contains("own", F.col("pred_id")), F.lit(False)).cast("int")
    sizes = {(p, i, o): (total - i, passing[p] - o) for p in range(len(predicates)) for i, o in ((0, 0), (1, 0), (1, 1))}
    kind = F.col("pred_id") * 3 + inside + passes
    number = {3 * p + i + o: nk for (p, i, o), nk in sizes.items() if nk[1] > 0}
    asked = asked.withColumn("kind", kind).where(F.col("kind").isin(list(number)))
    known = F.create_map(*[F.lit(x) for c, (_, k) in number.items() for x in (c, k)]) if number else F.lit(None)
    if not number:
        return asked.select("query_id", F.lit(0).cast("long").alias("passing"), *[F.lit(None).cast("double").alias(c) for c in ("expected", "nearest", "correlation")])
    left = asked.select(F.col("query_id").alias("id"), F.col("qvec").alias("vec"), F.array("kind").alias("tags"))
    if rank:
        # ranks are known without distances: the least of k of 1 to n is (n + 1) / (k + 1) in the mean
        first = exact.prefilter(entities, queries, predicates, 1).select(F.col("query_id"), F.array(F.sqrt("dist"), F.col("id").cast("double")).alias("place"))
        left = left.join(first, left["id"] == first["query_id"]).select("id", F.concat("vec", "place").alias("vec"), "tags")
        found = blocks.meet(left, rows, blocks.parts_for(asked), blocks.Before, "query_id long, before long")
        mean = F.create_map(*[F.lit(x) for c, (n, k) in number.items() for x in (c, (n + 1) / (k + 1))])
        each = found.join(asked.select("query_id", "kind"), "query_id").select("query_id", F.element_at(known, F.col("kind")).cast("long").alias("passing"), F.element_at(mean, F.col("kind")).alias("expected"), (F.col("before") + 1).cast("double").alias("nearest"))
        return each.withColumn("correlation", F.col("expected") - F.col("nearest"))
    weights = {c: subset_weights(n, k, k_targets) for c, (n, k) in number.items()}
    width = max(map(len, weights.values()))
    # right rows carry the predicates that they pass under the number of each kind of query
    right = rows.select("id", "vec", F.flatten(F.transform("tags", lambda p: F.array(p * 3, p * 3 + 1, p * 3 + 2))).alias("tags"))
    per = max(64, min(blocks.PART_ROWS, KEPT_BYTES // (8 * width)))
    found = blocks.meet(left, right, blocks.parts_for(asked, per), lambda own: blocks.Subsets(own, weights, k_targets), "query_id long, expected double, nearest double")
    each = found.join(asked.select("query_id", "kind"), "query_id").select("query_id", F.element_at(known, F.col("kind")).cast("long").alias("passing"), "expected", "nearest")
    return each.withColumn("correlation", F.col("expected") - F.col("nearest"))


def predicate_clustering(entities: DataFrame, p: P.Predicate) -> DataFrame:
    """Mean nearest-neighbour distance within the passing set, and to any other entity from it; a ratio near that of random subsets means no clustering."""
    rows = cut(entities.select("id", "vec", F.when(P.to_column(p), F.array(F.lit(1))).otherwise(F.array().cast("array<int>")).alias("tags")))
    some = rows.where(F.size("tags") > 0)
    each = blocks.meet(some, rows, blocks.parts_for(some), blocks.Closest, "id long, inside double, any double")
    return each.agg(F.avg("inside").alias("within"), F.avg("any").alias("overall"), F.count("*").alias("n"))


def purity(index: DataFrame, entities: DataFrame, predicates: list[P.Predicate], level: int = 0) -> DataFrame:
    """pred_id, P(neighbour passes | node passes)."""
    ok = entities.select("id", F.explode(P.passes(predicates)).alias("pred_id"))
    e = edges(index).where(F.col("level") == level).select("src", "dst")
    src = e.join(ok.withColumnRenamed("id", "src"), "src")
    both = src.join(ok.select(F.col("id").alias("dst"), "pred_id", F.lit(1).alias("hit")), ["dst", "pred_id"], "left")
    return both.groupBy("pred_id").agg((F.count("hit") / F.count("*")).alias("purity"))


def pred_evals(stats: DataFrame, dimension: int) -> DataFrame:
    """Predicate tests beside distances, and their share of the work when a distance costs ``dimension`` tests."""
    return stats.agg(F.avg("n_pred_eval").alias("pred_evals"), F.avg("n_dist").alias("distances"), (F.sum("n_pred_eval") / (F.sum("n_pred_eval") + dimension * F.sum("n_dist"))).alias("share"))


def pass_share(stats: DataFrame) -> DataFrame:
    return stats.agg((F.sum("n_passed") / F.greatest(F.sum("n_visited"), F.lit(1))).alias("pass_share"))
