"""Exact hybrid top-K: the definition, the pre-filter baseline, and the flat scan."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from facetgraph.functions import predicates as P
from facetgraph.functions import vectors as V

#: Bytes of query vectors that one pass carries to the executors; larger sets run in several passes.
QUERY_BYTES = 64 << 20
TOPK = "query_id long, id long, dist double"


def rank_topk(rows: DataFrame, k: int) -> DataFrame:
    """(query_id, rank, id, dist): the k nearest of each query, ties by id; Spark keeps k rows a partition before the shuffle."""
    w = Window.partitionBy("query_id").orderBy("dist", "id")
    return rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "id", "dist")


def merge(parts: list[DataFrame], k: int) -> DataFrame:
    out = parts[0].select("query_id", "id", "dist")
    for p in parts[1:]:
        out = out.unionByName(p.select("query_id", "id", "dist"))
    return rank_topk(out.distinct(), k)


def hybrid_topk(entities: DataFrame, queries: DataFrame, predicates: list[P.Predicate], k: int = 10, metric: str = "l2_squared", exclude_self: bool = True) -> DataFrame:
    """The definition, all in the JVM: rows meet the queries whose predicate they pass (an equi-join on the predicate's number)."""
    rows = entities.withColumn("pred_id", F.explode(P.passes(predicates))).select("id", "vec", "pred_id")
    pairs = rows.join(queries.select("query_id", "qvec", "pred_id"), "pred_id")
    pairs = pairs.where("id <> query_id") if exclude_self else pairs
    return rank_topk(pairs.select("query_id", "id", V.distance(metric, F.col("vec"), F.col("qvec")).alias("dist")), k)


def _batches(queries: DataFrame) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The queries in slices of a checked size."""
    n = queries.count()
    if not n:
        return
    width = len(queries.select("qvec").first()[0])
    parts = max(1, -(-n * width * 8 // QUERY_BYTES))
    for i in range(parts):
        rows = queries.where(F.pmod(F.xxhash64("query_id"), F.lit(parts)) == i).select("query_id", "qvec", "pred_id").collect()
        if rows:
            yield np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], np.float64), np.array([r[2] for r in rows], np.int64)


def _scan(ids: np.ndarray, q: np.ndarray, preds: np.ndarray, k: int, exclude_self: bool):
    """Nearest passing rows of each batch for every query: candidates by a matrix product, distances of those again in full."""
    schema = pa.schema([("query_id", pa.int64()), ("id", pa.int64()), ("dist", pa.float64())])
    qq = np.einsum("ij,ij->i", q, q)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = np.asarray(b.column("vec").flatten(), np.float64).reshape(b.num_rows, -1)
            own = b.column("id").to_numpy()
            lists = b.column("passes")
            sizes, flat = np.asarray(pa.compute.list_value_length(lists)), np.asarray(lists.flatten())
            who = np.repeat(np.arange(b.num_rows), sizes)
            for p in np.unique(preds):
                rows, ask = who[flat == p], np.flatnonzero(preds == p)
                if not len(rows):
                    continue
                y = x[rows]
                d = qq[ask][:, None] - 2 * q[ask] @ y.T + np.einsum("ij,ij->i", y, y)[None, :]
                take = min(len(rows), k + 1)
                bound = np.partition(d, take - 1, axis=1)[:, take - 1] + 1e-9 * (1 + qq[ask])
                at, near = np.nonzero(d <= bound[:, None])  # ties of the last place stay in
                square = (y[near] - q[ask][at]) ** 2
                # summed left to right, as a column expression sums
                dist = np.cumsum(square, axis=1)[:, -1] if square.shape[1] else np.zeros(len(at))
                qid, found = ids[ask][at], own[rows][near]
                keep = (found != qid) if exclude_self else np.ones(len(at), bool)
                yield pa.RecordBatch.from_arrays([pa.array(qid[keep]), pa.array(found[keep]), pa.array(dist[keep])], schema=schema)

    return run


def prefilter(entities: DataFrame, queries: DataFrame, predicates: list[P.Predicate], k: int = 10, exclude_self: bool = True) -> DataFrame:
    """Pre-filter: rows that pass no predicate are dropped by the filter, the rest compared by blocks in Arrow batches; recall is 1."""
    if k <= 0 or not predicates:
        return rank_topk(queries.where("false").select("query_id", F.col("query_id").alias("id"), F.lit(0.0).alias("dist")), 0)
    any_of = predicates[0]
    for p in predicates[1:]:
        any_of = any_of | p
    rows = P.apply(entities, any_of).select("id", "vec", P.passes(predicates).alias("passes"))
    parts = [rows.mapInArrow(_scan(ids, q, preds, k, exclude_self), TOPK) for ids, q, preds in _batches(queries)]
    return merge(parts, k) if parts else prefilter(entities, queries, predicates, 0)
