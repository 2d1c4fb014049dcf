"""Inverted lists with a filter: flat vectors, 8-bit scalar codes, or product codes; probed lists are pruned by list id."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetgraph.functions import predicates as P
from facetgraph.operators.exact import TOPK, _batches, merge, rank_topk

#: Vectors that the coarse and the product quantisers are fitted on, at most.
FIT_ROWS = 20_000


def kmeans(x: np.ndarray, k: int, rounds: int = 15, seed: int = 3) -> np.ndarray:
    rng = np.random.default_rng(seed)
    k = min(k, len(x))
    centers = x[rng.choice(len(x), k, replace=False)].astype(np.float64)
    for _ in range(rounds):
        own = assign(x, centers)
        sums, n = np.zeros_like(centers), np.bincount(own, minlength=k)
        np.add.at(sums, own, x)
        centers = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], centers)
    return centers


def assign(x: np.ndarray, centers: np.ndarray) -> np.ndarray:
    return np.argmin(np.einsum("ij,ij->i", centers, centers)[None, :] - 2 * x @ centers.T, axis=1)


def nearest_centroid(centers: np.ndarray):
    @F.pandas_udf("int")
    def own(vec: pd.Series) -> pd.Series:
        return pd.Series(assign(np.stack(vec.to_numpy()), centers).astype(np.int32))

    return own(F.col("vec"))


def sample_matrix(vectors: DataFrame) -> np.ndarray:
    return np.array([r[0] for r in vectors.orderBy(F.xxhash64("id"), "id").limit(FIT_ROWS).select("vec").collect()], np.float64)


class Codec:
    """codec: flat, sq8 (one byte a dimension between its bounds) or pq (``m`` subspaces of 2^nbits centroids)."""

    def __init__(self, codec: str, fit: np.ndarray, m: int = 8, nbits: int = 6):
        self.codec = codec
        if codec == "sq8":
            self.low, self.span = fit.min(0), np.maximum(np.ptp(fit, axis=0), 1e-12)
        elif codec == "pq":
            self.parts = np.array_split(np.arange(fit.shape[1]), m)
            self.books = [kmeans(fit[:, p], 1 << nbits) for p in self.parts]
        elif codec != "flat":
            raise ValueError("codec must be flat, sq8 or pq")

    def decode(self, x: np.ndarray) -> np.ndarray:
        """What the codes of ``x`` stand for."""
        if self.codec == "sq8":
            return np.clip(np.round((x - self.low) / self.span * 255), 0, 255) / 255 * self.span + self.low
        if self.codec == "pq":
            out = np.empty_like(x)
            for p, book in zip(self.parts, self.books):
                out[:, p] = book[assign(x[:, p], book)]
            return out
        return x

    def bytes(self, d: int) -> int:
        return {"flat": 4 * d, "sq8": d, "pq": len(getattr(self, "books", ()))}[self.codec]


def build(vectors: DataFrame, nlist: int) -> tuple[DataFrame, np.ndarray]:
    """(id, vec, list); write it partitioned by list, so that probes prune partitions."""
    centers = kmeans(sample_matrix(vectors), nlist)
    return vectors.withColumn("list", nearest_centroid(centers)), centers


def search(lists: DataFrame, centers: np.ndarray, entities: DataFrame, queries: DataFrame, predicates: list[P.Predicate], k: int = 10, nprobe: int = 4, codec: str = "flat", rerank: int = 4, exclude_self: bool = True) -> DataFrame:
    """Filter inside the ``nprobe`` nearest lists; coded distances pick ``rerank`` * k candidates a batch, whose distances are then exact."""
    code = Codec(codec, sample_matrix(lists)) if codec != "flat" else Codec("flat", centers)
    rows = lists.select("id", "vec", "list").join(entities.select("id", P.passes(predicates).alias("passes")).where(F.size("passes") > 0), "id")
    parts = []
    for qid, q, pred in _batches(queries):
        d = np.einsum("ij,ij->i", centers, centers)[None, :] - 2 * q @ centers.T
        probe = np.argsort(d, axis=1)[:, : min(nprobe, len(centers))]
        by_list: dict[int, np.ndarray] = {c: np.flatnonzero((probe == c).any(axis=1)) for c in np.unique(probe).tolist()}
        parts.append(rows.where(F.col("list").isin(list(by_list))).mapInArrow(_probe(qid, q, pred, by_list, code, k, rerank, exclude_self), TOPK))
    return merge(parts, k) if parts else rank_topk(queries.where("false").select("query_id", F.col("query_id").alias("id"), F.lit(0.0).alias("dist")), 0)


def _probe(qid: np.ndarray, q: np.ndarray, pred: np.ndarray, by_list: dict[int, np.ndarray], code: Codec, k: int, rerank: int, exclude_self: bool):
    """One batch of rows against the queries that probe their lists; which rows pass which query's predicate is one boolean matrix a batch."""
    schema = pa.schema([("query_id", pa.int64()), ("id", pa.int64()), ("dist", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = np.asarray(b.column("vec").flatten(), np.float64).reshape(b.num_rows, -1)
            y, own, at = code.decode(x), b.column("id").to_numpy(), b.column("list").to_numpy()
            lists = b.column("passes")
            ok_by = np.zeros((int(pred.max()) + 1, b.num_rows), bool)
            flat, who = np.asarray(lists.flatten()), np.repeat(np.arange(b.num_rows), np.asarray(pa.compute.list_value_length(lists)))
            known = flat < len(ok_by)
            ok_by[flat[known], who[known]] = True
            for c in np.unique(at).tolist():
                mine = at == c
                for i in by_list.get(c, np.empty(0, np.int64)).tolist():
                    ok = np.flatnonzero(mine & ok_by[pred[i]] & ((own != qid[i]) | (not exclude_self)))
                    if not len(ok):
                        continue
                    near = ok[np.argsort(((y[ok] - q[i]) ** 2).sum(1), kind="stable")[: k * (1 if code.codec == "flat" else rerank)]]
                    diff = x[near] - q[i]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(near), qid[i])), pa.array(own[near]), pa.array(np.einsum("ij,ij->i", diff, diff))], schema=schema)

    return run
