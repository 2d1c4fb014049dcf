"""The SQL surface: views, vector functions, and a table function that searches a registered index."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetgraph.operators import kernel as K
from facetgraph.sources import tables as T

FUNCTIONS = {
    "l2_squared": "aggregate(zip_with(a, b, (x, y) -> (cast(x as double) - cast(y as double)) * (cast(x as double) - cast(y as double))), 0.0D, (s, v) -> s + v)",
    "inner_product": "aggregate(zip_with(a, b, (x, y) -> cast(x as double) * cast(y as double)), 0.0D, (s, v) -> s + v)",
    "l1_distance": "aggregate(zip_with(a, b, (x, y) -> abs(cast(x as double) - cast(y as double))), 0.0D, (s, v) -> s + v)",
}


def register(spark: SparkSession, directory: str) -> None:
    """Base tables as views and the vector functions as temporary SQL functions, which Catalyst inlines."""
    T.views(spark, directory)
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body}")


#: Columns that ``hybrid_search`` takes from its table: those of an index, and of queries, each null where a row is the other.
SEARCHED = ("shard", "id", "top_level", "vec", "lists", "passes", "query_id", "qvec", "pred_id")


def register_search(spark: SparkSession, index: DataFrame, params: K.Params, name: str = "hybrid_search") -> None:
    """``name``(TABLE(rows) PARTITION BY shard, k, efs): a table function that searches a shard for all queries sent to it.

    Its rows are the index's, with ``passes`` (the numbers of the predicates that the entity passes), and the queries', once for each shard; see SEARCHED.
    The function meets each index row once, whatever the queries, and gives each query's k nearest of the shard.
    """
    from pyspark.sql.functions import udtf

    @udtf(returnType="query_id: bigint, id: bigint, dist: double")
    class Search:
        def __init__(self):
            self.ids, self.top, self.vecs, self.lists, self.passes, self.asked = [], [], [], [], [], []
            self.k, self.efs = 10, 40

        def eval(self, row, k: int, efs: int):
            if row["query_id"] is None:
                for column, value in ((self.ids, row["id"]), (self.top, row["top_level"]), (self.vecs, row["vec"]), (self.lists, row["lists"]), (self.passes, row["passes"] or [])):
                    column.append(value)
            else:
                self.asked.append((row["query_id"], row["qvec"], row["pred_id"]))
            self.k, self.efs = k, efs

        def terminate(self):
            if not self.ids:
                return
            order = np.argsort(self.ids)
            ids, top = np.array(self.ids)[order], np.array(self.top)[order]
            levels = [[K.NOTHING] * len(ids) for _ in range(int(top.max()) + 1)]
            for v, i in enumerate(order.tolist()):
                for level, near in enumerate(self.lists[i]):
                    levels[level][v] = np.searchsorted(ids, [x["dst"] for x in near]) if near else K.NOTHING
            g = K.Graph(ids, np.array(self.vecs, float)[order], top, levels, int(np.lexsort((ids, -top))[0]), params)
            passing: dict[int, np.ndarray] = {}
            for query_id, qvec, pred in sorted(self.asked):
                if pred not in passing:
                    passing[pred] = np.array([pred in self.passes[i] for i in order.tolist()])
                for d, v in K.search(g, np.array(qvec, float), self.k, self.efs, passing[pred], exclude=query_id)[0]:
                    yield query_id, v, d

    spark.udtf.register(name, Search)
    index.createOrReplaceTempView(f"{name}_index")


def nearest_by_sql(spark: SparkSession, directory: str, k: int = 10) -> DataFrame:
    """Top-K by plain SQL with the registered functions: every query against the rows of its own label."""
    register(spark, directory)
    return spark.sql(f"""
        SELECT query_id, CAST(r AS INT) AS rank, id, round(dist, 6) AS dist FROM (
          SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, id) AS r FROM (
            SELECT q.vec_id AS query_id, e.vec_id AS id, l2_squared(e.embedding, q.embedding) AS dist
            FROM embeddings q JOIN embeddings e ON e.label = q.label AND e.vec_id <> q.vec_id
            WHERE q.vec_id % {T.QUERY_STEP} = 0)) WHERE r <= {k}""")


def search_by_sql(spark: SparkSession, directory: str, shards: int = 2) -> DataFrame:
    """Graph search through the table function: every query of the stated set against the entities of its own label."""
    from facetgraph.operators import index as I
    from facetgraph.plans.experiments import cut

    e = cut(T.entity_vec(spark, directory).select("id", "vec", "label"))
    params = K.hnsw(m=8)
    register_search(spark, cut(I.build(e, params, shards)), params)
    e.createOrReplaceTempView("facet_entity")
    return spark.sql(f"""
        WITH sent AS (
          SELECT i.shard, i.id, i.top_level, i.vec, i.lists, array(e.label) AS passes, CAST(NULL AS BIGINT) AS query_id, CAST(NULL AS ARRAY<DOUBLE>) AS qvec, CAST(NULL AS INT) AS pred_id
          FROM hybrid_search_index i JOIN facet_entity e ON e.id = i.id
          UNION ALL
          SELECT s.shard, NULL, NULL, NULL, NULL, NULL, q.id, q.vec, q.label FROM facet_entity q CROSS JOIN (SELECT DISTINCT shard FROM hybrid_search_index) s WHERE q.id % {T.QUERY_STEP} = 0),
        found AS (SELECT * FROM hybrid_search(TABLE(SELECT * FROM sent) PARTITION BY (shard), 10, 2000)),
        ranked AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, id) AS r FROM found)
        SELECT query_id, CAST(r AS INT) AS rank, id, round(dist, 6) AS dist FROM ranked WHERE r <= 10""")
