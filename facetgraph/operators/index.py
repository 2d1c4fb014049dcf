"""Sharded graph indexes: build, store, search.

An index is one row for each node: (shard, id, top_level, vec, lists), where lists[l] are the neighbours on level l as
(dst, dist), nearest first. Vectors are shuffled once, to their shards; attributes are not stored: predicates are
evaluated by Catalyst at query time and reach the shards as lists of the predicates that a row passes.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, GroupedData, SparkSession
from pyspark.sql import functions as F

from facetgraph.functions import predicates as P
from facetgraph.operators import kernel as K
from facetgraph.operators.exact import rank_topk

NODE = "shard int, id long, top_level int, vec array<double>, lists array<array<struct<dst:long,dist:double>>>, pruned long"
LIST = pa.list_(pa.list_(pa.struct([("dst", pa.int64()), ("dist", pa.float64())])))
NODE_ARROW = pa.schema([("shard", pa.int32()), ("id", pa.int64()), ("top_level", pa.int32()), ("vec", pa.list_(pa.float64())), ("lists", LIST), ("pruned", pa.int64())])
FOUND = "query_id long, id long, dist double, n_dist long, n_visited long, n_pred_eval long, n_passed long, n_hops long, route string, shard int, efs int, seconds double"
FOUND_ARROW = pa.schema([("query_id", pa.int64()), ("id", pa.int64()), ("dist", pa.float64()), ("n_dist", pa.int64()), ("n_visited", pa.int64()), ("n_pred_eval", pa.int64()), ("n_passed", pa.int64()), ("n_hops", pa.int64()), ("route", pa.string()), ("shard", pa.int32()), ("efs", pa.int32()), ("seconds", pa.float64())])
LEVELS = 24
#: Bytes of vectors that one task builds and searches; the bulk builder compares all pairs of a shard, and a wide index keeps some thirty times these bytes while it works.
SHARD_BYTES = 4 << 20
MULTIPLIER = 2246822519


def level_of(key, m: int, seed: int):
    """Top level of a node: l with a uniform draw below m^-l, from integer arithmetic that any engine repeats."""
    u = F.pmod(key * F.lit(MULTIPLIER) + F.lit(seed), F.lit(4294967296))
    out = F.lit(0)
    for level in range(1, LEVELS):
        if m**level > 4294967296:
            break
        out = out + F.when(u * F.lit(m**level) < F.lit(4294967296) if m**level < 2**31 else F.lit(False), 1).otherwise(0)
    return out.cast("int")


def sql_level(key: str, m: int, seed: int) -> str:
    u = f"(({key} * {MULTIPLIER} + {seed}) % 4294967296)"
    return "(" + " + ".join(f"CASE WHEN {u} * {m**i} < 4294967296 THEN 1 ELSE 0 END" for i in range(1, LEVELS) if m**i < 2**31) + ")::INT"


def assign_shards(vectors: DataFrame, shards: int, by: str = "hash") -> DataFrame:
    """Adds shard: by id hash, or the nearest of ``shards`` centroids (fitted on a bounded sample)."""
    if by == "hash" or shards == 1:
        return vectors.withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int"))
    from facetgraph.operators.ivf import kmeans, nearest_centroid

    sample = np.array([r[0] for r in vectors.orderBy(F.xxhash64("id")).limit(10_000).select("vec").collect()])
    return vectors.withColumn("shard", nearest_centroid(kmeans(sample, shards)))


def matrix(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    n = table.num_rows
    vecs = np.asarray(table["vec"].combine_chunks().flatten(), np.float64)
    if n and len(vecs) % n:
        raise ValueError("vectors differ in their dimensions")
    return table["id"].to_numpy(), vecs.reshape(n, -1) if n else vecs.reshape(0, 1), table["top_level"].to_numpy()


def table_of(g: K.Graph, shard: int) -> pa.Table:
    n, top = len(g.ids), g.top.astype(np.int64)
    near = [g.levels[level][v] for v in range(n) for level in range(int(top[v]) + 1)]
    sizes = np.fromiter(map(len, near), np.int64, len(near))
    src, dst = np.repeat(np.repeat(np.arange(n), top + 1), sizes), np.concatenate(near) if near else K.NOTHING
    step = max(1, K.BLOCK_CELLS // max(1, g.vecs.shape[1]))
    dist = np.concatenate([K.squares(g.vecs[src[i : i + step]], g.vecs[dst[i : i + step]]) for i in range(0, len(src), step)] or [np.empty(0)])
    cuts = lambda x: pa.array(np.append(0, np.cumsum(x)).astype(np.int32))
    edges_ = pa.StructArray.from_arrays([pa.array(g.ids[dst]), pa.array(dist)], ["dst", "dist"])
    lists = pa.ListArray.from_arrays(cuts(top + 1), pa.ListArray.from_arrays(cuts(sizes), edges_))
    vecs = pa.ListArray.from_arrays(cuts(np.full(n, g.vecs.shape[1])), pa.array(g.vecs.reshape(-1)))
    return pa.table([pa.array(np.full(n, shard, np.int32)), pa.array(g.ids), pa.array(top.astype(np.int32)), vecs, lists, pa.array([g.pruned] * n, pa.int64())], schema=NODE_ARROW)


def graph_of(table: pa.Table, p: K.Params) -> K.Graph:
    table = table.sort_by("id")
    ids, vecs, top = matrix(table)
    n = len(ids)
    levels: list[list[np.ndarray]] = [[K.NOTHING] * n for _ in range(int(top.max()) + 1 if n else 0)]
    if n:
        by_node = table["lists"].combine_chunks()
        by_level = by_node.values
        dst = np.searchsorted(ids, np.asarray(by_level.values.field("dst")))
        first, cuts = np.asarray(by_node.offsets).tolist(), np.asarray(by_level.offsets).tolist()
        for v in range(n):
            for level, i in enumerate(range(first[v], first[v + 1])):
                if cuts[i + 1] > cuts[i]:
                    levels[level][v] = dst[cuts[i] : cuts[i + 1]]
    return K.Graph(ids, vecs, top, levels, int(np.lexsort((ids, -top))[0]) if n else 0, p)


def trim() -> None:
    """Returns to the system what this process has freed."""
    import ctypes

    pa.default_memory_pool().release_unused()
    give = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if give:
        give(0)


def given_back(kernel):
    """``kernel`` of one table, or of a key and two tables, which gives its memory back after each group: workers are kept for other tasks."""

    def alone(table: pa.Table) -> pa.Table:
        try:
            return kernel(table)
        finally:
            trim()

    def both(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        try:
            return kernel(key, left, right)
        finally:
            trim()

    return alone if kernel.__code__.co_argcount == 1 else both


def shards_for(vectors: DataFrame, shard_bytes: int = SHARD_BYTES) -> int:
    """Shards so that each holds about ``shard_bytes`` of vectors."""
    size = vectors.agg(F.sum(8 * F.size("vec"))).first()[0] or 0
    return max(1, -(-int(size) // shard_bytes))


def build(vectors: DataFrame, params: K.Params, shards: int | None = None, by: str = "hash", flat: bool = False) -> DataFrame:
    """The index of (id, vec): vectors go to their shards in one shuffle, each shard is built by one task. By default a shard holds SHARD_BYTES of vectors.

    ``flat``: all nodes on one level, a plain neighbour graph with the same lists and lookups.
    """

    def kernel(table: pa.Table) -> pa.Table:
        ids, vecs, top = matrix(table)
        return table_of(K.build(ids, vecs, top, params), table["shard"][0].as_py())

    return placed(vectors, params, shards, by, flat).applyInArrow(given_back(kernel), NODE)


def placed(vectors: DataFrame, params: K.Params, shards: int | None = None, by: str = "hash", flat: bool = False) -> GroupedData:
    """(shard, id, vec, top_level) of (id, vec), by shard."""
    known = vectors.select("id", "vec").where("vec is not null")
    shards = shards_for(known) if shards is None else shards
    rows = dealt(assign_shards(known, shards, by), shards)
    top = F.lit(0) if flat else level_of(F.col("id"), params.m, params.seed)
    return rows.withColumn("top_level", top).groupBy("shard")


def dealt(rows: DataFrame, shards: int) -> DataFrame:
    """``rows`` with few shards a task: a shard is small beside the work on it."""
    return rows.repartition(4 * shards, "shard") if shards > 1 else rows


def build_hnsw(vectors: DataFrame, m: int = 8, efc: int = 40, **kw) -> DataFrame:
    return build(vectors, K.hnsw(m=m, efc=efc), **kw)


def save(index: DataFrame, path: str) -> None:
    index.write.mode("overwrite").partitionBy("shard").parquet(path)


def store(index: DataFrame, path: str, name: str, buckets: int = 8) -> DataFrame:
    """The index as a table bucketed by shard: searches read it in place, and only queries and the numbers of passed predicates travel to it."""
    spark = index.sparkSession
    spark.sql(f"DROP TABLE IF EXISTS {name}")
    index.write.mode("overwrite").option("path", path).bucketBy(buckets, "shard").sortBy("shard").saveAsTable(name)
    return spark.table(name)


def load(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(NODE).parquet(path)


def edges(index: DataFrame) -> DataFrame:
    """(shard, level, src, pos, dst, dist)."""
    levels = index.select("shard", F.col("id").alias("src"), F.posexplode("lists").alias("level", "nbrs"))
    return levels.select("shard", "level", "src", F.posexplode("nbrs").alias("pos", "n")).select("shard", "level", "src", "pos", "n.dst", "n.dist")


def passing(entities: DataFrame, predicates: list[P.Predicate]) -> DataFrame:
    return entities.select("id", P.passes(predicates).alias("passes"))


def search(index: DataFrame, entities: DataFrame, queries: DataFrame, predicates: list[P.Predicate], params: K.Params, k: int = 10, efs: int | tuple[int, ...] = 40, lookup: str = "auto", exclude_self: bool = True, fallback: bool = True, over: str | None = None, trials: int = 1, whole: bool = False) -> DataFrame:
    """Raw per-shard results with counters and seconds (see ``topk`` and ``stats``); several beam widths ``efs`` are searched in one pass.

    ``over``: post-filter. The walk ignores the predicate and collects k ("K"), k / s of the shard ("K/s"), or doubles
    its width until k pass ("double"); what fails is dropped afterwards. ``trials``: repetitions that the seconds are a mean of.
    ``whole``: a beam as wide as all that may pass finds all of it, also where lists leave parts unlinked.
    """

    beams = (efs,) if isinstance(efs, int) else tuple(efs)

    def kernel(key: tuple, nodes: pa.Table, sent: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        asked = sent.filter(pa.compute.is_valid(sent["query_id"]))
        if nodes.num_rows and asked.num_rows:
            g = graph_of(nodes, params)
            passed = sent.filter(pa.compute.is_valid(sent["node"]))
            lists = passed["passes"].combine_chunks()
            at = np.minimum(np.searchsorted(g.ids, passed["node"].to_numpy()), len(g.ids) - 1)
            at = np.where(g.ids[at] == passed["node"].to_numpy(), at, -1)
            who, flat = np.repeat(at, np.asarray(pa.compute.list_value_length(lists))), np.asarray(lists.flatten())
            who, flat = who[who >= 0], flat[who >= 0]
            bits: dict[int, np.ndarray] = {}
            memos: dict[int, dict] = {}
            shard = nodes["shard"][0].as_py()
            vectors = np.asarray(asked["qvec"].combine_chunks().flatten(), np.float64).reshape(asked.num_rows, -1)
            for qid, pred, q in zip(asked["query_id"].to_pylist(), asked["pred_id"].to_pylist(), vectors):
                if pred not in bits:
                    bits[pred] = np.zeros(len(g.ids), bool)
                    bits[pred][who[flat == pred]] = True
                ok, own, memo = bits[pred], qid if exclude_self else None, memos.setdefault(pred if over is None else -1, {})
                for beam in beams:
                    began = time.perf_counter()
                    for _ in range(trials):
                        hits, c, route = K.search(g, q, k, beam, ok, lookup, own, fallback, whole, memo) if over is None else post_filter(g, q, k, beam, ok, own, over, whole, memo)
                    count = (c.n_dist, c.n_visited, c.n_pred_eval, c.n_passed, c.n_hops, route, shard, beam, (time.perf_counter() - began) / trials)
                    rows += [(qid, v, d, *count) for d, v in hits] or [(qid, None, None, *count)]
        return found_table(rows)

    # of the index only ids and shards meet the entities; vectors and lists stay where they are
    where_ = index.select(F.col("id").alias("node"), F.col("shard").alias("to_shard")).join(passing(entities, predicates).where(F.size("passes") > 0).withColumnRenamed("id", "node"), "node")
    nothing = lambda t, name: F.lit(None).cast(t).alias(name)
    marks = where_.select("to_shard", F.col("node").cast("long").alias("node"), F.col("passes").alias("passes"), nothing("long", "query_id"), nothing("array<double>", "qvec"), nothing("int", "pred_id"))
    shards = index.select(F.col("shard").alias("to_shard")).distinct()
    asked = queries.select("query_id", F.col("qvec").cast("array<double>").alias("qvec"), F.col("pred_id").cast("int").alias("pred_id")).join(F.broadcast(shards), how="inner")
    sent = marks.union(asked.select("to_shard", nothing("long", "node"), nothing("array<int>", "passes"), F.col("query_id").cast("long"), "qvec", "pred_id"))
    return index.select("shard", "id", "top_level", "vec", "lists").groupBy("shard").cogroup(sent.groupBy("to_shard")).applyInArrow(given_back(kernel), FOUND)


def found_table(rows: list[tuple]) -> pa.Table:
    return pa.table([pa.array(list(x), f.type) for x, f in zip(zip(*rows), FOUND_ARROW)] if rows else [pa.array([], f.type) for f in FOUND_ARROW], schema=FOUND_ARROW)


def post_filter(g: K.Graph, q: np.ndarray, k: int, efs: int, ok: np.ndarray, own: int | None, over: str, whole: bool = False, memo: dict | None = None) -> tuple[list, K.Counters, str]:
    """Walks by plain lists, whatever passes, and drops what fails; "double" widens one walk until k pass."""
    n, s, c = len(g.ids), float(ok.mean()) if len(ok) else 0.0, K.Counters()
    if not s:
        return [], c, "empty"
    want = min(n, k if over != "K/s" else int(-(-k // s)))
    start = K.descend(g, q, c)
    if over == "double" and efs >= n:
        # a beam that never fills: all that the lists lead to
        near_ = K.reached(g, [v for _, v in start], lambda v: g.levels[0][v].tolist(), np.ones(n, bool), c, whole, {} if memo is None else memo)
        c.n_pred_eval += len(near_)
        return K.ranked(g, q, near_[ok[near_] & (g.ids[near_] != own if own is not None else True)], k), c, "postfilter"
    walk = K.Walk(g, q, start, 0, ok, c)
    while True:
        # one place more, since the query itself may be among the found
        near = walk.widen(max(efs, want + 1))
        found = np.asarray([v for _, v in near if own is None or g.ids[v] != own][:want], np.int64)
        hits = found[ok[found]]
        if over != "double" or len(hits) >= k or want >= n:
            c.n_pred_eval += len(found)
            return K.ranked(g, q, hits, k), c, "postfilter"
        want = min(n, want * 2)


def topk(found: DataFrame, k: int) -> DataFrame:
    return rank_topk(found.where("id is not null"), k)


def stats(found: DataFrame) -> DataFrame:
    """Counters of each query, summed over the shards."""
    cols = ["n_dist", "n_visited", "n_pred_eval", "n_passed", "n_hops"]
    each = found.groupBy("query_id", "shard").agg(*[F.first(c).alias(c) for c in cols], F.first("route").alias("route"))
    return each.groupBy("query_id").agg(*[F.sum(c).alias(c) for c in cols], F.array_join(F.sort_array(F.collect_set("route")), "+").alias("route"))


def out_degree(index: DataFrame) -> DataFrame:
    """Mean list length by level, over the nodes of the level."""
    levels = index.select(F.posexplode("lists").alias("level", "nbrs"))
    return levels.groupBy("level").agg(F.count("*").alias("nodes"), F.avg(F.size("nbrs")).alias("degree"), F.max(F.size("nbrs")).alias("largest"))


def out_degrees(vectors: DataFrame, params: dict[str, K.Params], shards: int | None = None) -> DataFrame:
    """``out_degree`` of an index for each of ``params`` (one m and seed, bulk builder), with its name as method: a task builds the graphs of a shard and returns their counts, no lists."""
    if len({(p.m, p.seed) for p in params.values()}) != 1 or any(p.method != "bulk" for p in params.values()):
        raise ValueError("the graphs must share their levels and the bulk builder")
    first = next(iter(params.values()))
    counts = pa.schema([("method", pa.string()), ("level", pa.int32()), ("n", pa.int64()), ("links", pa.int64()), ("most", pa.int32())])

    def kernel(table: pa.Table) -> pa.Table:
        found = K.degrees(*matrix(table), params)
        return pa.table([pa.array(list(x), f.type) for x, f in zip(zip(*found), counts)], schema=counts)

    each = placed(vectors, first, shards).applyInArrow(given_back(kernel), "method string, level int, n long, links long, most int")
    return each.groupBy("method", "level").agg(F.sum("n").alias("nodes"), (F.sum("links") / F.sum("n")).alias("degree"), F.max("most").alias("largest"))


def index_size(index: DataFrame) -> DataFrame:
    """Bytes of the vectors as 4-byte floats and of the lists as 8-byte ids."""
    edges_ = F.aggregate("lists", F.lit(0), lambda s, x: s + F.size(x))
    return index.agg(F.sum(4 * F.size("vec")).alias("vector_bytes"), F.sum(8 * edges_).cast("long").alias("edge_bytes"))


def quality(index: DataFrame, entities: DataFrame, predicates: list[P.Predicate], params: K.Params) -> DataFrame:
    """(shard, pred_id, level, nodes, components, filtered_degree) of each predicate's subgraph; no edge crosses a shard."""
    schema = pa.schema([("shard", pa.int32()), ("pred_id", pa.int32()), ("level", pa.int32()), ("nodes", pa.int64()), ("components", pa.int64()), ("filtered_degree", pa.float64())])

    def kernel(table: pa.Table) -> pa.Table:
        table = table.sort_by("id")
        g, rows = graph_of(table, params), []
        passes = table["passes"].to_pylist()
        for i in range(len(predicates)):
            ok = np.array([i in x for x in passes], bool)
            rows += [(table["shard"][0].as_py(), i, *r) for r in K.subgraph_quality(g, ok)]
        return pa.table([pa.array(list(x), f.type) for x, f in zip(zip(*rows), schema)] if rows else [pa.array([], f.type) for f in schema], schema=schema)

    nodes = index.join(passing(entities, predicates), "id")
    return nodes.groupBy("shard").applyInArrow(kernel, "shard int, pred_id int, level int, nodes long, components long, filtered_degree double")


def recovery_violations(index: DataFrame, candidates: DataFrame, m_beta: int, cap: int) -> DataFrame:
    """Pruned level-0 candidates x of v (from ``candidates``: src, pos, dst) that no stored later neighbour of v lists.

    Candidates behind the point where the walk stopped early are outside the claim and not counted.
    """
    level0 = edges(index).where("level = 0")
    stored = level0.select("src", "dst", "pos")
    last = stored.groupBy("src").agg(F.max_by("dst", "pos").alias("last_dst"), F.count("*").alias("kept"))
    reach = candidates.join(last, (candidates["src"] == last["src"]) & (candidates["dst"] == last["last_dst"]), "inner").select(candidates["src"].alias("s"), F.col("pos").alias("stop"))
    pruned = candidates.join(stored.select("src", "dst"), ["src", "dst"], "left_anti").join(reach, F.col("src") == F.col("s")).where("pos < stop").select("src", "dst")
    tail = stored.where(F.col("pos") >= m_beta).select("src", F.col("dst").alias("y"))
    covered = tail.join(stored.select(F.col("src").alias("y"), F.col("dst")), "y").select("src", "dst").distinct()
    return pruned.join(covered, ["src", "dst"], "left_anti")
