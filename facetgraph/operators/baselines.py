"""Baselines that are not lists or scans: one graph per predicate, label-aware graphs, attribute-fused graphs."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetgraph.functions import predicates as P
from facetgraph.operators import index as I
from facetgraph.operators import kernel as K
from facetgraph.operators import prune

#: A label graph is meant for few labels.
MOST_LABELS = 1_000


def oracle_partition(entities: DataFrame, predicates: list[P.Predicate], params: K.Params) -> DataFrame:
    """One graph for each predicate, over the rows that pass it: the shard is the predicate's number."""
    if len(predicates) > MOST_LABELS:
        raise P.UnsupportedPredicate("the oracle needs a small set of predicates known beforehand")
    rows = entities.select("id", "vec", F.explode(P.passes(predicates)).alias("shard"))
    rows = rows.withColumn("top_level", I.level_of(F.col("id"), params.m, params.seed))

    def kernel(table: pa.Table) -> pa.Table:
        ids, vecs, top = I.matrix(table)
        return I.table_of(K.build(ids, vecs, top, params), table["shard"][0].as_py())

    return I.dealt(rows, len(predicates)).groupBy("shard").applyInArrow(kernel, I.NODE)


def search_partition(index: DataFrame, queries: DataFrame, params: K.Params, k: int = 10, efs: int | tuple[int, ...] = 40, exclude_self: bool = True, trials: int = 1, whole: bool = False) -> DataFrame:
    """Each query goes to its own predicate's graph. ``whole``: as in ``index.search``."""
    beams = (efs,) if isinstance(efs, int) else tuple(efs)

    def kernel(key: tuple, nodes: pa.Table, asked: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        if nodes.num_rows:
            g, memo = I.graph_of(nodes, params), {}
            for i in range(asked.num_rows):
                qid, q = asked["query_id"][i].as_py(), np.asarray(asked["qvec"][i].as_py(), np.float64)
                for beam in beams:
                    began = time.perf_counter()
                    for _ in range(trials):
                        hits, c, route = K.search(g, q, k, beam, None, "plain", qid if exclude_self else None, True, whole, memo)
                    count = (c.n_dist, c.n_visited, c.n_pred_eval, c.n_passed, c.n_hops, route, nodes["shard"][0].as_py(), beam, (time.perf_counter() - began) / trials)
                    rows += [(qid, v, d, *count) for d, v in hits] or [(qid, None, None, *count)]
        return I.found_table(rows)

    asked = queries.select("query_id", "qvec", F.col("pred_id").alias("to_shard"))
    return index.groupBy("shard").cogroup(asked.groupBy("to_shard")).applyInArrow(kernel, I.FOUND)


def partition_quality(index: DataFrame, params: K.Params) -> DataFrame:
    """(pred_id, level, nodes, components, filtered_degree) of each predicate's own graph, measured as ``index.quality`` measures subgraphs."""
    schema = pa.schema([("pred_id", pa.int32()), ("level", pa.int32()), ("nodes", pa.int64()), ("components", pa.int64()), ("filtered_degree", pa.float64())])

    def kernel(table: pa.Table) -> pa.Table:
        g = I.graph_of(table, params)
        rows = [(table["shard"][0].as_py(), *r) for r in K.subgraph_quality(g, np.ones(len(g.ids), bool))]
        return pa.table([pa.array(list(x), f.type) for x, f in zip(zip(*rows), schema)] if rows else [pa.array([], f.type) for f in schema], schema=schema)

    return index.groupBy("shard").applyInArrow(kernel, "pred_id int, level int, nodes long, components long, filtered_degree double")


def pruned_dense(entities: DataFrame, column: str, params: K.Params, rule: str, shards: int | None = None) -> DataFrame:
    """A dense index whose level 0 is pruned by relative neighbours instead of two-hop coverage: ``rule`` is blind, or aware (of ``column``)."""

    def kernel(table: pa.Table) -> pa.Table:
        table = table.sort_by("id")
        ids, vecs, top = I.matrix(table)
        labels = np.unique(np.array([str(x) for x in table["value"].to_pylist()]), return_inverse=True)[1]
        g = K.Graph(ids, vecs, top, [], int(np.lexsort((ids, -top))[0]), params)
        pairwise = lambda c, kept: g.dist(g.vecs[c], kept)
        for level in range(int(top.max()) + 1):
            nodes = np.flatnonzero(top >= level)
            lists = [K.NOTHING] * len(ids)
            for v, x in zip(nodes.tolist(), K.nearest(vecs, nodes, ids, params.width)):
                if level == 0 and len(x):
                    kept = prune.rng_labelled(x.tolist(), g.dist(vecs[v], x).tolist(), pairwise, params.width, labels if rule == "aware" else None, labels[v])
                    g.pruned += len(x) - len(kept)
                    x = np.asarray(kept, np.int64)
                lists[v] = x
            g.levels.append(lists)
        return I.table_of(g, table["shard"][0].as_py())

    rows = entities.select("id", "vec", F.col(column).cast("string").alias("value")).where("vec is not null")
    shards = I.shards_for(rows) if shards is None else shards
    rows = I.dealt(I.assign_shards(rows, shards), shards)
    return rows.withColumn("top_level", I.level_of(F.col("id"), params.m, params.seed)).groupBy("shard").applyInArrow(kernel, I.NODE)


def _labels(predicates: list[P.Predicate]) -> tuple[str, list]:
    found = [P.equality_label(p) for p in predicates]
    if len({f for f, _ in found}) != 1 or len(found) > MOST_LABELS:
        raise P.UnsupportedPredicate("equality on one attribute of few values")
    return found[0][0], [v for _, v in found]


def _robust(g: K.Graph, v: int, cands: list[int], most: int, alpha: float, labels: np.ndarray | None) -> np.ndarray:
    cands = [c for c in dict.fromkeys(cands) if c != v]
    d = g.dist(g.vecs[v], cands) if cands else np.empty(0)
    order = np.lexsort((g.ids[cands], d)) if cands else []
    cands, d = [cands[i] for i in order], [float(d[i]) for i in order]
    pairwise = lambda c, kept: g.dist(g.vecs[c], kept)
    return np.asarray(prune.rng_labelled(cands, d, pairwise, most, labels, None if labels is None else labels[v], alpha), np.int64)


def label_filtered(ids: np.ndarray, vecs: np.ndarray, labels: np.ndarray, r: int = 16, ef: int = 40, alpha: float = 1.2) -> K.Graph:
    """One flat graph: each point is placed by a walk among points of its own label, from the label's first point, and pruned label-aware."""
    g = K.Graph(ids, vecs, np.zeros(len(ids), np.int64), [[K.NOTHING] * len(ids)], 0, K.Params("label", m=r))
    starts: dict = {}
    lists, c = g.levels[0], K.Counters()
    for i in range(len(ids)):
        start = starts.setdefault(labels[i], i)
        if start == i:
            # labels are tied together, so that the whole stays one graph
            near = [s for s in starts.values() if s != i]
        else:
            same = labels == labels[i]
            at = [(float(g.dist(vecs[i], [start])[0]), start)]
            near = [v for _, v in K.search_layer(g, vecs[i], at, ef, lambda v: [x for x in lists[v].tolist() if same[x]], same, c)]
        lists[i] = _robust(g, i, near, r, alpha, labels)
        for v in lists[i].tolist():
            both = [*lists[v].tolist(), i]
            lists[v] = np.asarray(both, np.int64) if len(both) <= r else _robust(g, v, both, r, alpha, labels)
    return g


def label_stitched(ids: np.ndarray, vecs: np.ndarray, labels: np.ndarray, r_small: int = 8, r: int = 16, ef: int = 40, alpha: float = 1.2) -> K.Graph:
    """A pruned graph within each label, their edges united and pruned again label-aware."""
    g = K.Graph(ids, vecs, np.zeros(len(ids), np.int64), [[K.NOTHING] * len(ids)], 0, K.Params("label", m=r))
    lists = g.levels[0]
    starts: dict = {}
    for label in dict.fromkeys(labels.tolist()):
        nodes = np.flatnonzero(labels == label)
        starts[label] = int(nodes[0])
        near = K.nearest(vecs, nodes, ids, ef)
        for v, x in zip(nodes.tolist(), near):
            lists[v] = _robust(g, v, x.tolist(), r_small, alpha, None)
        back: dict[int, list[int]] = {int(v): lists[v].tolist() for v in nodes}
        for v in nodes.tolist():
            for y in lists[v].tolist():
                back[y].append(v)
        for v in nodes.tolist():
            lists[v] = _robust(g, v, back[v], r, alpha, labels)
    return g


def fused_graph(ids: np.ndarray, vecs: np.ndarray, labels: np.ndarray, weight: float, style: str = "knn", m: int = 16) -> K.Graph:
    """A graph of the distance plus ``weight`` where labels differ: the label is appended to the vector as a scaled one-hot part."""
    hot, _ = _hot(labels, weight)
    params = K.Params("lean" if style == "knn" else "hnsw", m=m, gamma=1, m_beta=m, efc=40, n_compressed=0, m0_factor=1 if style == "knn" else 2, method="bulk" if style == "knn" else "insert")
    return K.build(ids, np.concatenate([vecs, hot], axis=1), np.zeros(len(ids), np.int64), params)


LABELLED = I.NODE + ", label int"


def _hot(labels: np.ndarray, weight: float) -> tuple[np.ndarray, dict[int, int]]:
    """The scaled one-hot part of each row's vector, and each label's place in it."""
    values = {v: i for i, v in enumerate(dict.fromkeys(labels.tolist()))}
    hot = np.zeros((len(labels), max(1, len(values))))
    hot[np.arange(len(labels)), [values[v] for v in labels.tolist()]] = np.sqrt(weight / 2)
    return hot, values


def build_label_graph(entities: DataFrame, predicates: list[P.Predicate], kind: str, shards: int | None = None, **settings) -> DataFrame:
    """An index for equality on one attribute of few values; kind: filtered, stitched, fused-knn or fused-nsw. Rows of ``index.NODE`` with label, the number of the predicate that a row passes, or -1."""
    column, values = _labels(predicates)
    number = {v: i for i, v in enumerate(values)}

    def kernel(table: pa.Table) -> pa.Table:
        table = table.sort_by("id")
        ids, vecs, _ = I.matrix(table)
        labels = np.array([number.get(x, -1) for x in table["value"].to_pylist()])
        if kind.startswith("fused"):
            g = fused_graph(ids, vecs, labels, settings.get("weight", 1.0), kind.split("-")[1])
        else:
            g = (label_filtered if kind == "filtered" else label_stitched)(ids, vecs, labels, **settings)
        out = I.table_of(g, table["shard"][0].as_py())
        out = out.set_column(out.schema.get_field_index("vec"), "vec", pa.array(list(vecs), pa.list_(pa.float64())))
        return out.append_column("label", pa.array(labels.astype(np.int32)))

    rows = entities.select("id", "vec", F.col(column).alias("value"), F.lit(0).alias("top_level")).where("vec is not null")
    shards = I.shards_for(rows) if shards is None else shards
    return I.dealt(I.assign_shards(rows, shards), shards).groupBy("shard").applyInArrow(kernel, LABELLED)


def search_label_graph(index: DataFrame, queries: DataFrame, kind: str, k: int = 10, efs: int | tuple[int, ...] = 40, exclude_self: bool = True, weight: float = 1.0) -> DataFrame:
    """Walks from the label's first point: among points of the label alone, or, for fused graphs, by the distance with the label's part."""
    beams = (efs,) if isinstance(efs, int) else tuple(efs)

    def kernel(key: tuple, nodes: pa.Table, asked: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        if nodes.num_rows and asked.num_rows:
            nodes = nodes.sort_by("id")
            g, labels, shard = I.graph_of(nodes, K.Params("label")), nodes["label"].to_numpy(), nodes["shard"][0].as_py()
            vecs, starts = g.vecs, {int(v): int(i) for v, i in zip(*np.unique(labels, return_index=True))}
            hot, values = _hot(labels, weight)
            if kind.startswith("fused"):
                g.vecs = np.concatenate([vecs, hot], axis=1)
            for i in range(asked.num_rows):
                qid, pred, q = asked["query_id"][i].as_py(), asked["pred_id"][i].as_py(), np.asarray(asked["qvec"][i].as_py(), np.float64)
                ok, own = labels == pred, (qid if exclude_self else None)
                for beam in beams:
                    began, c, found = time.perf_counter(), K.Counters(), []
                    if kind.startswith("fused"):
                        part = np.zeros(hot.shape[1])
                        if pred in values:
                            part[values[pred]], g.entry = np.sqrt(weight / 2), starts[pred]
                        near, c, _ = K.search(g, np.concatenate([q, part]), k + 1, beam, np.ones(len(labels), bool), "plain", own)
                        found = [int(np.searchsorted(g.ids, v)) for _, v in near]
                    elif pred in starts:
                        at = [(float(g.dist(q, [starts[pred]])[0]), starts[pred])]
                        c.n_dist += 1
                        found = [v for _, v in K.search_layer(g, q, at, max(beam, k + 1), lambda v: [x for x in g.levels[0][v].tolist() if ok[x]], ok, c)]
                    hits = sorted((float(((vecs[v] - q) ** 2).sum()), int(g.ids[v])) for v in found if ok[v] and g.ids[v] != own)[:k]
                    count = (c.n_dist, c.n_visited, c.n_pred_eval, c.n_passed, c.n_hops, kind, shard, beam, time.perf_counter() - began)
                    rows += [(qid, v, d, *count) for d, v in hits] or [(qid, None, None, *count)]
        return I.found_table(rows)

    asked = queries.select("query_id", "qvec", "pred_id").join(F.broadcast(index.select(F.col("shard").alias("to_shard")).distinct()))
    return index.groupBy("shard").cogroup(asked.groupBy("to_shard")).applyInArrow(kernel, I.FOUND)


def label_graph_search(entities: DataFrame, queries: DataFrame, predicates: list[P.Predicate], kind: str, k: int = 10, efs: int = 40, shards: int | None = None, exclude_self: bool = True, **settings) -> DataFrame:
    """Builds a label graph and searches it."""
    index = build_label_graph(entities, predicates, kind, shards, **settings)
    return search_label_graph(index, queries, kind, k, efs, exclude_self, settings.get("weight", 1.0))
