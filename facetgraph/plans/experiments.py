"""The experiments: recall and distance tables, curves, index costs, graph quality, pruning, baselines."""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetgraph.functions import predicates as P
from facetgraph.operators import baselines, exact, ivf, relgraph
from facetgraph.operators import index as I
from facetgraph.operators import kernel as K
from facetgraph.plans import metrics
from facetgraph.plans.workloads import SEARCH_STEP, WORKLOADS, Workload, entities, queries, searches
from facetgraph.sources import tables as T
from facetgraph.sources.tables import cut

M, GAMMA, SEED, TOP = 8, 12, 7, 10
DENSE, LEAN, HNSW = K.dense(m=M, gamma=GAMMA, m_beta=2 * M), K.lean(m=M), K.hnsw(m=M)


#: Beam widths of the measured curves, and the step of their query sets.
WIDTHS, CURVE_STEP = tuple(range(10, 801, 50)), 25


def _ready(spark: SparkSession, directory: str, w: Workload) -> tuple[DataFrame, DataFrame, DataFrame]:
    rows = entities(spark, directory, w)
    # texts are kept only where a predicate reads them
    e = cut(rows.drop(*[c for c in ("caption", "text") if f"'{c}'" not in repr(w.predicates)]))
    q = cut(searches(e, w))
    return e, q, cut(exact.prefilter(e, q, list(w.predicates), TOP))


POINT = ["method", "efs", "recall", "n_dist", "n_pred_eval", "pass_share", "fallback_share", "qps"]


def _points(truth: DataFrame, runs: list[tuple[str, DataFrame]]) -> DataFrame:
    """A row for each method and beam width: recall, distances, predicate tests, share of the visited that pass, share of fallbacks, queries a second."""
    out = None
    for method, found in runs:
        one = metrics.curve_of(cut(found), truth, TOP).withColumn("method", F.lit(method)).select(POINT)
        out = one if out is None else out.union(one)
    return out


def _methods(e: DataFrame, q: DataFrame, w: Workload, efs, trials: int = 1) -> list[tuple[str, DataFrame]]:
    preds = list(w.predicates)
    hnsw = cut(I.build(e, HNSW))
    return [
        ("oracle", baselines.search_partition(cut(baselines.oracle_partition(e, preds, HNSW)), q, HNSW, TOP, efs, trials=trials)),
        ("dense", I.search(cut(I.build(e, DENSE)), e, q, preds, DENSE, TOP, efs, trials=trials)),
        ("lean", I.search(cut(I.build(e, LEAN)), e, q, preds, LEAN, TOP, efs, trials=trials)),
        ("postfilter", I.search(hnsw, e, q, preds, HNSW, TOP, efs, over="K/s", trials=trials)),
        ("postfilter_k", I.search(hnsw, e, q, preds, HNSW, TOP, efs, over="K", trials=trials)),
    ]


def recall_table(spark: SparkSession, directory: str, w: Workload, efs: int = 40) -> DataFrame:
    """Every method at one beam width, beside the pre-filter, which is exact and computes a distance for each row that passes."""
    e, q, truth = _ready(spark, directory, w)
    passing = metrics.selectivity(e, list(w.predicates)).select("pred_id", "passing")
    exact_row = q.join(F.broadcast(passing), "pred_id").agg(F.lit("prefilter").alias("method"), F.lit(0).alias("efs"), F.lit(1.0).alias("recall"), F.avg("passing").alias("n_dist"), F.lit(float(e.count())).alias("n_pred_eval"), F.lit(1.0).alias("pass_share"), F.lit(0.0).alias("fallback_share"), F.lit(None).cast("double").alias("qps"))
    return _points(truth, _methods(e, q, w, efs)).union(exact_row.select(POINT))


def curve(spark: SparkSession, directory: str, w: Workload, widths=WIDTHS, step: int = CURVE_STEP, trials: int = 1) -> DataFrame:
    """The methods over beam widths, all widths in one pass."""
    e, _, _ = _ready(spark, directory, w)
    q = cut(queries(e, replace(w, step=step)))
    return _points(cut(exact.prefilter(e, q, list(w.predicates), TOP)), _methods(e, q, w, tuple(widths), trials))


def read_offs(spark: SparkSession, directory: str, w: Workload) -> DataFrame:
    """Distances at recall 0.8, pace at recall 0.9, recall at the dense index's pace, points on the frontier; each beside the oracle's."""
    return metrics.read_offs(cut(curve(spark, directory, w)))


def scale_series(spark: SparkSession, directory: str, times=(1, 2, 4), efs: int = 40) -> DataFrame:
    """The methods on one, two and four times the vectors: copies are moved by a fixed pattern of their own, ids and labels are new, queries stay."""
    w = WORKLOADS["eq12"]
    base = T.entity_vec(spark, directory).select("id", "vec")
    out = None
    for t in times:
        copy = F.explode(F.sequence(F.lit(0), F.lit(t - 1)))
        more = base.withColumn("c", copy).withColumn("new", F.col("id") + F.col("c") * 10_000_000)
        moved = more.select(F.col("new").alias("id"), F.transform("vec", lambda x, i: x + F.when(F.col("c") > 0, 0.05).otherwise(0.0) * F.sin((i + 1) * F.col("new"))).alias("vec"))
        e = cut(moved.withColumn("cat12", T.cat12(F.col("id"))))
        q = cut(T.query_set(e.where("id < 10000000"), w.pick(), CURVE_STEP))
        truth = cut(exact.prefilter(e, q, list(w.predicates), TOP))
        n = e.count()
        one = _points(truth, _methods(e, q, w, efs)).withColumn("vectors", F.lit(n)).withColumn("prefilter_distances", F.lit(n / 12))
        out = one if out is None else out.union(one)
    return out


def inverted_lists(spark: SparkSession, directory: str) -> DataFrame:
    """Flat, 8-bit and product-coded lists over numbers of probes, and plain graphs filtered afterwards: recall, pace, and which variant is best at recall 0.9 (or, if none comes there, in recall)."""
    w = WORKLOADS["eq12"]
    e, q, truth = _ready(spark, directory, w)
    lists, centers = ivf.build(e.select("id", "vec"), 16)
    lists, n, preds, rows = cut(lists), q.count(), list(w.predicates), []
    for codec in ("flat", "sq8", "pq"):
        for nprobe in (2, 4, 8, 16):
            began = time.perf_counter()
            found = cut(ivf.search(lists, centers, e, q, preds, TOP, nprobe, codec))
            rows.append((f"ivf_{codec}", nprobe, metrics.mean_recall(truth, found, TOP), n / (time.perf_counter() - began)))
    hnsw = cut(I.build(e, HNSW))
    for efs in (10, 40, 160):
        began = time.perf_counter()
        found = cut(I.search(hnsw, e, q, preds, HNSW, TOP, efs, over="K"))
        rows.append(("hnsw_filtered", efs, metrics.mean_recall(truth, I.topk(found, TOP), TOP), n / (time.perf_counter() - began)))
    table = spark.createDataFrame([(m, p, float(r), float(s)) for m, p, r, s in rows], "method string, setting int, recall double, qps double")
    best = metrics.qps_at_recall(table, 0.9).orderBy(F.col("qps").desc()).first()
    name = best["method"] if best else max(rows, key=lambda r: r[2])[0]
    return table.withColumn("pareto_best", F.col("method") == name)


def plain_curve(spark: SparkSession, directory: str) -> DataFrame:
    """Search without predicates over beam widths: layered graphs, and the dense and lean indexes read by their first entries."""
    w = WORKLOADS["eq12"]
    e = cut(entities(spark, directory, w))
    q = cut(queries(e, replace(w, step=CURVE_STEP)).withColumn("pred_id", F.lit(0)))
    truth = cut(exact.prefilter(e, q, [P.always()], TOP))
    runs = [(name, I.search(cut(I.build(e, params)), e, q, [P.always()], params, TOP, WIDTHS)) for name, params in (("hnsw", HNSW), ("dense", DENSE), ("lean", LEAN))]
    return _points(truth, runs)


def build_widths(spark: SparkSession, directory: str) -> DataFrame:
    """The inserting builder with walks that read the first m, 2 m or all entries of each list: seconds to index beside recall, distances and pace."""
    w = WORKLOADS["eq12"]
    e, q, truth = _ready(spark, directory, w)
    out = None
    for width in (M, 2 * M, M * GAMMA):
        params = K.dense(m=M, gamma=GAMMA, m_beta=2 * M, method="insert", build_width=width)
        began = time.perf_counter()
        index = cut(I.build(e, params))
        one = _points(truth, [(f"first {width}", I.search(index, e, q, list(w.predicates), params, TOP, 40))]).withColumn("seconds", F.lit(time.perf_counter() - began))
        out = one if out is None else out.union(one)
    return out


def flat_graph(spark: SparkSession, directory: str) -> DataFrame:
    """Widened and two-hop lookups on a neighbour graph without layers, beside the layered indexes."""
    w = WORKLOADS["eq12"]
    e, q, truth = _ready(spark, directory, w)
    preds, runs = list(w.predicates), []
    for name, params in (("dense", DENSE), ("lean", LEAN)):
        for flat in (True, False):
            index = cut(I.build(e, params, flat=flat))
            runs.append((f"{name}_{'flat' if flat else 'layered'}", I.search(index, e, q, preds, params, TOP, (10, 40, 160))))
    return _points(truth, runs)


def index_costs(spark: SparkSession, directory: str) -> DataFrame:
    """Seconds to index, bytes of vectors and edges, and pruned candidates a node, by builder, on both views."""
    rows = []
    for view in ("vec", "doc"):
        e = cut(T.entity_vec(spark, directory).select("id", "vec", "label") if view == "vec" else T.entity_doc(spark, directory).select("id", "vec", F.col("cat12").alias("label")))
        n = max(e.count(), 1)
        values = sorted(r[0] for r in e.select("label").distinct().collect())
        preds = [P.eq("label", v) for v in values]
        builds = {"dense": lambda e=e: I.build(e, DENSE), "lean": lambda e=e: I.build(e, LEAN), "hnsw": lambda e=e: I.build(e, HNSW)}
        if view == "vec":
            # the inserting and the label-aware builders walk point by point, on one core
            builds |= {f"{k}_inserted": lambda e=e, k=k: I.build(e, {"dense": K.dense(m=M, gamma=GAMMA, m_beta=2 * M, method="insert"), "lean": K.lean(m=M, method="insert"), "hnsw": K.hnsw(m=M, method="insert")}[k]) for k in ("dense", "lean", "hnsw")}
            builds |= {f"label_{k}": lambda e=e, k=k, preds=preds: baselines.build_label_graph(e, preds, k).drop("label") for k in ("filtered", "stitched")}
        vectors = 0
        for name, build in builds.items():
            t = time.perf_counter()
            index = cut(build())
            spent = time.perf_counter() - t
            vectors, edge_bytes = I.index_size(index).first()
            pruned = index.groupBy("shard").agg(F.max("pruned").alias("p")).agg(F.sum("p")).first()[0] or 0
            rows.append((view, name, spent, vectors, edge_bytes, pruned / n))
        rows.append((view, "flat", 0.0, vectors, 0, 0.0))
    return spark.createDataFrame(rows, "view string, method string, seconds double, vector_bytes long, edge_bytes long, pruned_per_node double")


def degrees(spark: SparkSession, directory: str) -> DataFrame:
    """Mean and largest list length by level and builder, on both views."""
    out = None
    for view, load in (("vec", T.entity_vec), ("doc", T.entity_doc)):
        e = cut(load(spark, directory).select("id", "vec"))
        found = I.out_degrees(e, {"dense": DENSE, "lean": LEAN, "hnsw": HNSW})
        one = found.select("level", "nodes", "degree", "largest", "method", F.lit(view).alias("view"))
        out = one if out is None else out.union(one)
    return out


def graph_quality(spark: SparkSession, directory: str) -> DataFrame:
    """Strong components, height and filtered degree by level of predicate subgraphs and of the oracle's graphs, for date ranges of five selectivities."""
    e = cut(T.entity_vec(spark, directory).where("o_date is not null"))
    cuts = e.agg(F.expr("percentile_approx(o_date, array(0.0127, 0.0485, 0.1215, 0.2529, 0.6164), 100000)")).first()[0]
    preds = [P.lt("o_date", c) for c in cuts]
    columns = ["graph", "pred_id", "level", "nodes", "components", "filtered_degree"]
    whole = I.quality(I.build(e, DENSE), e, preds, DENSE).withColumn("graph", F.lit("dense")).select(columns)
    alone = baselines.partition_quality(baselines.oracle_partition(e, preds, HNSW), HNSW).withColumn("graph", F.lit("oracle")).select(columns)
    both = cut(whole.union(alone))
    height = both.groupBy("graph", "pred_id").agg(F.max("level").alias("height"))
    return both.join(height, ["graph", "pred_id"])


def pruning_ablation(spark: SparkSession, directory: str) -> DataFrame:
    """Level-0 pruning of the same candidates: two-hop coverage at several m_beta, none, relative neighbours blind and aware of the attribute. Time to index, edges, pruned candidates a node, recall, distances, pace."""
    w = WORKLOADS["eq12"]
    e, q, truth = _ready(spark, directory, w)
    n, preds = e.count(), list(w.predicates)
    plain = K.dense(m=M, gamma=GAMMA, m_beta=M * GAMMA, n_compressed=0)
    arms = [(f"two_hop_{b}", K.dense(m=M, gamma=GAMMA, m_beta=b), None) for b in (M, 2 * M, 4 * M)]
    arms += [("none", plain, None), ("two_levels", K.dense(m=M, gamma=GAMMA, m_beta=2 * M, n_compressed=2), None), ("rng_blind", plain, "blind"), ("rng_aware", plain, "aware")]
    out = None
    for name, params, rule in arms:
        began = time.perf_counter()
        index = cut(I.build(e, params) if rule is None else baselines.pruned_dense(e, "cat12", params, rule))
        spent = time.perf_counter() - began
        pruned = index.groupBy("shard").agg(F.max("pruned").alias("p")).agg(F.sum("p")).first()[0] or 0
        degree = I.out_degree(index).where("level = 0").first()["degree"]
        one = _points(truth, [(name, I.search(index, e, q, preds, params, TOP, 40))])
        one = one.select("*", F.lit(spent).alias("seconds"), F.lit(I.index_size(index).first()[1]).alias("edge_bytes"), F.lit(float(degree)).alias("degree"), F.lit(pruned / n).alias("pruned_per_node"))
        out = one if out is None else out.union(one)
    return out


def recovery(spark: SparkSession, directory: str) -> DataFrame:
    """Pruned candidates of the exact lists that no stored neighbour leads to, by builder: the bulk builder must leave none, the inserting one
    prunes lists of its own, found by walks, so that some of the exact candidates were never its candidates."""
    e = cut(T.entity_vec(spark, directory).select("id", "vec"))
    lists = cut(relgraph.knn_graph(relgraph.nodes_of(e, M, SEED), 0, M * GAMMA))
    out = None
    for method in ("bulk", "insert"):
        params = K.dense(m=M, gamma=GAMMA, m_beta=2 * M, method=method)
        one = I.recovery_violations(cut(I.build(e, params, 1)), lists, params.m_beta, M * GAMMA).agg(F.lit(method).alias("builder"), F.count("*").alias("violations"))
        out = one if out is None else out.union(one)
    return out.withColumn("candidates", F.lit(lists.count()))


def baseline_recall(spark: SparkSession, directory: str) -> DataFrame:
    """Label graphs, fused graphs and plain graph search on the equality workload, each built once and searched at three beam widths."""
    w = WORKLOADS["label"]
    e, q, truth = _ready(spark, directory, w)
    preds = list(w.predicates)
    runs = [(kind, baselines.search_label_graph(cut(baselines.build_label_graph(e, preds, kind)), q, kind, TOP, (10, 40, 160))) for kind in ("filtered", "stitched", "fused-knn", "fused-nsw")]
    runs.append(("dense", I.search(cut(I.build(e, DENSE)), e, q, preds, DENSE, TOP, (10, 40, 160))))
    return _points(truth, runs)


#: A predicate of each kind.
KINDS = {"equals": P.eq("label", 1), "any_of": P.contains_any("brands", ["Brand#11"]), "between": P.between("label", 1, 2), "regex": P.regex("caption", "a")}


def support_matrix(spark: SparkSession, directory: str) -> DataFrame:
    """Which predicates the restricted baselines accept: as published, and here, where inverted lists take any, since the filter is Catalyst's; and the vectors that pass."""
    rows = []
    for i, (name, p) in enumerate(KINDS.items()):
        for method in ("label_graph", "fused_graph", "ivf", "graph"):
            ok = True
            published = method == "graph" or p.op in ("eq", "between") and (method == "ivf" or p.op == "eq")
            if method in ("label_graph", "fused_graph"):
                try:
                    baselines._labels([p])
                except P.UnsupportedPredicate:
                    ok = False
            rows.append((method, name, published, ok, i))
    matrix = spark.createDataFrame(rows, "method string, predicate string, published boolean, supported boolean, pred_id int")
    passing = metrics.selectivity(T.entity_vec(spark, directory), list(KINDS.values())).select("pred_id", "passing")
    return matrix.join(F.broadcast(passing), "pred_id").drop("pred_id")


def purity(spark: SparkSession, directory: str) -> DataFrame:
    """P(neighbour passes | node passes) beside the selectivity, with and without clustering."""
    out = None
    for name in ("label", "kw_no"):
        w = WORKLOADS[name]
        e = cut(entities(spark, directory, w))
        one = metrics.purity(I.build(e, DENSE), e, list(w.predicates)).join(metrics.selectivity(e, list(w.predicates)).select("pred_id", "selectivity"), "pred_id").withColumn("workload", F.lit(name))
        out = one if out is None else out.union(one)
    return out


def side_by_side(spark: SparkSession, directory: str) -> DataFrame:
    """Nearest vectors with and without the keyword predicate, for every query."""
    w = WORKLOADS["kw_pos"]
    e = cut(entities(spark, directory, w))
    q = cut(queries(e, w))
    plain = exact.prefilter(e, q.withColumn("pred_id", F.lit(0)), [P.always()], TOP)
    both = exact.prefilter(e, q, list(w.predicates), TOP)
    return plain.select("query_id", "rank", F.col("id").alias("vector_only")).join(both.select("query_id", "rank", F.col("id").alias("hybrid")), ["query_id", "rank"], "left")


def percentiles(spark: SparkSession, directory: str, efs: int = 40) -> DataFrame:
    """Recall and distances for date ranges of the five stated selectivities, a row for each and method."""
    from facetgraph.sources.tables import query_set

    e = cut(T.entity_vec(spark, directory).where("o_date is not null").drop("caption"))
    shares = (0.0127, 0.0485, 0.1215, 0.2529, 0.6164)
    cuts = e.agg(F.expr(f"percentile_approx(o_date, array({', '.join(map(str, shares))}), 100000)")).first()[0]
    built, out = {"dense": cut(I.build(e, DENSE)), "lean": cut(I.build(e, LEAN)), "hnsw": cut(I.build(e, HNSW))}, None
    for share, bound in zip(shares, cuts):
        preds = [P.lt("o_date", bound)]
        q = cut(query_set(e, F.lit(0), SEARCH_STEP, 0))
        truth = cut(exact.prefilter(e, q, preds, TOP))
        runs = [("postfilter" if over else name, I.search(built[name], e, q, preds, params, TOP, efs, over=over)) for name, params, over in (("dense", DENSE, None), ("lean", LEAN, None), ("hnsw", HNSW, "K/s"))]
        one = _points(truth, runs).withColumn("selectivity", F.lit(share))
        out = one if out is None else out.union(one)
    return out


def throughput(spark: SparkSession, directory: str, trials: int = 50) -> DataFrame:
    """Queries a second at one beam width: of one thread, a mean of ``trials`` repetitions of each query, and for the pre-filter through Spark."""
    w = WORKLOADS["eq12"]
    e, _, _ = _ready(spark, directory, w)
    q = cut(queries(e, replace(w, step=50)))
    truth = cut(exact.prefilter(e, q, list(w.predicates), TOP))
    graphs = _points(truth, _methods(e, q, w, 40, trials)).select("method", "recall", "qps")
    spark_qps = metrics.qps(lambda: exact.prefilter(e, q, list(w.predicates), TOP), q.count(), 3)
    return graphs.union(spark.createDataFrame([("prefilter_through_spark", 1.0, spark_qps)], "method string, recall double, qps double"))


def tuning(spark: SparkSession, directory: str) -> DataFrame:
    """gamma from the workload's least selectivity and raised until hybrid recall meets plain recall; m and efc, and m_beta within the budget, by pace at recall 0.9."""
    from facetgraph.plans import routing

    w = WORKLOADS["eq12"]
    e, q, truth = _ready(spark, directory, w)
    preds = list(w.predicates)
    low = routing.s_min(routing.estimate(e, preds), 0.05)
    rows = [("gamma", f"start={routing.gamma_from_selectivity(low)}", float(low))]
    rows += [("gamma", f"gamma={g}", r) for g, r in routing.raise_gamma(e, q, preds, truth, M, routing.gamma_from_selectivity(low), 40)]
    plain = cut(exact.prefilter(e, q.withColumn("pred_id", F.lit(0)), [P.always()], TOP))
    stitched = baselines.build_label_graph(e, preds, "stitched", r_small=M, r=2 * M)
    budget = max(sum(I.index_size(stitched).first()), 2 * 4 * 64 * e.count())
    for step, curves in (("grid", routing.grid(e, q, plain, (8, 16), (40, 80))), ("m_beta", routing.choose_m_beta(e, q, preds, truth, M, GAMMA, budget))):
        curves = cut(curves)
        paces = metrics.qps_at_recall(curves, 0.9).collect()
        rows += [(step, r["method"], float(r["qps"])) for r in paces] + [(f"{step} chosen", best[0], float(best[1])) for best in [routing.best_at(curves)] if best]
    return spark.createDataFrame(rows, "step string, setting string, value double")
