"""Plans on the smallest tables: invariants, edge cases, and oracles in DuckDB."""

import glob
import os

import duckdb
import pytest
from pyspark.sql import functions as F

from facetgraph import registry
from facetgraph.functions import predicates as P
from facetgraph.operators import baselines, exact, ivf
from facetgraph.operators import index as I
from facetgraph.operators import kernel as K
from facetgraph.plans import metrics, routing
from facetgraph.plans.experiments import cut
from facetgraph.plans.workloads import WORKLOADS, queries
from facetgraph.sources import tables as T
from facetgraph.streaming import queries as stream


@pytest.fixture(scope="module")
def entity(spark, sf):
    return cut(T.entity_vec(spark, sf))


@pytest.fixture(scope="module")
def asked(entity):
    return cut(queries(entity, WORKLOADS["label"]))


PREDS = list(WORKLOADS["label"].predicates)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def plain(x):
    return None if x is None or x != x else round(x, 6) if isinstance(x, float) else str(x) if hasattr(x, "year") else x


@pytest.mark.parametrize("name", ["prefilter_eq", "prefilter_mixed", "hybrid_topk_cosine", "selectivity_and", "lookup_filtered", "ann_exhaustive", "oracle_partition_exhaustive", "pareto_frontier", "qps_at_recall", "cost_model", "route_decision", "asof_event", "sliding_windows", "prefilter_kw_neg", "selectivity_lang_next", "query_correlation_neg", "query_correlation_three_targets", "estimate_sample", "rng_kept", "udtf_hybrid_search", "last_results_stream"])
def test_oracle(spark, sf, name):
    con = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM read_parquet('{f}')")
    got = registry.QUERIES[name](spark, sf)
    want = con.sql(registry.ORACLES[name])
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    key = lambda r: tuple(map(str, map(plain, r)))
    assert sorted(key(r[c] for c in columns) for r in got.collect()) == sorted(key(r) for r in want.select(*columns).fetchall())


def test_prefilter_is_the_definition(entity, asked):
    a = exact.prefilter(entity, asked, PREDS).select("query_id", "rank", "id")
    b = exact.hybrid_topk(entity, asked, PREDS).select("query_id", "rank", "id")
    assert rows(a) == rows(b)


def test_shards_and_partitions_do_not_change_the_index(entity):
    params = K.dense(m=4, gamma=5, m_beta=8)
    one = I.build(entity.repartition(7), params).select("id", "lists")
    two = I.build(entity.coalesce(1), params).select("id", "lists")
    assert one.exceptAll(two).count() == 0


def test_sharded_search_reaches_high_recall_and_counts(entity, asked):
    truth = exact.prefilter(entity, asked, PREDS)
    params = K.dense(m=8, gamma=10, m_beta=16)
    found = cut(I.search(I.build(entity, params, shards=3), entity, asked, PREDS, params, 10, 60))
    assert metrics.mean_recall(truth, I.topk(found, 10), 10) > 0.9
    assert I.stats(found).where("n_dist <= 0").count() == 0


def test_order_of_distances(entity, asked):
    """Of the methods at one beam: post-filter computes the most distances, the oracle's graph fewer."""
    hnsw = K.hnsw(m=8)
    dense = K.dense(m=8, gamma=10, m_beta=16)
    mean = lambda f: I.stats(f).agg(F.avg("n_dist")).first()[0]
    post = mean(I.search(I.build(entity, hnsw), entity, asked, PREDS, hnsw, 10, 40, over="K/s"))
    graph = mean(I.search(I.build(entity, dense), entity, asked, PREDS, dense, 10, 40))
    assert graph < post


def test_no_recovery_violations(spark, sf):
    assert {r["builder"]: r["violations"] for r in registry.QUERIES["recovery_violations"](spark, sf).collect()}["bulk"] == 0


def test_routing_threshold(spark):
    q = spark.createDataFrame([(1, 0), (2, 1), (3, 2)], "query_id long, pred_id int")
    s = spark.createDataFrame([(0, 0.05), (1, 0.1), (2, 0.11)], "pred_id int, s_est double")
    assert [r["route"] for r in routing.route(q, s, 10).orderBy("query_id").collect()] == ["prefilter", "prefilter", "graph"]


def test_wrong_estimates_leave_results_valid(spark, entity, asked):
    params = K.dense(m=8, gamma=10, m_beta=16)
    index = cut(I.build(entity, params))
    truth = exact.prefilter(entity, asked, PREDS)
    for s in (0.0, 1.0):
        wrong = spark.createDataFrame([(i, s) for i in range(10)], "pred_id int, s_est double")
        got = routing.routed_search(index, entity, asked, PREDS, params, wrong, 10, 60)
        assert metrics.mean_recall(truth, got, 10) > (0.999 if s == 0 else 0.9)


def test_unsupported_predicates(entity, asked):
    p = [P.regex("caption", "a")]
    with pytest.raises(P.UnsupportedPredicate):
        baselines.label_graph_search(entity, asked, p, "filtered")


def test_inverted_lists_take_any_predicate(entity, asked):
    preds = [P.regex("caption", "a"), P.contains_any("brands", ["Brand#11", "Brand#32"])]
    q = asked.withColumn("pred_id", F.pmod("query_id", F.lit(2)).cast("int"))
    lists, centers = ivf.build(entity.select("id", "vec"), 8)
    assert rows(ivf.search(lists, centers, entity, q, preds, 10, 8).select("query_id", "rank", "id")) == rows(exact.prefilter(entity, q, preds).select("query_id", "rank", "id"))


def test_empty_and_null_cases(spark, entity, asked):
    none = asked.withColumn("pred_id", F.lit(0))
    assert exact.prefilter(entity, none, [P.never()]).count() == 0
    assert exact.prefilter(entity, asked, PREDS, k=0).count() == 0
    few = exact.prefilter(entity, none, [P.in_("id", [1, 2, 3])])
    assert few.groupBy("query_id").count().where("count <> 3").count() == 0
    assert entity.where(P.to_column(P.contains_any("brands", ["Brand#11"])) & F.col("brands").isNull()).count() == 0


def test_stream_equals_batch(spark, sf):
    live = stream.drain(stream.last_results(stream.query_stream(spark, sf)), "last_live")
    still = stream.last_results(T.load(spark, sf, "events"))
    assert rows(live.select("user_id", "event_id")) == rows(still.select("user_id", "event_id"))


def test_index_round_trip(spark, entity, tmp_path):
    index = I.build(entity, K.lean(m=4), shards=2)
    I.save(index, str(tmp_path / "index"))
    assert I.load(spark, str(tmp_path / "index")).count() == entity.count()


def test_index_source_gives_the_edges(spark, entity, tmp_path):
    from facetgraph.sources import index_source

    index = I.build(entity, K.lean(m=4), shards=2)
    I.save(index, str(tmp_path / "index"))
    index_source.register(spark)
    read = spark.read.format("facet_index")
    assert rows(read.load(str(tmp_path / "index"))) == rows(I.edges(index))
    assert rows(read.option("level", "1").load(str(tmp_path / "index"))) == rows(I.edges(index).where("level = 1"))


def test_text_sources(spark, tmp_path):
    (tmp_path / "a.csv").write_text('id,name,vec\n1,"x, y","[1.5,2]"\n2,,\n')
    got = T.load_text(spark, str(tmp_path / "a.csv"), "id long, name string, vec array<double>").collect()
    assert [(r["id"], r["name"], r["vec"]) for r in got] == [(1, "x, y", [1.5, 2.0]), (2, None, None)]
    (tmp_path / "a.json").write_text('{"id": 1, "vec": [1.5, 2]}\nnonsense\n')
    got = T.load_text(spark, str(tmp_path / "a.json"), "id long, vec array<double>", "json").collect()
    assert [(r["id"], r["vec"], r["_bad"]) for r in got] == [(1, [1.5, 2.0], None), (None, None, "nonsense")]
    with pytest.raises(ValueError, match="csv or json"):
        T.load_text(spark, "x", "id long", "xml")


def test_a_stored_index_is_searched_in_place(spark, entity, asked, tmp_path):
    params = K.dense(m=4, gamma=8, m_beta=8)
    stored = I.store(I.build(entity, params, shards=3), str(tmp_path / "stored"), "facet_stored", 3)
    found = I.search(stored, entity, asked, PREDS, params, 10, (20, entity.count()))
    plan = found._jdf.queryExecution().executedPlan().toString()
    sides = plan.split("FlatMapCoGroupsInArrow", 1)[1]
    left = sides.split("Scan parquet", 1)[0] if "Scan parquet" in sides else sides.split("FileScan parquet", 1)[0]
    assert "Exchange" not in left
    plainly = I.search(I.build(entity, params, shards=3), entity, asked, PREDS, params, 10, (20, entity.count()))
    key = ["efs", "query_id", "shard", "id", "n_dist"]
    assert rows(found.select(key).na.fill(-1)) == rows(plainly.select(key).na.fill(-1))


def test_the_widened_walk_is_the_wide_one(entity):
    import numpy as np

    table = I.build(entity, K.hnsw(m=6)).toArrow()
    g = I.graph_of(table, K.hnsw(m=6))
    rng = np.random.default_rng(1)
    for _ in range(10):
        q = rng.normal(size=g.vecs.shape[1])
        ok = np.ones(len(g.ids), bool)
        walk = K.Walk(g, q, K.descend(g, q, K.Counters()), 0, ok, K.Counters())
        walk.widen(5)
        c = K.Counters()
        at = K.descend(g, q, K.Counters())
        assert walk.widen(60) == K.search_layer(g, q, at, 60, lambda v: g.levels[0][v].tolist(), ok, c)
        assert walk.c.n_dist == c.n_dist
