"""Wide beams on lists that leave parts unlinked; builders in small blocks; joins by blocks."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from facetgraph import registry
from facetgraph.functions import predicates as P
from facetgraph.operators import baselines, blocks, exact, relgraph
from facetgraph.operators import index as I
from facetgraph.operators import kernel as K
from facetgraph.plans.experiments import cut


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.fixture(scope="module")
def islands(spark):
    """Three groups far apart, each larger than a list, so that no list leads out of its group."""
    rng = np.random.default_rng(3)
    vecs = [(i, [float(x) for x in rng.normal(size=6) + 100 * (i % 3)], i % 2) for i in range(90)]
    return cut(spark.createDataFrame(vecs, "id long, vec array<double>, label int"))


LABELS = [P.eq("label", 0), P.eq("label", 1)]


def asked(e):
    # vectors between the groups: the nearest of a query lie in several
    return e.where("id % 5 = 0").select(F.col("id").alias("query_id"), F.transform("vec", lambda x: x * 0.6 + 40).alias("qvec"), (F.col("id") % 2).cast("int").alias("pred_id"))


@pytest.mark.parametrize("params, over", [(K.dense(m=2, gamma=4, m_beta=8, n_compressed=0), None), (K.hnsw(m=2), "double")])
def test_a_wide_beam_crosses_unlinked_groups(islands, params, over):
    want = rows(exact.hybrid_topk(islands, asked(islands), LABELS, 40))
    found = I.search(I.build(islands, params), islands, asked(islands), LABELS, params, 40, islands.count(), over=over, whole=True)
    assert rows(I.topk(found, 40)) == want


def test_a_wide_beam_crosses_unlinked_groups_of_a_partition(islands):
    params = K.hnsw(m=2)
    want = rows(exact.hybrid_topk(islands, asked(islands), LABELS, 40))
    found = baselines.search_partition(baselines.oracle_partition(islands, LABELS, params), asked(islands), params, 40, islands.count(), whole=True)
    assert rows(I.topk(found, 40)) == want


def test_blocks_do_not_change_neighbours():
    rng = np.random.default_rng(5)
    x = np.round(rng.normal(size=(300, 5)), 1)
    x[100:160] = x[0]  # more copies than the spare candidates
    nodes, ids = np.arange(300), rng.permutation(1000)[:300]
    for v, near in enumerate(K.nearest(x, nodes, ids, 20, cells=900)):
        d = K.squares(x, x[v])
        d[v] = np.inf
        assert near.tolist() == np.lexsort((ids, d))[:20].tolist()


def test_what_a_never_full_beam_reaches_is_what_the_walk_reaches():
    rng = np.random.default_rng(7)
    vecs, ids = rng.normal(size=(400, 4)), np.arange(400)
    top = (rng.random(400) < 0.1).astype(int)
    for params in (K.dense(m=3, gamma=4, m_beta=6), K.lean(m=3)):
        g, ok, memo = K.build(ids, vecs, top, params), rng.random(400) < 0.4, {}
        for q in rng.normal(size=(20, 4)):
            got, c, _ = K.search(g, q, 400, 400, ok, memo=memo)
            # one more goal than there are nodes to find keeps the walk itself
            d = Counting(g, q, ok)
            assert [v for _, v in got] == d.ids and (c.n_dist, c.n_visited, c.n_pred_eval, c.n_passed, c.n_hops) == d.counts


class Counting:
    """The walk node by node, as the finite beam does it."""

    def __init__(self, g, q, ok):
        c, p = K.Counters(), g.params
        near = lambda level: (lambda v: K.lookup_two_hop(g.levels[level], v, ok, p.m, c) if p.kind == "lean" else K.lookup_compressed(g.levels[level], v, ok, p.m, p.m_beta, c) if level < p.n_compressed else K.lookup_filtered(g.levels[level], v, ok, p.m, c))
        at = [(float(g.dist(q, [g.entry])[0]), g.entry)]
        c.n_dist += 1
        for level in range(len(g.levels) - 1, 0, -1):
            at = K.search_layer(g, q, at, 1, near(level), ok, c) or at
        found = K.search_layer(g, q, at, 400, near(0), ok, c)
        self.ids = [int(g.ids[v]) for _, v in found]
        self.counts = (c.n_dist, c.n_visited, c.n_pred_eval, c.n_passed, c.n_hops)


@pytest.mark.parametrize("name", ["filtered_degree", "predicate_clustering", "query_correlation_no", "query_correlation_rank", "query_correlation_three_targets"])
def test_pairs_are_met_in_blocks(spark, sf, name):
    assert no_pairs(registry.QUERIES[name](spark, sf))


def no_pairs(df):
    """No pair of vectors is a row of the plan, and no join on one shard holds them all."""
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    return "aggregate(zip_with" not in plan and "Join Cross" not in plan


def test_block_neighbours_are_the_joined_ones(islands):
    want = relgraph.knn_join(*[islands.withColumn("shard", F.lit(0))] * 2, 7).select("src", "pos", "dst")
    for parts in (1, 3):
        tagged = islands.select("id", "vec", F.array().cast("array<int>").alias("tags"))
        got = blocks.meet(tagged, tagged.repartition(5), parts, lambda own: blocks.Nearest(own, 7), "src long, pos int, dst long, dist double")
        assert rows(got.select("src", "pos", "dst")) == rows(want)


def test_weights_of_random_subsets():
    from itertools import combinations

    from facetgraph.plans.metrics import subset_weights

    for n, k, t in ((7, 3, 1), (7, 3, 2), (6, 6, 3), (8, 1, 3), (5, 5, 1)):
        sets = list(combinations(range(n), k))
        want = [sum(i in sorted(x)[:t] for x in sets) / len(sets) for i in range(n)]
        got = subset_weights(n, k, t)
        assert np.allclose(np.append(got, np.zeros(n - len(got))), want)


def test_searches_ask_for_every_fiftieth_row(spark, sf):
    from facetgraph.plans import experiments
    from facetgraph.plans.workloads import WORKLOADS

    e, q, _ = experiments._ready(spark, sf, WORKLOADS["eq12"])
    assert rows(q.select("query_id")) == rows(e.where("id % 50 = 0").select("id"))
    assert q.select("pred_id").distinct().count() == min(12, q.count()) and "caption" not in e.columns
    assert "caption" in experiments._ready(spark, sf, WORKLOADS["regex"])[0].columns


@pytest.mark.parametrize("name", ["cost_model", "distances_at_recall", "pareto_frontier", "qps_at_recall", "recall_at_qps", "support_matrix"])
def test_a_table_is_read(spark, sf, name):
    assert registry.QUERIES[name](spark, sf).inputFiles()


@pytest.mark.parametrize("name", ["dense_exhaustive", "dense_two_levels_exhaustive", "lean_exhaustive"])
def test_a_wide_beam_carries_what_it_reads_and_asks_every_fiftieth_row(spark, monkeypatch, name):
    from facetgraph.plans import experiments
    from facetgraph.plans.workloads import WORKLOADS, entities, searches

    sf, carried = "/root/testdata/sf0.01", []
    monkeypatch.setattr(experiments, "cut", lambda df: carried.append(df.columns) or cut(df))
    found = cut(registry.QUERIES[name](spark, sf))
    w = WORKLOADS["label"]
    e = entities(spark, sf, w)
    truth = cut(exact.prefilter(e, searches(e, w), list(w.predicates), registry.TOP))
    assert carried[0] == ["id", "vec", "label"]
    assert rows(found.select("query_id").distinct()) == rows(e.where("id % 50 = 0").select("id"))
    assert found.join(truth, ["query_id", "id"]).count() >= 0.9 * truth.count()


def test_degrees_of_all_kinds_from_one_search_for_neighbours(spark, sf):
    from facetgraph.plans import experiments
    from facetgraph.sources import tables as T

    for load in (T.entity_vec, T.entity_doc):
        e = cut(load(spark, sf).select("id", "vec"))
        kinds = {"dense": experiments.DENSE, "lean": experiments.LEAN, "hnsw": experiments.HNSW}
        want = [(name, *r) for name, p in kinds.items() for r in rows(I.out_degree(I.build(e, p, shards=3)).select("level", "nodes", "degree", "largest"))]
        got = rows(I.out_degrees(e, kinds, shards=3).select("method", "level", "nodes", "degree", "largest"))
        assert [r[:3] + r[4:] for r in got] == [r[:3] + r[4:] for r in sorted(want)] and np.allclose([r[3] for r in got], [r[3] for r in sorted(want)])


def test_relative_neighbours_by_each_kept_one():
    from facetgraph.operators import prune

    rng = np.random.default_rng(11)
    for most in (1, 4, 16):
        x = np.round(rng.normal(size=(40, 3)), 1)
        far = (x**2).sum(axis=1)
        order = np.lexsort((np.arange(40), far)).tolist()
        pairwise = lambda c, kept: ((x[kept] - x[c]) ** 2).sum(axis=1)
        want = prune.rng_labelled(order, far[order].tolist(), pairwise, most, None, None)
        assert prune.rng(order, far[order].tolist(), pairwise, most) == want
    assert prune.rng([], [], pairwise, 4) == []


def test_text_vectors_are_counted_once_a_word(spark):
    from facetgraph.sources import tables as T

    texts = [(1, "a b\tb\u00a0c  d"), (2, None), (3, " \n "), (1, "b\u000bx\fy"), (4, "\u00e9 \u00e9 z"), (None, "q")]
    df = spark.createDataFrame(texts, "id long, text string")
    token = F.explode(F.filter(F.split("text", r"\s+"), lambda t: t != "")).alias("t")
    cell = F.pmod(F.conv(F.substring(F.md5("t"), 1, 8), 16, 10).cast("long"), F.lit(T.BUCKETS)).cast("int")
    counts = {}
    for i, c, n in df.select("id", token).groupBy("id", cell).count().collect():
        counts.setdefault(i, [0.0] * T.BUCKETS)[c] = float(n)
    want = {i: [x / sum(y * y for y in v) ** 0.5 for x in v] for i, v in counts.items()}
    out = T.text_vector(df, "id", "text")
    assert {r["id"]: list(r["vec"]) for r in out.collect()} == want and None in want and 2 not in want
    assert "transform(" not in out._jdf.queryExecution().optimizedPlan().toString()
