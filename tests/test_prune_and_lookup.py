"""Hand-made lists: compression, lookups, pruning rules, search rules."""

import numpy as np

from facetgraph.operators import kernel as K
from facetgraph.operators import prune

A, B, C, D, E, F, G, H = range(8)
LISTS = {A: [], B: [], C: [E, G], D: [F, H], E: [], F: []}


def test_two_hop_stops_when_reached_and_kept_pass_the_cap():
    assert prune.two_hop([A, B, C, D, E, F], LISTS.get, 2, 6) == [A, B, C, D]


def test_two_hop_drops_what_is_reached():
    assert prune.two_hop([A, B, C, D, E, F], LISTS.get, 2, 12) == [A, B, C, D]


def level():
    rows = {8: [A, B, C, D], C: [E, G], D: [F, H]}
    return [np.array(rows.get(v, []), np.int64) for v in range(9)]


PASS = np.array([False, True, True, False, True, True, True, True, True])


def test_compressed_lookup_goes_through_failing_nodes():
    assert K.lookup_compressed(level(), 8, PASS, 10, 2, K.Counters()) == [B, C, E, G, F, H]
    assert K.lookup_compressed(level(), 8, PASS, 3, 2, K.Counters()) == [B, C, E]


def test_filtered_and_two_hop_lookup():
    assert K.lookup_filtered(level(), 8, PASS, 3, K.Counters()) == [B, C]
    assert K.lookup_two_hop(level(), 8, PASS, 3, K.Counters()) == [B, C, E]


def test_blind_rng_loses_what_a_failing_node_covers_and_the_labelled_rule_keeps_it():
    points = np.array([[0.0], [1.0], [1.5]])
    dist = lambda x, kept: ((points[kept] - points[x]) ** 2).sum(1)
    labels = np.array([1, 0, 1])
    assert prune.rng([1, 2], [1.0, 2.25], dist, 2) == [1]
    assert prune.rng_labelled([1, 2], [1.0, 2.25], dist, 2, labels, 1) == [1, 2]


def graph(params, n=120, seed=1):
    rng = np.random.default_rng(seed)
    ids = np.arange(n)
    top = np.where(ids % 8 == 0, 1, 0) + np.where(ids % 64 == 0, 1, 0)
    return K.build(ids, rng.normal(size=(n, 6)), top, params)


def exact(g, q, ok, k, own=None):
    d = ((g.vecs - q) ** 2).sum(1)
    return [int(i) for i in np.lexsort((g.ids, d)) if ok[i] and i != own][:k]


def test_wide_beams_are_exact_on_what_is_reached():
    """Wide lists reach every node; kNN lists of which only the first m are followed need not, so those are held to a recall."""
    g = graph(K.dense(m=8, gamma=10, m_beta=16, n_compressed=0))
    everything = np.ones(len(g.ids), bool)
    hit = [set(exact(g, q, everything, 5)) & {v for _, v in K.search(g, q, 5, 120, everything)[0]} for q in g.vecs]
    assert sum(map(len, hit)) >= 0.9 * 5 * len(hit)
    for params in (K.hnsw(m=8), K.hnsw(m=8, method="insert")):
        g = graph(params)
        everything = np.ones(len(g.ids), bool)
        for q in g.vecs[::17]:
            assert [v for _, v in K.search(g, q, 5, 120, everything)[0]] == exact(g, q, everything, 5)


def test_results_pass_and_come_sorted():
    g = graph(K.dense(m=8, gamma=5, m_beta=8))
    ok = g.ids % 5 == 0
    hits, counters, route = K.search(g, g.vecs[3], 5, 30, ok)
    assert route == "graph" and all(v % 5 == 0 for _, v in hits) and hits == sorted(hits)
    assert counters.n_passed == counters.n_visited


def test_degrees_stay_within_the_cap_and_lookups_within_m():
    for method in ("bulk", "insert"):
        g = graph(K.dense(m=4, gamma=5, m_beta=8, method=method))
        assert max(len(x) for level in g.levels for x in level) <= 20
        ok = np.ones(len(g.ids), bool)
        assert all(len(K.lookup_compressed(g.levels[0], v, ok, 4, 8, K.Counters())) <= 4 for v in range(len(g.ids)))


def test_lean_is_dense_with_gamma_one():
    lean, dense = graph(K.lean(m=6)), graph(K.dense(m=6, gamma=1, m_beta=6, n_compressed=0))
    assert all((a == b).all() for x, y in zip(lean.levels, dense.levels) for a, b in zip(x, y))


def test_empty_predicate_empty_graph_and_k_zero():
    g = graph(K.dense(m=4, gamma=5))
    assert K.search(g, g.vecs[0], 5, 20, np.zeros(len(g.ids), bool))[2] == "empty"
    assert K.search(g, g.vecs[0], 0, 20)[0] == []
    none = K.build(np.empty(0, np.int64), np.empty((0, 3)), np.empty(0, np.int64), K.dense())
    assert K.search(none, np.zeros(3), 3, 5)[0] == []


def test_unreachable_cluster_falls_back_to_the_exact_scan():
    near, far = np.random.default_rng(0).normal(size=(40, 3)), np.random.default_rng(1).normal(size=(5, 3)) + 1000
    g = K.build(np.arange(45), np.concatenate([near, far]), np.zeros(45, np.int64), K.lean(m=3))
    ok = np.arange(45) >= 40
    hits, _, route = K.search(g, np.zeros(3), 5, 10, ok)
    assert route == "fallback" and {v for _, v in hits} == {40, 41, 42, 43, 44}


def test_strong_components():
    lists = {0: [1], 1: [0], 2: [0], 3: []}
    assert K.strong_components(4, lists.get, [0, 1, 2, 3]) == 3
