"""Operators against brute force, and on nulls, empty and long texts, repeated rows, empty tables and clashing columns."""

import hashlib
import itertools
import os
import random
import re
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from facetgraph.llm import decontaminate, exchange, labelled, licenses, lm_score, mixing, ngram_join, quality, sharding, substring_dedup, syncmers, toxicity
from facetgraph.llm.graph import components
from facetgraph.llm.textkit import ALNUM, BLANK, Tokens, Words, alnum_words, blank_words, sieve_kernel, sieve_of

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, shard int, h long, label int, leader long, seed long"
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(t):
    return WORD.findall((t or "").translate(LOWER))


def table(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), 1, 2, 3, 4, 5, 6) for i, t, s in rows], SCHEMA)


@pytest.fixture(scope="module")
def edge(spark):
    rng = random.Random(4)
    vocab = [f"w{i}" for i in range(400)]
    base = [" ".join(rng.choice(vocab) for _ in range(n)) for n in (3, 4, 5, 6, 60, 120, 120, 300)]
    near = base[5].split()
    near[50] = "changed"
    long = " ".join(rng.choice(vocab) for _ in range(30_000))
    rows = [(1, None, "a"), (2, "", "a"), (3, " \t\n ", None), (4, "...!!", "b"), (None, base[4], "b"), (5, base[5], "a"), (5, base[5], "a"), (6, base[5], None), (7, " ".join(near), "c"), (8, long, "c"), (9, long + " tail", "c"), (-3, base[7], "b"), (1 << 40, "ÉK naïve " + base[6], "b")]
    rows += [(100 + i, t, "d") for i, t in enumerate(base)]
    return table(spark, rows)


@pytest.fixture(scope="module")
def empty(spark):
    return table(spark, [])


def pairs(df):
    return df.collect()


# --- n-gram join ---


def brute_components(rows, k=5):
    sets = {}
    for i, t in rows:
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w[a : a + k]) for a in range(len(w) - k + 1)} or ({tuple(w)} if w else set())
    up = {i: i for i in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both and 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
            x, y = sorted((root(a), root(b)))
            up[y] = x
    return {i: (len(sets[i]), root(i)) for i in sets}


def random_copies(n, seed):
    rng = random.Random(seed)
    vocab = [f"v{i}" for i in range(60)]
    out = []
    for i in range(n):
        if out and rng.random() < 0.6:
            w = rng.choice(out)[1].split()
            for _ in range(rng.randrange(0, 4)):
                w[rng.randrange(len(w))] = rng.choice(vocab)
        else:
            w = [rng.choice(vocab) for _ in range(rng.choice((2, 5, 8, 30, 60, 90)))]
        out.append((i, " ".join(w)))
    return out


@pytest.mark.parametrize(("block", "heap"), [(1024, 1 << 40), (1024, 0), (4, 2048)])
def test_ngram_join_is_the_brute_force(spark, block, heap):
    rows = random_copies(140, 1)
    got = ngram_join.near_duplicate_components(table(spark, [(i, t, "s") for i, t in rows]), block_rows=block, heap_most=heap)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got.collect()} == brute_components(rows)


def test_ngram_join_edges(edge, empty):
    got = {r["doc_id"]: r for r in ngram_join.near_duplicate_components(edge).collect()}
    assert got[1]["n_shingles"] == 0 and got[1]["component_id"] == 1 and got[4]["component_id"] == 4
    assert got[None]["component_id"] is None
    assert got[6]["component_id"] == 5 and got[9]["component_id"] == 8
    assert ngram_join.near_duplicate_components(edge).count() == edge.count()
    assert ngram_join.near_duplicate_components(empty).count() == 0
    kept = ngram_join.one_of_each(edge)
    # the row without doc_id is a copy of 104
    assert kept.columns == edge.columns and kept.where("doc_id = 5").count() == 1 and kept.where("doc_id is null").count() == 0


def test_one_of_each_is_decided_whatever_the_order(spark):
    texts = {i: f"{i} " + " ".join(f"k{i}x{j}" for j in range(30)) for i in range(6)}
    rows = [(None, texts[0], "a"), (None, texts[0], "b"), (1, texts[1], "a"), (None, texts[1], "a"), (2, texts[2], "a"), (2, texts[3], "a"), (2, texts[3], "a"), (None, "", "a"), (None, None, "a")]
    got = [sorted(map(tuple, ngram_join.one_of_each(table(spark, r).repartition(n)).select("doc_id", "text", "source").collect()), key=str) for r, n in ((rows, 1), (rows[::-1], 3))]
    assert got[0] == got[1]
    assert [r[0] for r in got[0]].count(1) == 1 and [r[0] for r in got[0]].count(2) == 1 and sum(r[1] == texts[0] for r in got[0]) == 1
    assert sum(not r[1] for r in got[0]) == 2


def test_merge_skip_counts_what_reaches_the_threshold():
    rng = random.Random(6)
    for t in (1, 2, 4, 7):
        lists = [sorted(rng.sample(range(40), rng.randrange(1, 25))) for _ in range(9)]
        every = Counter(x for q in lists for x in q)
        want = {x: c for x, c in every.items() if c >= t}
        assert ngram_join.merge_skip(lists, t) == want == ngram_join.at_least([np.asarray(q) for q in lists], t, 0)


def test_signatures_never_part_a_link():
    rng = np.random.default_rng(2)
    sets = [rng.integers(0, 1 << 63, rng.integers(1, 200), dtype=np.int64).astype(np.uint64) for _ in range(40)]
    sets += [np.append(x[: len(x) * 9 // 10 + 1], rng.integers(0, 1 << 63, len(x) // 12, dtype=np.int64).astype(np.uint64)) for x in sets]
    sets = sorted((np.unique(x) for x in sets), key=len)
    n = np.array(list(map(len, sets)))
    sigs = ngram_join.signatures(np.concatenate(sets), np.repeat(np.arange(len(sets)), n), n)
    for num, den in ((80, 100), (30, 100)):
        roots = ngram_join.near_by_signature(n, sigs, num, den).roots()
        for a, b in itertools.combinations(range(len(sets)), 2):
            both = len(np.intersect1d(sets[a], sets[b]))
            if both and den * both >= num * (n[a] + n[b] - both):
                assert roots[a] == roots[b]


def test_components_of_a_long_path(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(200)] + [(500, 501)], "a long, b long")
    got = {r["node"]: r["component"] for r in components(e).collect()}
    assert got == {i: 0 for i in range(201)} | {500: 500, 501: 500}


def test_sieve_keeps_every_key(spark):
    keys = spark.range(0, 5000, 7)
    got = {r["id"] for r in spark.range(0, 5000).mapInArrow(sieve_kernel(sieve_of(keys, "id"), "id"), "id long").collect()}
    assert set(range(0, 5000, 7)) <= got and len(got) < 1000


# --- decontamination ---


def test_decontamination_is_the_brute_force(spark, edge):
    rng = random.Random(2)
    vocab = [f"t{i}" for i in range(50)]
    items = [(i, " ".join(rng.choice(vocab) for _ in range(n))) for i, n in enumerate((20, 40, 13, 5, 1))] + [(9, None), (8, "")]
    docs = []
    for i in range(60):
        w = [rng.choice(vocab) for _ in range(rng.randrange(0, 120))]
        if i % 3 == 0:
            piece = items[i % 4][1].upper().split()[: rng.randrange(3, 41)]
            w[len(w) // 2 : len(w) // 2] = piece
        docs.append((i, (", " if i % 2 else " ").join(w)))
    windows = {}
    for i, t in items:
        x = words(t)
        for a in range(max(1, len(x) - 12) if x else 0):
            windows.setdefault(tuple(x[a : a + 13]), set()).add(i)
    bench = spark.createDataFrame(items, "item_id long, text string")
    for size in (16 << 20, 200):  # one slice, several slices
        index = decontaminate.build_index(table(spark, [(i, t, "s") for i, t in docs]))
        got = {r["doc_id"]: r for r in decontaminate.document_hits(index, bench, slice_bytes=size).collect()}
        bad = {i for i, r in got.items() if r["n_hit"] and 20 * r["n_hit"] >= r["n_words"]}
        assert bad and {r["doc_id"] for r in decontaminate.clean(table(spark, [(i, t, "s") for i, t in docs]), bench, slice_bytes=size).collect()} == set(got) - bad
        for i, t in docs:
            x, hit, found = words(t), set(), set()
            for w, who in windows.items():
                for a in range(len(x) - len(w) + 1):
                    if tuple(x[a : a + len(w)]) == w:
                        hit.update(range(a, a + len(w)))
                        found |= who
            assert (got[i]["n_words"], got[i]["n_hit"], got[i]["items"]) == (len(x), len(hit), sorted(found))
            assert sum(s["b"] - s["a"] for s in got[i]["spans"]) == len(hit)


def test_decontamination_query_is_the_brute_force(spark, tmp_path):
    rng = random.Random(21)
    fresh = lambda n: [f"t{rng.randrange(60)}" for _ in range(n)]
    items = [(i, " ".join(fresh(n))) for i, n in ((11, 30), (2, 14), (30, 13), (4, 6), (None, 20))] + [(5, None), (6, "")]
    docs = [(i, " ".join(fresh(20) + items[i % 5][1].split()[: rng.randrange(5, 31)] + fresh(rng.randrange(400)))) for i in range(50)] + [(60, None), (61, ""), (7, "t1"), (None, items[0][1])]
    table(spark, [(i, t, "s") for i, t in docs]).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    want = []
    for i, t in docs:
        x, hit, found = words(t), set(), set()
        for item, b in items:
            y = words(b)
            for a in range(max(1, len(y) - 12) if y else 0):
                w = y[a : a + 13]
                for p in range(len(x) - len(w) + 1):
                    if x[p : p + len(w)] == w:
                        hit.update(range(p, p + len(w)))
                        found |= {item} - {None}
        want.append((i, len(x), len(hit), len(found), hashlib.sha256(",".join(sorted(map(str, found))).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(x)))
    got = [tuple(r) for r in decontaminate.op8_decontaminate(spark, str(tmp_path)).select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated").collect()]
    assert sorted(got, key=str) == sorted(want, key=str) and any(w[-1] for w in want) and not all(w[-1] for w in want)


def test_decontamination_edges(spark, edge, empty):
    bench = spark.createDataFrame([(1, "w1 w2")], "item_id long, text string")
    assert decontaminate.document_hits(decontaminate.build_index(edge), bench).count() == edge.count()
    assert decontaminate.clean(empty, bench).count() == 0 and decontaminate.clean(edge, bench).columns == edge.columns
    assert decontaminate.clean(edge, bench.where("false")).count() == edge.count()


def test_clean_tells_rows_of_one_id_apart(spark):
    docs = table(spark, [(1, "a b c", "s"), (1, "x y z", "s"), (None, "a b c", "s"), (None, "q", "s"), (2, None, "s"), (1, "a b c", "s")])
    bench = spark.createDataFrame([(1, "A b, C")], "item_id long, text string")
    assert sorted((str(r["doc_id"]), str(r["text"])) for r in decontaminate.clean(docs, bench).collect()) == [("1", "x y z"), ("2", "None"), ("None", "q")]


def test_phrase_and_proximity_search(spark):
    rows = [(1, "the red fox and the dog"), (2, "red the fox"), (3, "the red fox the red fox"), (1, "the red fox and the dog"), (4, "the red"), (5, "fox"), (6, None), (7, "red a b c d the e f fox")]
    index = decontaminate.build_index(table(spark, [(i, t, "s") for i, t in rows]))
    ask = spark.createDataFrame([(7, ["the", "red", "fox"]), (8, ["fox", "the"]), (9, [])], "query_id long, words array<string>")
    got = sorted(map(tuple, decontaminate.search(index, ask).collect()))
    assert got == [(7, 1, 0), (7, 3, 0), (7, 3, 3), (8, 3, 2)]
    near = {(r["query_id"], r["doc_id"]) for r in decontaminate.search(index, ask, 2).collect()}
    assert near == {(7, 1), (7, 2), (7, 3), (8, 1), (8, 2), (8, 3)}


# --- mixing ---


def test_mix_comes_near_its_targets(edge, empty):
    got = mixing.with_times(edge)
    rows = got.select("source", "__size", "__source_size", "__target", "__times").collect()
    total = sum(r["__size"] for r in rows)
    targets = {r["source"]: r["__target"] for r in rows}
    assert sum(targets.values()) == pytest.approx(1.5 * total)
    for s in targets:
        mine = [r for r in rows if r["source"] == s]
        taken = sum(r["__size"] * r["__times"] for r in mine)
        assert abs(taken - targets[s]) <= max(r["__size"] for r in mine) and targets[s] <= 2 * mine[0]["__source_size"]
    assert max(r["__times"] for r in rows) <= 2
    assert mixing.mix(edge).columns == edge.columns
    assert mixing.with_times(empty).count() == 0


def test_mix_is_its_sql(spark, sf):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{sf}/documents.parquet')")
    want = sorted(con.sql(f"SELECT doc_id, size, source_size, target, taken FROM ({mixing.OP2_SQL})").fetchall())
    assert sorted(tuple(r) for r in mixing.op2_mix_sources(spark, sf).select("doc_id", "size", "source_size", "target", "taken").collect()) == want


def test_mix_of_very_many_sources_is_the_mix_of_few(edge, monkeypatch):
    key = ["doc_id", "text", "source", "__size", "__target", "__times"]
    want = sorted(map(str, mixing.with_times(edge).select(key).collect()))
    monkeypatch.setattr(mixing, "BROADCAST_SOURCES", 0)
    assert sorted(map(str, mixing.with_times(edge).select(key).collect())) == want


# --- sharding ---


def test_hypergeometric_has_its_mean_and_bounds():
    rng = random.Random(1)
    draws = [sharding.hypergeometric(rng, 30, 70, 20) for _ in range(4000)]
    assert min(draws) >= 0 and max(draws) <= 20
    assert np.mean(draws) == pytest.approx(6, abs=0.1) and np.var(draws) == pytest.approx(20 * 0.3 * 0.7 * 80 / 99, rel=0.1)
    big = [sharding.hypergeometric(rng, 10**9, 3 * 10**9, 10**6) for _ in range(20)]
    assert np.mean(big) == pytest.approx(250_000, abs=1500)


def test_matrix_uses_up_rows_and_fills_shards():
    rows = [5, 0, 17, 40, 3]
    m = sharding.communication_matrix(rows, 4, 9)
    assert [sum(r) for r in m] == rows
    sizes = [sum(c) for c in zip(*m)]
    assert max(sizes) - min(sizes) <= 1


def test_shards_are_equal_and_slots_gapless(edge, empty):
    got = sharding.shard_rows(edge, shards=4).collect()
    by = {s: sorted(r["__slot"] for r in got if r["__shard"] == s) for s in range(4)}
    assert sum(map(len, by.values())) == edge.count() and max(map(len, by.values())) - min(map(len, by.values())) <= 1
    assert all(v == list(range(len(v))) for v in by.values())
    assert sharding.shard_rows(empty, shards=4).count() == 0


def test_sharding_query_is_its_contract(spark, tmp_path):
    import zlib

    rows = [(i, f"text {i % 7} é" if i % 5 else None, "s") for i in range(500)] + [(None, "same", "s")] * 300 + [(9, "same", "s")] * 200
    table(spark, rows).repartition(7).write.parquet(f"{tmp_path}/documents.parquet")
    runs_ = [sorted((tuple(r) for r in sharding.op3_shard_documents(spark, str(tmp_path)).collect()), key=str) for _ in range(2)]
    assert runs_[0] == runs_[1]
    raw = lambda t: (t or "").encode()
    assert sorted((str(r[0]), r[1], r[2]) for r in runs_[0]) == sorted((str(i), len(raw(t)) + 8, zlib.crc32(raw(t))) for i, t, _ in rows)
    by = {}
    for _, _, _, law, shard, slot, grown in runs_[0]:
        assert law == "rows" and grown is None
        by.setdefault(shard, []).append(slot)
    assert set(by) == set(range(24)) and all(sorted(x) == list(range(len(x))) for x in by.values()) and {len(x) for x in by.values()} <= {41, 42}


def test_sharding_is_uniform_and_buckets_keep_slots_gapless(spark):
    docs = spark.range(0, 6000, 1, 5).select(F.col("id").alias("doc_id"), F.lit("").alias("text"))
    got = sharding.shard_rows(docs, 6, cell_rows=50).collect()
    for s in range(6):
        mine = [r for r in got if r["__shard"] == s]
        assert sorted(r["__slot"] for r in mine) == list(range(1000))
        # from each fifth of the ids about a fifth, and slots that tell nothing of ids
        share = Counter(r["doc_id"] // 1200 for r in mine)
        assert all(140 < c < 260 for c in share.values())
        assert abs(np.corrcoef([r["doc_id"] for r in mine], [r["__slot"] for r in mine])[0, 1]) < 0.15


# --- classifiers ---


def test_factorization_machine_learns_a_pair_that_no_weight_can():
    rng = np.random.default_rng(0)
    docs, y = [], []
    for _ in range(1500):
        a, b = rng.integers(0, 2, 2)
        docs.append(np.array([10] * a + [20] * b + [30, int(rng.integers(40, 60))], np.int32))
        y.append(int(a == b))
    y = np.array(y, float)
    m = toxicity.fit(docs[:1000], y[:1000])
    doc = np.repeat(np.arange(500), [len(d) for d in docs[1000:]])
    z = m.logits(doc, np.concatenate(docs[1000:]), 500)
    assert ((z > 0) == (y[1000:] == 1)).mean() > 0.95


def test_factorization_machine_learns_a_pair_amid_many_terms():
    """Neither term of the pair tells anything alone, and 20,000 background terms are frequent enough to be kept."""
    rng = np.random.default_rng(1)
    docs, y = [], []
    for _ in range(4000):
        a, b = rng.integers(0, 2, 2)
        docs.append(np.unique(np.concatenate([[10] * a, [20] * b, 1000 + rng.integers(0, 20_000, 30)])).astype(np.int32))
        y.append(int(a == b))
    y = np.array(y, float)
    terms, scale = toxicity.term_scales(docs[:3000], y[:3000])
    assert len(terms) > 10_000 and {10, 20} <= set(terms.tolist())
    m = toxicity.fit(docs[:3000], y[:3000], 30)
    held = docs[3000:]
    z = m.logits(np.repeat(np.arange(len(held)), [len(d) for d in held]), np.concatenate(held), len(held))
    assert ((z > 0) == (y[3000:] == 1)).mean() > 0.9


def test_a_repeated_document_is_sampled_once(spark):
    docs = table(spark, [(1, t, "s") for t in ("b", "a", "a")] + [(2, None, "s"), (3, "c", "s")])
    sample = spark.createDataFrame([(1, 1), (2, 0)], "doc_id long, label int")
    assert sorted(map(tuple, labelled.texts_of(docs, sample).select("doc_id", "label", "text").collect())) == [(1, 1, "a"), (2, 0, None)]


def test_machine_formula():
    m = toxicity.Machine(np.array([0, 1, 2] + [-1] * (toxicity.BUCKETS - 3)), 0.5, np.array([1.0, 2.0, 3.0]), np.array([[1.0, 0.0], [2.0, 1.0], [0.0, 4.0]]))
    assert m.logits(np.array([0, 0, 0]), np.array([0, 1, 2]), 1)[0] == pytest.approx(0.5 + 6 + (1 * 2) + 0 + 1 * 4)


def test_toxicity_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.1"
    got = toxicity.op4_toxicity(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").select("toxic", "predicted").collect()
    c = Counter((r["toxic"], r["predicted"]) for r in got)
    assert c[1, 1] / (c[1, 1] + c[1, 0]) > 0.8 and c[0, 1] / (c[0, 1] + c[0, 0]) < 0.01


def test_quality_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.1"
    got = quality.op6_quality(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").select("quality", "predicted").collect()
    c = Counter((r["quality"], r["predicted"]) for r in got)
    assert c[1, 1] / (c[1, 1] + c[1, 0]) > 0.98 and c[0, 0] / (c[0, 0] + c[0, 1]) > 0.9


def test_toxicity_is_fitted_away_from_the_driver(spark, sf, monkeypatch):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    sample = labelled.sample_ids(labelled.training_labels(labels, "toxic", toxicity.FOLDS, toxicity.HELD_OUT))
    rows = labelled.texts_of(docs, sample).collect()
    terms = sorted((r["label"], toxicity.term_pairs([(r["text"] or "").encode()])[1].astype(np.int32).tobytes()) for r in rows)
    plain = toxicity.fit([np.frombuffer(t, np.int32) for _, t in terms], np.array([float(y) for y, _ in terms]))
    here, real = os.getpid(), toxicity.fit

    def elsewhere(*args):
        assert os.getpid() != here
        return real(*args)

    monkeypatch.setattr(toxicity, "fit", elsewhere)
    m = toxicity.train(docs, labels)
    assert (m.place == plain.place).all() and m.bias == plain.bias and (m.weights == plain.weights).all() and (m.factors == plain.factors).all()


def test_class_prior_is_found():
    rng = np.random.default_rng(3)
    p = rng.normal(2, 1, 4000)
    u = np.concatenate([rng.normal(2, 1, 2800), rng.normal(-3, 1, 1200)])
    assert quality.class_prior(p, u) == pytest.approx(0.7, abs=0.06)


def test_classifier_edges(spark, edge, empty):
    labels = spark.createDataFrame([(5, 1, 1), (5, None, 0), (7, 0, 0), (8, 0, 1), (None, 1, 1)], "doc_id long, toxic int, quality int")
    m = toxicity.train(edge, labels)
    scored = toxicity.score_toxicity(edge, m).select("__toxicity").collect()
    assert len(scored) == edge.count() and all(0 <= r[0] <= 1 for r in scored)
    assert toxicity.without_toxic(edge, m).columns == edge.columns and toxicity.without_toxic(empty, m).count() == 0
    assert toxicity.train(edge, labels.where("false")).bias < 0
    q = quality.train(edge, labels)
    assert all(0 <= r[0] <= 1 for r in edge.select(quality.score_udf(q)).collect())
    assert np.allclose(quality.train(empty, labels.where("false")).scores(np.zeros((1, quality.WIDTH))), 0.5)
    assert empty.select(quality.score_udf(q)).count() == 0 and toxicity.score_toxicity(empty, m).count() == 0
    assert labelled.training_labels(labels, "toxic", 3, 5).count() == 3


# --- fingerprints ---


def test_syncmers_are_context_free_and_cover(spark):
    rng = random.Random(5)
    w = [f"x{rng.randrange(200)}" for _ in range(400)]
    docs = table(spark, [(1, " ".join(w), "s"), (2, " ".join(["new"] * 7 + w[100:300]), "s"), (3, "one two", "s"), (4, None, "s")])
    found = {}
    for r in syncmers.anchors(docs).collect():
        found.setdefault(r["doc_id"], {})[r["at"]] = r["hash"]
    inside = {a - 100: h for a, h in found[1].items() if 100 <= a <= 300 - syncmers.K}
    assert inside == {a - 7: h for a, h in found[2].items() if a >= 7}
    assert 0.3 < len(found[1]) / 395 < 0.5 and len(found[3]) == 1 and 4 not in found
    best = syncmers.positional_matches(syncmers.anchors(docs.where("doc_id = 2")), syncmers.anchors(docs)).orderBy(F.desc("matches")).first()
    assert (best["other_id"], best["shift"]) == (1, 93)


def test_fingerprints_edited_texts_and_likeness(spark, tmp_path):
    rng = random.Random(6)
    texts = {i: (" ".join(f"y{rng.randrange(300)}" for _ in range(rng.randrange(1, 200))) if i % 5 else None) for i in range(0, 60, 3)}
    texts[60] = texts[57]
    table(spark, [(i, t, "s") for i, t in texts.items()]).write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["doc_id"]: r for r in syncmers.op5_syncmer_fingerprints(spark, str(tmp_path)).collect()}
    ids = sorted(texts)
    for i, j in zip(ids, ids[1:] + ids[:1]):
        a, b = texts[i] or "", texts[j] or ""
        half = len(a) // 2
        assert got[i]["n_chars"] == len(a)
        assert got[i]["edited_sha256"] == hashlib.sha256((a[: len(a) - half] + b[:half]).encode()).hexdigest()
        assert 0 <= got[i]["near_edited"] <= 1
    assert got[57]["fingerprint"] == got[60]["fingerprint"] and got[57]["near_next"] == 1


def chained_hash(values):
    """Spark's xxhash64 of several longs."""
    import xxhash

    seed = 42
    for v in values:
        seed = xxhash.xxh64_intdigest((v & (1 << 64) - 1).to_bytes(8, "little"), seed=seed)
    return seed


def brute_fingerprint(text):
    import xxhash

    h = [xxhash.xxh64_intdigest(w, seed=42) for w in re.split(rb"[ \t-\r]+", text.encode()) if w]
    inner = [chained_hash(h[i : i + syncmers.S]) for i in range(len(h) - syncmers.S + 1)]
    signed_ = lambda x: x - (1 << 64) if x >> 63 else x
    anchors = []
    for i in range(len(h) - syncmers.K + 1):
        own = list(map(signed_, inner[i : i + syncmers.K - syncmers.S + 1]))
        if min(own) in (own[0], own[-1]):
            anchors.append(chained_hash(h[i : i + syncmers.K]))
    if h and len(h) < syncmers.K:
        anchors = [chained_hash(h)]
    return sorted({a >> 32 for a in anchors})[: syncmers.KEEP]


def test_fingerprints_are_the_brute_force_also_on_odd_rows(spark, edge, tmp_path):
    edge.write.parquet(f"{tmp_path}/documents.parquet")
    got = syncmers.op5_syncmer_fingerprints(spark, str(tmp_path)).collect()
    rows = [(r["doc_id"], r["text"] or "") for r in edge.collect()]
    assert sorted(str(r["doc_id"]) for r in got) == sorted(str(i) for i, _ in rows)
    prints = lambda t: "".join(f"{x:08x}" for x in brute_fingerprint(t))
    assert Counter((str(r["doc_id"]), r["n_chars"], r["fingerprint"]) for r in got) == Counter((str(i), len(t), prints(t)) for i, t in rows)
    by_id = {i: t for i, t in rows if i is not None}
    ids = sorted(by_id)
    for r in got:
        if r["doc_id"] in (7, 8, 100, 104):
            a, b = by_id[r["doc_id"]], by_id[ids[ids.index(r["doc_id"]) + 1]]
            half = len(a) // 2
            mine, changed, following = brute_fingerprint(a), brute_fingerprint(a[: len(a) - half] + b[:half]), brute_fingerprint(b)
            assert r["edited_fingerprint"] == "".join(f"{x:08x}" for x in changed)
            for name, other in (("near_edited", changed), ("near_next", following)):
                union = sorted(set(mine) | set(other))[: syncmers.KEEP]
                assert r[name] == pytest.approx(len(set(mine) & set(other) & set(union)) / len(union))


def test_successors_of_very_many_rows_of_one_id(spark, monkeypatch):
    rng = random.Random(7)
    rows = [(None, f"n{rng.randrange(10**9)}", "s") for _ in range(300)] + [(5, f"m{rng.randrange(10**9)}", "s") for _ in range(200)] + [(i, f"t{i}", "s") for i in (*range(-3, 5), *range(6, 80))] + [(5, "same", "s")] * 3
    docs = table(spark, rows)
    find = lambda: sorted(map(str, syncmers.with_next(docs, ["text"]).select("doc_id", "text", "next_text").collect()))
    want = find()
    monkeypatch.setattr(syncmers, "RANGE_ROWS", 10)
    assert find() == want and len(want) == len(rows)


def test_fingerprint_of_one_and_of_no_document(spark, tmp_path):
    table(spark, [(5, "a b c d e f g h", "s")]).write.parquet(f"{tmp_path}/one/documents.parquet")
    assert syncmers.op5_syncmer_fingerprints(spark, f"{tmp_path}/one").first()["near_next"] == 1
    table(spark, []).write.parquet(f"{tmp_path}/none/documents.parquet")
    assert syncmers.op5_syncmer_fingerprints(spark, f"{tmp_path}/none").count() == 0


# --- licences ---


def test_license_scan_is_the_brute_force(spark, edge):
    texts = {1: "Licensed under the MIT License.", 2: "x mit\nlicense, GNU General Public License version 3; apache license", 3: "Redistribution and use in source and binary forms, with or without modification, are permitted", 4: None, 5: "the licence of mit", 6: "Licensed under CC BY-NC 4.0.", 7: "mit licenſe and K"}
    got = {r["doc_id"]: r for r in licenses.scan(table(spark, [(i, t, "s") for i, t in texts.items()])).collect()}
    for i, t in texts.items():
        x, places = words(t), []
        for phrase, label in licenses.BASE:
            p = phrase.split()
            places += [(a, label) for a in range(len(x) - len(p) + 1) if x[a : a + len(p)] == p]
        assert (got[i]["n_words"], got[i]["n_base"], got[i]["base_labels"]) == (len(x), len(places), ",".join(sorted({b for _, b in places})))
        assert got[i]["first_word"] == min((a for a, _ in places), default=None) and got[i]["last_word"] == max((a for a, _ in places), default=None)
    assert got[3]["labels"] == "bsd" and got[3]["score"] == 1 and got[6]["labels"] == "cc-by-nc" and got[2]["labels"] == "apache,gpl,mit"
    assert licenses.scan(edge).count() == edge.count()


def test_license_scan_finds_every_template_of_a_file_with_several(spark):
    texts = {1: " x ".join(t for _, t, _ in licenses.TEMPLATES), 2: "All rights reserved. Redistribution and use in source and binary forms, with or without modification, are permitted"}
    texts |= {i: "all rights reserved" for i in range(10, 30)}
    got = {r["doc_id"]: r for r in licenses.scan(table(spark, [(i, t, "s") for i, t in texts.items()])).collect()}
    assert set(got[1]["labels"].split(",")) == {label for label, _, _ in licenses.TEMPLATES} | {label for _, label in licenses.BASE}
    assert got[2]["labels"] == "bsd,proprietary"


def test_license_templates_from_a_table(spark):
    table_ = spark.createDataFrame([("house", "Granted under the House License, v2", "house license"), ("house", "Granted under the House License, v2", "house license")], "label string, template string, key string")
    got = {r["doc_id"]: r for r in licenses.scan(table(spark, [(1, "granted under the HOUSE license v2", "s"), (2, "mit license", "s"), (3, None, "s")]), licenses.templates_of(table_)).collect()}
    assert (got[1]["labels"], got[1]["score"], got[2]["labels"], got[3]["labels"]) == ("house", 1.0, "mit", "")
    with pytest.raises(ValueError, match="key phrase"):
        licenses.templates_of(spark.createDataFrame([("x", "a b", "c")], "label string, template string, key string"))
    assert licenses.scan(table(spark, [])).count() == 0


# --- shared passages ---


def test_chaining_is_the_quadratic_recurrence():
    rng = random.Random(8)
    for _ in range(30):
        segs = sorted({(rng.randrange(200), rng.randrange(200), rng.randrange(8, 20)) for _ in range(12)})
        best = {}
        for i, (p, o, z) in enumerate(segs):
            best[i] = z + max([0.0] + [best[j] - 0.1 * (p - segs[j][0] - segs[j][2] + o - segs[j][1] - segs[j][2]) for j in range(i) if segs[j][0] + segs[j][2] <= p and segs[j][1] + segs[j][2] <= o])
        chain = substring_dedup.chains_of(segs, 0.1, 10_000)[0]
        score = sum(segs[i][2] for i in chain) - 0.1 * sum(segs[b][0] - segs[a][0] - segs[a][2] + segs[b][1] - segs[a][1] - segs[a][2] for a, b in zip(chain, chain[1:]))
        assert score == pytest.approx(max(best.values()))


def test_chaining_is_optimal_under_its_gap():
    assert substring_dedup.chains_of([(0, 0, 500), (510, 900, 30), (545, 941, 30)], 0.1, 40)[0] == [0] and [1, 2] in substring_dedup.chains_of([(0, 0, 500), (510, 900, 30), (545, 941, 30)], 0.1, 40)
    rng = random.Random(18)
    for _ in range(200):
        segs = sorted({(rng.randrange(150), rng.randrange(150), rng.randrange(4, 14)) for _ in range(14)})
        best = {}
        for i, (p, o, z) in enumerate(segs):
            gaps = [(j, p - segs[j][0] - segs[j][2], o - segs[j][1] - segs[j][2]) for j in range(i)]
            best[i] = z + max([0.0] + [best[j] - 0.05 * (a + b) for j, a, b in gaps if 0 <= a <= 20 and 0 <= b <= 20])
        chain = substring_dedup.chains_of(segs, 0.05, 20)[0]
        score = sum(segs[i][2] for i in chain) - 0.05 * sum(segs[b][0] - segs[a][0] - segs[a][2] + segs[b][1] - segs[a][1] - segs[a][2] for a, b in zip(chain, chain[1:]))
        assert score == pytest.approx(max(best.values()))


def test_seeds_are_the_least_of_their_windows():
    rng = np.random.default_rng(4)
    lens = np.array([0, 3, 9, 10, 11, 60, 1, 200])
    h = rng.integers(0, 1 << 63, lens.sum(), dtype=np.int64).astype(np.uint64)
    h[40:50] = h[40]
    d = np.repeat(np.arange(len(lens)), lens)
    for w in (1, 4, 10, 26):
        want = np.zeros(len(h), bool)
        for a, n in zip(np.cumsum(lens) - lens, lens):
            for i in range(max(1, n - w + 1) if n else 0):
                window = (h[a + i : a + min(n, i + w)] >> np.uint64(24)).tolist()
                want[a + i + len(window) - 1 - window[::-1].index(min(window))] = True
        assert (substring_dedup.minimizers(h, d, lens, w) == want).all()


def test_recall_of_edited_passages(spark):
    """Passages of 60 to 300 words with changed, dropped and added words, against the passages that were planted."""
    rng = random.Random(31)
    fresh = lambda n: [f"z{rng.randrange(6000)}" for _ in range(n)]
    docs, planted = [], {}
    for kind, share in enumerate((0.05, 0.1, 0.125, 0.15)):
        for size in (60, 100, 300):
            for _ in range(10):
                a, passage = len(docs), fresh(size)
                edited = []
                for j, w in enumerate(passage):
                    # every eighth word for the third kind, else at random, a tenth of them dropped and a tenth added
                    hit = j % 8 == 3 if kind == 2 else rng.random() < share
                    edited += [w] if not hit else fresh(1) if kind == 2 or (r := rng.random()) < 0.8 else [] if r < 0.9 else [w, *fresh(1)]
                planted[a + 1, a] = (kind, size)
                docs += [(a, fresh(rng.randrange(50)) + passage + fresh(40)), (a + 1, fresh(rng.randrange(90)) + edited + fresh(10))]
    got = {}
    for r in substring_dedup.shared_passages(table(spark, [(i, " ".join(w), "s") for i, w in docs])).collect():
        got[r["doc_id"], r["other_id"]] = max(got.get((r["doc_id"], r["other_id"]), 0), r["end_word"] - r["start_word"])
    assert set(got) <= set(planted)
    found = Counter((kind, size) for pair, (kind, size) in planted.items() if got.get(pair, 0) >= 0.8 * size - 5)
    total = Counter(planted.values())
    assert all(found[x] == total[x] for x in total if x[1] == 300)
    assert sum(found.values()) / sum(total.values()) > 0.9, found


def test_passage_whose_halves_stand_elsewhere(spark):
    rng = random.Random(41)
    fresh = lambda n: [f"z{rng.randrange(6000)}" for _ in range(n)]
    p = fresh(80)
    docs = {1: p[:40], 8: p[:40], 2: p[40:], 9: p[40:], 3: p, 4: p}
    got = substring_dedup.shared_passages(table(spark, [(i, " ".join(fresh(30) + x + fresh(30)), "s") for i, x in docs.items()])).collect()
    assert [(r["doc_id"], r["other_id"], r["start_word"], r["end_word"]) for r in got if r["end_word"] - r["start_word"] >= 80] == [(4, 3, 30, 110)]


def test_planted_passages_are_found_and_clean_documents_are_not(spark):
    rng = random.Random(9)
    fresh = lambda n: [f"z{rng.randrange(5000)}" for _ in range(n)]
    passage = fresh(80)
    edited = list(passage)
    edited[20] = "other"
    del edited[50]
    docs = [(i, " ".join(fresh(200)), "s") for i in range(20)]
    docs += [(100, " ".join(fresh(40) + passage + fresh(30)), "s"), (101, " ".join(fresh(10) + passage + fresh(90)), "s"), (102, " ".join(fresh(70) + edited), "s")]
    got = {(r["doc_id"], r["other_id"]): r for r in substring_dedup.shared_passages(table(spark, docs)).collect()}
    assert {x for pair in got for x in pair} == {100, 101, 102}
    one, two = got[101, 100], got[102, 100]
    assert (one["start_word"], one["end_word"], one["other_start"], one["identity"]) == (10, 90, 40, 1.0)
    assert two["start_word"] == 70 and two["end_word"] == 149 and 0.9 < two["identity"] < 1


def test_passage_of_lines_that_other_documents_lead(spark):
    rng = random.Random(3)
    fresh = lambda n: [f"z{rng.randrange(5000)}" for _ in range(n)]
    lines = [fresh(20) for _ in range(3)]
    docs = [(i, " ".join(fresh(30) + lines[i % 3] + fresh(30)), "s") for i in [*range(150), *range(1000, 1150)]]
    docs += [(i, " ".join(fresh(25 + i % 7) + lines[0] + lines[1] + lines[2] + fresh(40)), "s") for i in (500, 600)]
    got = {(r["doc_id"], r["other_id"]): r for r in substring_dedup.shared_passages(table(spark, docs)).collect()}
    assert set(got) == {(600, 500)}
    r = got[600, 500]
    assert (r["start_word"], r["end_word"], r["other_start"], r["identity"]) == (30, 90, 28, 1.0)


def test_edited_passage_whose_seeds_other_documents_lead(spark, monkeypatch):
    rng = random.Random(17)
    fresh = lambda n: [f"z{rng.randrange(6000)}" for _ in range(n)]
    p = fresh(240)
    edited = [fresh(1)[0] if i % 24 == 11 else w for i, w in enumerate(p)]
    # every run of ten words of the passage stands in a smaller and in a greater document, of which none has more than twenty of them
    docs = [(k * 1000 + i, fresh(30) + p[i * 10 : i * 10 + 20] + fresh(30)) for k in (0, 2) for i in range(24)]
    docs += [(1000 + i, fresh(20 + i) + x + fresh(30)) for i, x in enumerate((p, edited, p, edited))]
    docs += [(1010, docs[-1][1])]
    for most in (1 << 20, 50):
        monkeypatch.setattr(substring_dedup, "MATCHES", most)
        got = {(r["doc_id"], r["other_id"]): r["end_word"] - r["start_word"] for r in substring_dedup.shared_passages(table(spark, [(i, " ".join(w), "s") for i, w in docs])).collect()}
        assert {(b, a) for b in range(1000, 1004) for a in range(1000, b)} <= set(got)
        assert {x for pair in got for x in pair} == {*range(1000, 1004), 1010}
        assert all(got[b, a] >= 230 for b, a in got if b < 1010)


def test_pairs_are_chained_wherever_a_chain_can_be():
    rng = np.random.default_rng(8)
    pair = np.sort(rng.integers(0, 300, 900))
    at, other = rng.integers(0, 400, 900), rng.integers(0, 400, 900)
    order = np.lexsort((at, pair))
    pair, at, other = np.unique(pair[order], return_inverse=True)[1], at[order], other[order]
    good = substring_dedup.chainable(pair, at, other)
    for i in range(pair[-1] + 1):
        own = pair == i
        if substring_dedup.seed_chains(substring_dedup.stretched(at[own], other[own], np.full(own.sum(), substring_dedup.K))):
            assert good[i]
    assert 0 < good.sum() < len(good)


def test_near_copies_are_tied_to_leaders_and_lose_no_link(spark):
    """Forty edited copies have far fewer rows than pairs, each pair is linked by a row or through a third text; what two of them share beside their leader is found."""
    rng = random.Random(23)
    fresh = lambda n: [f"z{rng.randrange(6000)}" for _ in range(n)]
    p, extra = fresh(300), fresh(90)
    docs = {i: fresh(10) + [fresh(1)[0] if rng.random() < 0.02 else w for w in p] + fresh(20) for i in range(40)}
    docs |= {i: docs[i] + x + fresh(10) for i, x in ((20, extra), (30, [fresh(1)[0] if j % 18 == 9 else w for j, w in enumerate(extra)]))}
    # the parts of what these two share stand elsewhere too, in smaller and in greater documents
    docs |= {100 * k + a - 1000: fresh(20) + extra[a : a + 20] + fresh(20) for k in (0, 20) for a in range(0, 80, 10)}
    rows = substring_dedup.shared_passages(table(spark, [(i, " ".join(x), "s") for i, x in docs.items()])).collect()
    near = {}
    for r in rows:
        for a, b, x, y in ((r["doc_id"], r["other_id"], r["other_start"], r["other_end"]), (r["other_id"], r["doc_id"], r["start_word"], r["end_word"])):
            near.setdefault(a, []).append((b, x, y))
    linked = lambda a, b: any(o == b or any(o == q and min(y, v) - max(x, u) >= substring_dedup.LEAST for q, u, v in near[b]) for o, x, y in near[a])
    assert all(linked(a, b) for a in range(40) for b in range(a))
    assert len({(r["doc_id"], r["other_id"]) for r in rows}) < 400
    assert any((r["doc_id"], r["other_id"]) == (30, 20) and r["start_word"] <= 345 and r["end_word"] >= 405 for r in rows)


def test_a_chunk_meets_one_part_of_the_documents_at_a_time(spark, monkeypatch):
    """Parts of three documents give the rows that one part gives; chains of a part are made before the next is read, and no answer holds two parts."""
    import pyarrow as pa

    rng = random.Random(19)
    fresh = lambda n: [f"z{rng.randrange(6000)}" for _ in range(n)]
    p = fresh(240)
    edited = [fresh(1)[0] if i % 24 == 11 else w for i, w in enumerate(p)]
    # every run of ten words of the passage stands in a smaller and in a greater document, which lead it
    docs = [(k * 1000 + i, fresh(30) + p[i * 10 : i * 10 + 20] + fresh(30)) for k in (0, 2) for i in range(24)]
    docs += [(1000 + i, fresh(20 + i) + x + fresh(30)) for i, x in enumerate((p, edited, p, edited))]
    found = lambda: sorted(map(tuple, substring_dedup.shared_passages(table(spark, [(i, " ".join(w), "s") for i, w in docs])).collect()))
    whole = found()
    lead, read, made = substring_dedup.mark_lead_kernel, [], []
    monkeypatch.setattr(substring_dedup, "PART_DOCS", 3)
    monkeypatch.setattr(substring_dedup, "mark_lead_kernel", lambda parts: made.append(parts) or lead(parts))
    assert found() == whole and {(b, a) for b in range(1000, 1004) for a in range(1000, b)} <= {(r[0], r[3]) for r in whole}
    assert made[0] > 5

    # one chunk by hand: the text, its marked seeds, and what a bucket answers in four parts
    plan, own, texts = exchange.Plan(0, 1 << 20), np.arange(40), [" ".join(edited if i % 2 else p) for i in range(40)]
    text = [t.encode() for t in texts]
    words = substring_dedup.Words(text, substring_dedup.ALNUM)
    keys = substring_dedup.Keys(substring_dedup.SEEDS, words, substring_dedup.Stretches(words.hashes))
    none = lambda n, t: np.zeros(n, t)
    marks = [substring_dedup.pressed(keys.hash[m], keys.at[m].astype(np.int32), none(m.sum(), np.int64), none(m.sum(), np.int32), none(m.sum(), np.int32)) for m in (keys.row == i for i in own)]
    batch = pa.RecordBatch.from_arrays([pa.array(own), pa.array(text, pa.binary()), pa.array(marks, pa.binary())], ["doc_id", "text", "marks"])
    rows = list(substring_dedup.marked_rows(plan)(iter([batch])))
    answers = pa.Table.from_batches(lead(4)(substring_dedup.mark_ask_kernel(plan)(iter([batch])))).sort_by("kind")
    parts = {}
    for kind, piece in zip(answers["kind"].to_pylist(), answers["piece"].to_pylist()):
        if kind > substring_dedup.MARKS:
            parts.setdefault(kind - substring_dedup.MARKS - 1, set()).update(substring_dedup.unpressed(piece)[2].tolist())
    assert sorted(x for docs_ in parts.values() for x in docs_) == own.tolist() and len(parts) == 4
    assert all((substring_dedup.part_of(np.array(sorted(x)), 4) == k).all() for k, x in parts.items())

    def stream():
        yield from rows
        for b in answers.to_batches(max_chunksize=1):
            read.append(b["kind"][0].as_py())
            yield b

    chains = substring_dedup.other_chain_kernel(plan)(stream())
    first = next(chains)
    assert max(read) <= substring_dedup.MARKS + 2 and set(first["other_id"].to_pylist()) <= parts[0]
    pairs = {*zip(first["doc_id"].to_pylist(), first["other_id"].to_pylist())}
    for b in chains:
        pairs |= {*zip(b["doc_id"].to_pylist(), b["other_id"].to_pylist())}
    assert pairs == {(b, a) for b in range(40) for a in range(b)}


def test_one_class_has_words_of_a_leader_in_common():
    rng = np.random.default_rng(4)
    first = rng.integers(0, 300, 3000).astype(np.int32)
    last = (first + substring_dedup.LEAST + rng.integers(0, 200, 3000)).astype(np.int32)
    kind = substring_dedup.class_of(np.zeros(3000, np.int64), first, last)
    assert 1 < len(np.unique(kind)) < 300
    for k in np.unique(kind):
        assert last[kind == k].min() - first[kind == k].max() >= substring_dedup.LEAST
    assert (substring_dedup.class_of(np.zeros(1, np.int64), np.zeros(1, np.int32), np.zeros(1, np.int32)) == 0).all()


def test_pairs_that_link_no_stretches_have_no_chain():
    rng = np.random.default_rng(12)
    pair = np.sort(rng.integers(0, 400, 1600))
    at, other = rng.integers(0, 300, 1600), rng.integers(0, 900, 1600)
    order = np.lexsort((at, pair))
    pair, at, other = np.unique(pair[order], return_inverse=True)[1], at[order], other[order]
    good = substring_dedup.linkable(pair, at, other)
    for i in range(pair[-1] + 1):
        own = pair == i
        assert good[i] or not substring_dedup.seed_chains(substring_dedup.stretched(at[own], other[own], np.full(own.sum(), substring_dedup.K)))
    assert 0 < good.sum() < len(good)


def test_every_shared_window_lies_in_a_passage(spark):
    """Pieces of one text at any lengths: each window that two documents share is reported in both."""
    rng = random.Random(8)
    source, least = [f"q{i}" for i in range(150)], substring_dedup.LEAST
    docs = {}
    for i in range(60):
        a, n = rng.randrange(100), rng.choice([30, 44, 49, 50, 51, 55, 80])
        docs[i] = [f"u{i}x{j}" for j in range(rng.randrange(20))] + source[a : a + n] + [f"v{i}x{j}" for j in range(rng.randrange(60))]
    seen = Counter()
    for t in docs.values():
        seen.update({tuple(t[a : a + least]) for a in range(len(t) - least + 1)})
    spans = {}
    for r in substring_dedup.shared_passages(table(spark, [(i, " ".join(t), "s") for i, t in docs.items()])).collect():
        spans.setdefault(r["doc_id"], []).append((r["start_word"], r["end_word"]))
        spans.setdefault(r["other_id"], []).append((r["other_start"], r["other_end"]))
    shared = [(i, a) for i, t in docs.items() for a in range(len(t) - least + 1) if seen[tuple(t[a : a + least])] > 1]
    assert len(shared) > 100
    assert [(i, a) for i, a in shared if not any(x <= a and a + least <= y for x, y in spans.get(i, []))] == []


@pytest.mark.parametrize("once", [1, 9])
def test_every_place_of_a_repeated_passage(spark, once):
    rng = random.Random(5)
    fresh = lambda n: [f"z{rng.randrange(5000)}" for _ in range(n)]
    passage = fresh(60)
    docs = [(5, " ".join(fresh(20) + passage + fresh(40) + passage + fresh(20)), "s"), (once, " ".join(fresh(15) + passage + fresh(15)), "s")]
    spans = set()
    for r in substring_dedup.shared_passages(table(spark, docs)).collect():
        spans |= {(r["doc_id"], r["start_word"], r["end_word"]), (r["other_id"], r["other_start"], r["other_end"])}
    assert spans == {(5, 20, 80), (5, 120, 180), (once, 15, 75)}


def test_passage_edges(edge, empty):
    assert substring_dedup.shared_passages(empty).count() == 0
    found = {(r["doc_id"], r["other_id"]) for r in substring_dedup.shared_passages(edge).collect()}
    assert (6, 5) in found and (9, 8) in found


# --- language models ---


def test_cross_entropy_difference_is_the_formula(spark, edge, empty):
    docs = table(spark, [(1, "a b a b", "s"), (2, "c d", "s"), (3, None, "s")])
    target = spark.createDataFrame([(1,), (1,), (None,), (77,)], "doc_id long")
    got = {r["doc_id"]: r for r in lm_score.score(docs, target).collect()}
    a, b, c = lm_score.MIXTURE
    p = lambda two, one: a * two + b * one + c / lm_score.UNIGRAMS
    back = [p(1 / 2, 2 / 6), p(1, 2 / 6), p(1, 2 / 6), p(1, 2 / 6)]
    back[2] = p(1 / 1, 2 / 6)
    near = [p(1, 2 / 4), p(1, 2 / 4), p(1, 2 / 4), p(1, 2 / 4)]
    assert got[1]["background_loss"] == pytest.approx(-np.mean(np.log(back)), abs=1e-3)
    assert got[1]["target_loss"] == pytest.approx(-np.mean(np.log(near)), abs=1e-3)
    assert got[1]["score"] < 0 < got[2]["score"] and got[3]["score"] == 0 and got[3]["n_tokens"] == 0
    assert lm_score.score(edge, target.where("false")).count() == edge.count()
    assert lm_score.score(empty, target).count() == 0


def brute_scores(rows, good):
    """The two mean losses of each row, from plain dictionaries."""
    counts = [(Counter(), Counter(), Counter()) for _ in range(2)]
    for i, t in rows:
        x = words(t)
        for two, one, seen in counts[: 1 + (i in good)]:
            two.update(zip([""] + x, x))
            one.update(x)
            seen.update(([""] + x)[:-1])
    a, b, c = lm_score.MIXTURE

    def loss(m, u, w):
        two, one, seen = counts[m]
        uni = one[w] / one.total() if one.total() else 1 / lm_score.UNIGRAMS
        return -np.log(a * (two[u, w] / seen[u] if seen[u] else uni) + b * uni + c / lm_score.UNIGRAMS)

    return [(i, len(x), *(float(np.mean([loss(m, u, w) for u, w in zip([""] + x, x)])) if x else 0.0 for m in (1, 0))) for i, x in ((i, words(t)) for i, t in rows)]


def test_lm_scores_are_the_brute_force_over_many_chunks_and_buckets(spark, monkeypatch):
    rng = random.Random(12)
    rows = [(i, " ".join(f"w{int(rng.paretovariate(0.7)) % 500}" for _ in range(rng.randrange(0, 60)))) for i in range(300)] + [(7, "w1 w2"), (7, "w1 w2"), (900, None)]
    good = set(range(0, 300, 7))
    monkeypatch.setattr(exchange, "BUCKET_BYTES", 4000)
    monkeypatch.setattr(exchange, "LEAST_CHUNK", 900)
    monkeypatch.setattr(exchange, "CHUNK_SHARE", 10)
    marks = spark.createDataFrame([(i,) for i in good], "doc_id long")
    want = sorted(brute_scores(rows, good))
    docs = table(spark, [(i, t, "s") for i, t in rows])
    got = sorted(map(tuple, lm_score.score(docs.repartition(5), marks).select("doc_id", "n_tokens", "target_loss", "background_loss").collect()))
    assert [g[:2] for g in got] == [w[:2] for w in want] and np.allclose([g[2:] for g in got], [w[2:] for w in want])
    some = sorted(map(tuple, lm_score.score(docs, marks, docs.where("doc_id < 50")).select("doc_id", "n_tokens", "target_loss", "background_loss").collect()))
    assert np.allclose(some, [w for w in want if w[0] < 50])


def test_bigram_counts_stay_exact_beyond_any_table(spark):
    """More distinct bigrams than 2^20: every token is alone in its context, so every loss is known."""
    n, each = 300, 5000
    docs = table(spark, [(i, " ".join(f"w{i * each + j}" for j in range(each)), "s") for i in range(n)])
    total, (a, b, c) = n * each, lm_score.MIXTURE
    p = lambda two: a * two + b / total + c / lm_score.UNIGRAMS
    want = -(np.log(p(1 / n)) + (each - 1) * np.log(p(1))) / each
    got = lm_score.score(docs, docs.where("doc_id < 3").select("doc_id"), docs.where("doc_id >= 297")).collect()
    assert len(got) == 3 and all(r["n_tokens"] == each for r in got)
    assert [r["background_loss"] for r in got] == pytest.approx([want] * 3, rel=1e-9)
    unseen = -np.log(c / lm_score.UNIGRAMS)
    assert [r["target_loss"] for r in got] == pytest.approx([unseen] * 3, rel=1e-3)


def test_tokens_split_at_ascii_blanks_only():
    t = Tokens([b"A\x0bb\xc2\xa0c \x1cd", b"", b"x"])
    assert t.lens.tolist() == [3, 0, 1] and t.vocabulary[0] == b"a"


def test_words_are_the_tokens_whatever_the_blocks(monkeypatch):
    rng = random.Random(3)
    texts = [" ".join(rng.choice(["Ab", "ab", "\xe9t\xe9", "x" * 40, "\x00y", "q-r", "\u212a"]) for _ in range(rng.randrange(40))).encode() for _ in range(60)]
    for split, table_ in ((alnum_words, ALNUM), (blank_words, BLANK)):
        want = Tokens(texts, split)
        one = Words(texts, table_)
        assert want.lens.tolist() == one.lens.tolist() and want.pos.tolist() == one.pos.tolist()
        assert len(set(zip(want.hashes.tolist(), one.hashes.tolist()))) == len(set(want.hashes.tolist())) == len(set(one.hashes.tolist()))
        monkeypatch.setattr(Words, "BLOCK", 50)
        assert Words(texts, table_).hashes.tolist() == one.hashes.tolist()
        monkeypatch.setattr(Words, "LONG", 30)
        assert len(set(Words(texts, table_).hashes.tolist())) == len(set(one.hashes.tolist()))
        monkeypatch.undo()
    assert Words([], ALNUM).lens.tolist() == [] and Words([b"", b" "], ALNUM).lens.tolist() == [0, 0]


@pytest.mark.parametrize("name", ["op7_license_scan", "op8_decontaminate", "op9_ngram_jaccard", "op10_lm_score"])
def test_query_is_its_sql(spark, sf, name):
    from facetgraph.llm.entry import ORACLES, QUERIES

    con = duckdb.connect()
    for t in ("documents", "benchmark", "labels"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    got, want = QUERIES[name](spark, sf), con.sql(ORACLES[name])
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    assert sorted(str(tuple(r)) for r in got.select(columns).collect()) == sorted(map(str, want.select(*columns).fetchall()))
