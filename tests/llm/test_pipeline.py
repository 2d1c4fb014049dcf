"""The pipeline on the smallest table: each stage's contract, and the whole against the operators' own decisions."""

import os
import shutil
import subprocess
import sys
from collections import Counter
from pathlib import Path

import duckdb
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from facetgraph.llm import decontaminate, mixing, ngram_join, toxicity


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    done = {}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf)
        done[name] = {r["doc_id"] for r in out.select("doc_id").collect()}
        assert out.columns == columns + ["shard", "slot"] * (name == "sharding")
        docs = out
    assert done["sharding"] == done["mixing"] <= done["decontaminate"] <= done["near_duplicates"] <= done["toxicity"]


def test_stages_agree_with_the_operators(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    machine = toxicity.train(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    scores = {r["doc_id"]: r["__toxicity"] for r in toxicity.score_toxicity(docs, machine).collect()}
    kept = {r["doc_id"] for r in corpus_pipeline.toxicity(spark, docs, sf).collect()}
    assert kept == {i for i, s in scores.items() if s < toxicity.CUT}
    comps = {r["doc_id"]: r["component_id"] for r in ngram_join.near_duplicate_components(docs).collect()}
    assert {r["doc_id"] for r in corpus_pipeline.near_duplicates(spark, docs, sf).collect()} == set(comps.values())
    bad = {r["doc_id"] for r in decontaminate.op8_decontaminate(spark, sf).where("contaminated").collect()}
    assert {r["doc_id"] for r in corpus_pipeline.decontaminate(spark, docs, sf).collect()} == set(comps) - bad


def test_run_gives_every_row_a_place(spark, sf):
    out = corpus_pipeline.run(spark, sf)
    sizes = [r["count"] for r in out.groupBy("shard").count().collect()]
    assert max(sizes) - min(sizes) <= 1 and out.select("shard", "slot").distinct().count() == out.count()


@pytest.fixture(scope="module")
def odd(spark, sf):
    """Nulls in every column, empty and long texts, ties, repeated rows, and columns named as the stages' own."""
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(40)
    more = [(None, None, None, None, None), (None, "", "en", None, 0), (None, "same words " * 40, "en", "z", 1), (None, "same words " * 40, "en", "z", 1), (3, None, None, "z", None), (3, "a b c", "en", None, 5), (3, "a b c", "en", None, 5), (70001, "long " * 60_000, "en", "z", 9), (70002, "...", "en", "z", 3)]
    rows = docs.union(spark.createDataFrame(more, docs.schema))
    return rows.withColumn("shard", F.lit(1)).withColumn("h", F.lit(2)).withColumn("size", F.lit(3)).withColumn("label", F.lit(None).cast("int")).withColumn("leader", F.lit(5))


@pytest.mark.parametrize("stage", [s for _, s in corpus_pipeline.STAGES], ids=[n for n, _ in corpus_pipeline.STAGES])
def test_stages_on_odd_rows(spark, sf, odd, stage):
    out = stage(spark, odd, sf)
    added = {"__shard", "slot"} if stage is corpus_pipeline.sharding else set()
    assert set(out.columns) == set(odd.columns) | added
    rows = Counter(tuple(r) for r in out.select(odd.columns).collect())
    given = Counter(tuple(r) for r in odd.collect())
    assert set(rows) <= set(given)
    if stage is corpus_pipeline.sharding:
        assert rows == given
    if stage is corpus_pipeline.near_duplicates:
        assert sum(n for r, n in rows.items() if r[0] == 3) == 1 and sum(n for r, n in rows.items() if r[0] is None and r[1] and r[1].startswith("same")) == 1
    if stage in (corpus_pipeline.decontaminate, corpus_pipeline.toxicity):
        assert all(rows[r] in (0, n) for r, n in given.items())
    if stage is corpus_pipeline.decontaminate:
        assert all(rows[r] == n for r, n in given.items() if not r[1])
    if stage is corpus_pipeline.mixing:
        assert all(n <= 2 * given[r] for r, n in rows.items())
    assert stage(spark, odd.where("false"), sf).count() == 0


def test_the_entry_without_the_toolbox(tmp_path):
    root = Path(__file__).resolve().parents[2]
    shutil.copytree(root, tmp_path / "repo", ignore=shutil.ignore_patterns(".git", "llm", "__pycache__", "spark-warehouse", ".pytest_cache"))
    code = "import __spark_entry__ as e; q = e.queries(); assert 'prefilter_eq' in q and not [n for n in q if n.startswith('op') or n == 'pipeline']; assert set(e.oracle_sql()) <= set(q)"
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "repo", env={**os.environ, "PYTHONPATH": str(tmp_path / "repo")}, capture_output=True, text=True)
    assert done.returncode == 0, done.stderr


def test_the_run_is_the_plain_stages(spark, sf, tmp_path):
    """Every stage but the classifier's scores by plain Python or SQL, from the table to the rows of ``run``."""
    from test_operators import brute_components, words

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    machine = toxicity.train(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    rows = [r for r in toxicity.score_toxicity(docs, machine).collect() if r["__toxicity"] < toxicity.CUT]
    component = brute_components([(r["doc_id"], r["text"]) for r in rows])
    rows = [r for r in rows if component[r["doc_id"]][1] == r["doc_id"]]
    windows = set()
    for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect():
        x = words(r["text"])
        windows |= {tuple(x[a : a + 13]) for a in range(max(1, len(x) - 12) if x else 0)}
    sizes = {len(w) for w in windows}

    def dirty(text):
        x, hit = words(text), set()
        for n in sizes:
            for p in range(len(x) - n + 1):
                if tuple(x[p : p + n]) in windows:
                    hit.update(range(p, p + n))
        return bool(hit) and 20 * len(hit) >= len(x)

    kept = [r.asDict() for r in rows if not dirty(r["text"])]
    assert 0 < len(kept) < len(rows)
    spark.createDataFrame([tuple(r[c] for c in docs.columns) for r in kept], docs.schema).write.parquet(f"{tmp_path}/kept.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{tmp_path}/kept.parquet/*.parquet')")
    # a document without words weighs nothing; it is taken as often as its source's threshold says, which SQL's word counts do not tell
    taken = {i: (n, t) for i, n, t in con.sql(f"SELECT doc_id, size, taken FROM ({mixing.OP2_SQL})").fetchall()}
    out = Counter(r["doc_id"] for r in corpus_pipeline.run(spark, sf).collect())
    assert set(out) <= set(taken)
    assert all(out[i] == t // n for i, (n, t) in taken.items() if n)
