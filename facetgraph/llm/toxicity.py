"""Toxicity by a factorization machine over hashed terms.

Terms are a document's distinct words, their first letters, and first letters seen several times, hashed. The machine
adds a weight for each term and, for each pair of terms, the product of their
factors: a term that is harmless alone can count beside another, which additive
weights cannot say. It is fitted in one task from a bounded sample of labelled
rows (``labelled.SAMPLE_ROWS``) over all hashed terms that at least SEEN of them hold, whatever
their classes, so that terms which tell something only in pairs take part. It scores every text whole, in Arrow batches and without a shuffle.

Rows. Null and empty texts get the score of a text without terms. Without labels of both classes every
score is the share of toxic labels (0 if there are none). Rows without doc_id are scored too (held_out null).
Repeated rows are scored each. Other columns are ignored by the query and kept by ``score_toxicity``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from facetgraph.llm.labelled import fold, sample_ids, texts_of, training_labels
from facetgraph.llm.textkit import Tokens, alnum_words, arrow, text_chunks

BUCKETS, SEEN, FACTORS, STEM = 1 << 18, 3, 8, 4
#: A stem that occurs so often is a further term.
REPEATS = (2, 4)
EPOCHS, BATCH, RATE, DECAY, SEED = 9, 128, 0.025, 2e-4, 11
#: Terms that count in full for telling the classes apart alone, and how fast the others count less.
TELLING, SHARP = 1024, 4
FOLDS, HELD_OUT, CUT = 3, 1, 0.7


def term_pairs(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (document, hashed term) pairs, sorted."""
    t = Tokens(texts, alnum_words)
    word = (t.table % np.uint64(BUCKETS)).astype(np.int64)
    stem = np.fromiter((xxhash.xxh3_64_intdigest(w.decode("utf-8", "replace")[:STEM].encode(), 1) % BUCKETS for w in t.vocabulary), np.int64, len(t.vocabulary))
    if not len(t.codes):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    stems, times = np.unique(t.docs * BUCKETS + stem[t.codes], return_counts=True)
    often = [stems[times >= n] // BUCKETS * BUCKETS + (stems[times >= n] * 40_503 + n) % BUCKETS for n in REPEATS]
    key = np.unique(np.concatenate([t.docs * BUCKETS + word[t.codes], stems, *often]))
    return key // BUCKETS, key % BUCKETS


@dataclass
class Machine:
    place: np.ndarray  # bucket → term, -1 elsewhere
    bias: float
    weights: np.ndarray
    factors: np.ndarray

    def logits(self, doc: np.ndarray, bucket: np.ndarray, n: int) -> np.ndarray:
        term = self.place[bucket]
        doc, term = doc[term >= 0], term[term >= 0]
        out = self.bias + np.bincount(doc, weights=self.weights[term], minlength=n)
        for f in range(self.factors.shape[1]):
            v = self.factors[term, f]
            out += 0.5 * (np.bincount(doc, weights=v, minlength=n) ** 2 - np.bincount(doc, weights=v * v, minlength=n))
        return out


def term_scales(docs: list[np.ndarray], y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Buckets that at least SEEN documents hold, and how far each counts, up to 1.

    A term counts by how well it tells the classes apart alone (the two-class chi statistic, against that of the TELLING-th best), or by
    how many documents hold it, whichever is more: a rare term without a class of its own can hardly be learnt, a frequent one may matter beside others.
    """
    count = np.zeros((2, BUCKETS))
    for label in (0, 1):
        chosen = [d for d, z in zip(docs, y) if z == label]
        if chosen:
            count[label] = np.bincount(np.concatenate(chosen), minlength=BUCKETS)
    n = np.array([(y == 0).sum(), (y == 1).sum()], float)
    seen, rate = count.sum(0), (count + 0.5) / (n + 1)[:, None]
    spread = np.abs(rate[1] - rate[0]) / np.sqrt((seen + 1) / (n.sum() + 2) * (1 / max(n[0], 1) + 1 / max(n[1], 1)))
    terms = np.flatnonzero(seen >= SEEN)
    best = np.sort(spread[terms])[::-1]
    bar = best[min(TELLING, len(best)) - 1] if len(best) else 1.0
    return terms, np.maximum(np.minimum(1, (spread[terms] / bar) ** SHARP), np.sqrt(seen[terms] / n.sum()))


def summed(values: np.ndarray, group: np.ndarray, n: int) -> np.ndarray:
    """Rows of ``values`` summed by group."""
    return np.stack([np.bincount(group, weights=values[:, f], minlength=n) for f in range(values.shape[1])], axis=1)


def fit(docs: list[np.ndarray], y: np.ndarray, epochs: int = EPOCHS) -> Machine:
    """docs[i]: hashed terms of document i; y: 0 or 1. Adam on the logistic loss; a step moves the terms of its batch alone."""
    place = np.full(BUCKETS, -1, np.int32)
    share = float(y.mean()) if len(y) else 0.0
    if not 0 < share < 1:
        return Machine(place, -40.0 if share == 0 else 40.0, np.zeros(1), np.zeros((1, 1)))
    chosen, scale = term_scales(docs, y)
    place[chosen] = np.arange(len(chosen), dtype=np.int32)
    rows = [p[p >= 0] for p in (place[d] for d in docs)]
    rng = np.random.default_rng(SEED)
    k = len(chosen)
    bias = np.array([np.log(share / (1 - share))])
    # the weight and the factors of a term side by side
    both = np.concatenate([np.zeros((k, 1)), rng.normal(0, 0.01, (k, FACTORS))], axis=1)
    m, s, m0, s0, step = np.zeros_like(both), np.zeros_like(both), 0.0, 0.0, 0
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for a in range(0, len(order), BATCH):
            pick = order[a : a + BATCH]
            lens = np.fromiter((len(rows[i]) for i in pick), np.int64, len(pick))
            doc, term = np.repeat(np.arange(len(pick)), lens), np.concatenate([rows[i] for i in pick])
            used, own = np.unique(term, return_inverse=True)
            x = scale[used][:, None]
            now = both[used]
            mine = (now * x)[own]
            v = mine[:, 1:]
            total = summed(v, doc, len(pick))
            squares = np.bincount(doc, weights=(v * v).sum(1), minlength=len(pick))
            z = bias[0] + np.bincount(doc, weights=mine[:, 0], minlength=len(pick)) + 0.5 * ((total**2).sum(1) - squares)
            g = (1 / (1 + np.exp(-np.clip(z, -40, 40))) - y[pick]) / len(pick)
            grad = x * summed(np.concatenate([g[doc][:, None], g[doc][:, None] * (total[doc] - v)], axis=1), own, len(used)) + DECAY * now
            step += 1
            m[used], s[used] = 0.9 * m[used] + 0.1 * grad, 0.999 * s[used] + 0.001 * grad**2
            both[used] -= RATE * (m[used] / (1 - 0.9**step)) / (np.sqrt(s[used] / (1 - 0.999**step)) + 1e-8)
            m0, s0 = 0.9 * m0 + 0.1 * g.sum(), 0.999 * s0 + 0.001 * g.sum() ** 2
            bias -= RATE * (m0 / (1 - 0.9**step)) / (np.sqrt(s0 / (1 - 0.999**step)) + 1e-8)
    both *= scale[:, None]
    if not k:
        both = np.zeros((1, 1 + FACTORS))
    return Machine(place, float(bias[0]), both[:, 0].astype(np.float32), both[:, 1:].astype(np.float32))


def terms_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        labels = batch.column(batch.schema.get_field_index("label")).to_pylist()
        for at, texts in text_chunks(batch):
            doc, bucket = term_pairs(texts)
            cuts = np.searchsorted(doc, np.arange(len(texts) + 1))
            rows = [bucket[a:b].astype(np.int32).tobytes() for a, b in zip(cuts, cuts[1:])]
            yield pa.RecordBatch.from_arrays([pa.array(labels[at : at + len(texts)], pa.int32()), pa.array(rows, pa.binary())], ["label", "terms"])


def fit_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The machine of all rows of ``terms_kernel``, as one row."""
    held = list(batches)
    if not sum(b.num_rows for b in held):
        return
    # the order of arrival must not matter
    rows = pa.Table.from_batches(held).sort_by([("label", "ascending"), ("terms", "ascending")])
    del held
    terms = rows.column("terms").cast(pa.large_binary()).combine_chunks()
    cuts, y = np.frombuffer(terms.buffers()[1], np.int64) // 4, rows.column("label").to_numpy().astype(float)
    flat = np.frombuffer(terms.buffers()[2], np.int32) if terms.buffers()[2] else np.empty(0, np.int32)
    m = fit([flat[a:b] for a, b in zip(cuts, cuts[1 : len(terms) + 1])], y)
    yield pa.RecordBatch.from_arrays([pa.array([m.place.astype(np.int32).tobytes()]), pa.array([m.bias]), pa.array([m.weights.astype(np.float32).tobytes()]), pa.array([m.factors.astype(np.float32).tobytes()])], ["place", "bias", "weights", "factors"])


def train(documents: DataFrame, labels: DataFrame, column: str = "toxic", folds: int = FOLDS, held_out: int = HELD_OUT) -> Machine:
    """The machine fitted in one task on the sample; the driver holds what it has learnt alone."""
    sample = sample_ids(training_labels(labels, column, folds, held_out))
    rows = texts_of(documents, sample).transform(arrow, terms_kernel, "label int, terms binary")
    made = rows.repartition(1).transform(arrow, fit_kernel, "place binary, bias double, weights binary, factors binary").collect()
    if not made:
        return fit([], np.empty(0))
    m, weights = made[0], np.frombuffer(made[0]["weights"], np.float32)
    return Machine(np.frombuffer(m["place"], np.int32), m["bias"], weights, np.frombuffer(m["factors"], np.float32).reshape(len(weights), -1))


def score_udf(machine: Machine) -> Column:
    @F.pandas_udf("double")
    def score(series: pd.Series) -> pd.Series:
        batch = pa.RecordBatch.from_arrays([pa.array(series, pa.string(), from_pandas=True)], ["text"])
        out = [np.empty(0)]
        for _, texts in text_chunks(batch):
            doc, bucket = term_pairs(texts)
            out.append(1 / (1 + np.exp(-np.clip(machine.logits(doc, bucket, len(texts)), -40, 40))))
        return pd.Series(np.concatenate(out))

    return score(F.col("text").cast("string"))


def score_toxicity(documents: DataFrame, machine: Machine, name: str = "__toxicity") -> DataFrame:
    return documents.withColumn(name, score_udf(machine))


def without_toxic(documents: DataFrame, machine: Machine, most: float = CUT) -> DataFrame:
    """``documents`` whose score stays below ``most``, with their own columns."""
    return score_toxicity(documents, machine).where(F.col("__toxicity") < most).select(documents.columns)


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    machine = train(documents, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = score_toxicity(documents, machine)
    held = fold(F.col("doc_id"), FOLDS) == HELD_OUT
    return scored.select("doc_id", held.alias("held_out"), F.col("__toxicity").alias("score"), (F.col("__toxicity") >= CUT).cast("int").alias("predicted"))
