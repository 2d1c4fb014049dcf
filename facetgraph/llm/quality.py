"""Quality by positive-unlabelled learning.

Trusted positives are the documents that training labels mark good; unlabelled text is
a sample of all documents. No negative label is used. The class prior, the share of good documents
in unlabelled text, is estimated from how a first classifier's scores are spread on
held-back positives and unlabelled rows: at a threshold that positives pass
and bad documents do not, the pass rates' ratio is the prior. The classifier then
minimises the unbiased risk with the part that stands for negatives kept from going below zero.

Features are shares of character classes, repeated words and word shapes, each as a mean and as the largest
of any stretch of the text. The fit sees bounded samples (``labelled.SAMPLE_ROWS`` each); all texts are scored whole.

Rows. Null and empty texts have zero features and get that score. Without positive labels every score is
0.5. Rows without doc_id are scored (held_out null); repeated rows are scored each. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from facetgraph.llm.labelled import fold, sample_ids, texts_of, training_labels
from facetgraph.llm.textkit import Tokens, arrow, text_chunks

FOLDS, HELD_OUT, CUT = 5, 0, 0.3
STRETCH, WORD_STRETCH = 512, 64
STEPS, RATE, DECAY = 1500, 0.02, 1e-3

#: Character classes: lower, upper, digit, blank, stops, bang, bars, symbols, control, beyond ASCII.
CLASSES = 10


def _classes() -> np.ndarray:
    table = np.full(256, 7, np.uint8)
    for b in range(256):
        c = chr(b)
        if b >= 0x80:
            table[b] = 9
        elif c.islower():
            table[b] = 0
        elif c.isupper():
            table[b] = 1
        elif c.isdigit():
            table[b] = 2
        elif c in " \t\n\r\v\f":
            table[b] = 3
        elif c in ".,;:'\"()-":
            table[b] = 4
        elif c in "!?":
            table[b] = 5
        elif c == "|":
            table[b] = 6
        elif b < 32 or b == 127:
            table[b] = 8
    return table


TABLE = _classes()
WIDTH = 2 * CLASSES + 6


def _stretches(lens: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts of stretches of about ``size`` in each of the runs laid end to end, and the run of each."""
    n = np.maximum(1, lens // size) * (lens > 0)
    run = np.repeat(np.arange(len(lens)), n)
    index = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
    return (np.cumsum(lens) - lens)[run] + index * lens[run] // np.maximum(1, n[run]), run


def _mean_max(marks: np.ndarray, lens: np.ndarray, size: int, rows: int) -> np.ndarray:
    """Share of marked places in each run, and the largest share in any of its stretches."""
    out = np.zeros((2, rows))
    at, run = _stretches(lens, size)
    if len(at):
        sums = np.add.reduceat(marks.astype(np.float64), at)
        lengths = np.diff(np.append(at, len(marks)))
        out[0] = np.bincount(run, weights=sums, minlength=rows) / np.maximum(1, lens)
        np.maximum.at(out[1], run, sums / np.maximum(1, lengths))
    return out


def features(texts: list[bytes]) -> np.ndarray:
    n = len(texts)
    out = np.zeros((n, WIDTH))
    lens = np.fromiter(map(len, texts), np.int64, n)
    kinds = TABLE[np.frombuffer(b"".join(texts), np.uint8)]
    for c in range(CLASSES):
        out[:, 2 * c : 2 * c + 2] = np.sqrt(_mean_max(kinds == c, lens, STRETCH, n)).T
    t = Tokens(texts, bytes.split)
    if len(t.codes):
        again = np.append(False, (t.codes[1:] == t.codes[:-1]) & (t.docs[1:] == t.docs[:-1]))
        out[:, 2 * CLASSES : 2 * CLASSES + 2] = np.sqrt(_mean_max(again, t.lens, WORD_STRETCH, n)).T
        distinct = np.bincount(np.unique(t.docs * len(t.vocabulary) + t.codes) // len(t.vocabulary), minlength=n)
        out[:, 2 * CLASSES + 2] = distinct / np.maximum(1, t.lens) * (t.lens > 0)
        out[:, 2 * CLASSES + 3] = np.log1p(t.lens)
        sizes = np.fromiter(map(len, t.vocabulary), np.int64, len(t.vocabulary))
        out[:, 2 * CLASSES + 4] = np.bincount(t.docs, weights=sizes[t.codes], minlength=n) / np.maximum(1, t.lens) / 10
        out[:, 2 * CLASSES + 5] = np.bincount(t.docs, weights=sizes[t.codes] > 20, minlength=n) / np.maximum(1, t.lens)
    return out


def softplus(x: np.ndarray) -> np.ndarray:
    return np.logaddexp(0, x)


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


@dataclass
class Model:
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    prior: float

    def inputs(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -6, 6)
        return np.concatenate([z, z * z / 6, np.ones((len(z), 1))], axis=1)

    def scores(self, x: np.ndarray) -> np.ndarray:
        return sigmoid(self.inputs(x) @ self.weights)


def descend(gradient, width: int, steps: int = STEPS) -> np.ndarray:
    w, m, s = np.zeros(width), np.zeros(width), np.zeros(width)
    for i in range(1, steps + 1):
        g = gradient(w)
        m, s = 0.9 * m + 0.1 * g, 0.999 * s + 0.001 * g * g
        w -= RATE * (m / (1 - 0.9**i)) / (np.sqrt(s / (1 - 0.999**i)) + 1e-8)
    return w


def class_prior(positive: np.ndarray, unlabelled: np.ndarray) -> float:
    """Smallest upper bound, over thresholds, of unlabelled pass rate / positive pass rate."""
    cuts = np.quantile(positive, np.linspace(0, 0.95, 96))
    p = np.array([(positive >= c).mean() for c in cuts])
    u = np.array([(unlabelled >= c).mean() for c in cuts])
    slack = np.sqrt(np.log(40) / (2 * max(1, len(positive)))) + np.sqrt(np.log(40) / (2 * max(1, len(unlabelled))))
    best = int(np.argmin((u + slack) / np.maximum(p, 1e-9)))
    return float(np.clip(u[best] / max(p[best], 1e-9), 0.01, 0.99))


def fit(positive: np.ndarray, unlabelled: np.ndarray) -> Model:
    pool = unlabelled if len(unlabelled) else np.zeros((1, WIDTH))
    model = Model(pool.mean(0), np.maximum(pool.std(0), 1e-3), np.zeros(2 * WIDTH + 1), 0.5)
    if not len(positive) or not len(unlabelled):
        return model
    p, u = model.inputs(positive), model.inputs(unlabelled)
    even = lambda w, a, b: (-(sigmoid(-(a @ w)) @ a) / len(a) + (sigmoid(b @ w) @ b) / len(b)) / 2 + DECAY * w
    first = descend(lambda w: even(w, p[::2], u[::2]), p.shape[1], STEPS // 3)
    prior = class_prior(p[1::2] @ first, u[1::2] @ first) if len(p) > 1 and len(u) > 1 else 0.5

    def risk(w: np.ndarray) -> np.ndarray:
        zp, zu = p @ w, u @ w
        negative = softplus(zu).mean() - prior * softplus(zp).mean()
        g = (sigmoid(zu) @ u) / len(u) - prior * (sigmoid(zp) @ p) / len(p)
        if negative < 0:
            return -g
        return -prior * (sigmoid(-zp) @ p) / len(p) + g + DECAY * w

    model.weights, model.prior = descend(risk, p.shape[1]), prior
    return model


def feature_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        labels = batch.column(batch.schema.get_field_index("label")).to_pylist()
        for at, texts in text_chunks(batch):
            rows = [x.tobytes() for x in features(texts)]
            yield pa.RecordBatch.from_arrays([pa.array(labels[at : at + len(texts)], pa.int32()), pa.array(rows, pa.binary())], ["label", "x"])


def train(documents: DataFrame, labels: DataFrame, column: str = "quality", folds: int = FOLDS, held_out: int = HELD_OUT) -> Model:
    good = sample_ids(training_labels(labels, column, folds, held_out).where("label = 1")).select("doc_id", F.lit(1).alias("label"))
    web = sample_ids(documents.select("doc_id").distinct(), seed=8).select("doc_id", F.lit(0).alias("label"))
    rows = texts_of(documents, good.union(web)).transform(arrow, feature_kernel, "label int, x binary").collect()
    rows = sorted((r["label"], bytes(r["x"])) for r in rows)
    take = lambda z: np.array([np.frombuffer(x, np.float64) for y, x in rows if y == z]).reshape(-1, WIDTH)
    rng = np.random.default_rng(5)
    return fit(rng.permutation(take(1)), rng.permutation(take(0)))


def score_udf(model: Model) -> Column:
    @F.pandas_udf("double")
    def score(series: pd.Series) -> pd.Series:
        batch = pa.RecordBatch.from_arrays([pa.array(series, pa.string(), from_pandas=True)], ["text"])
        return pd.Series(np.concatenate([np.empty(0), *(model.scores(features(texts)) for _, texts in text_chunks(batch))]))

    return score(F.col("text").cast("string"))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = train(documents, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = documents.withColumn("score", score_udf(model))
    held = fold(F.col("doc_id"), FOLDS) == HELD_OUT
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted"))
