"""Cross-entropy difference between a target and a background n-gram model.

Both are interpolated bigram models, alike in all but the documents they count: the target's are
those that labels mark good, the background's are all. Bigrams, words and contexts are counted exactly, under 64-bit hashes, however many
there are. A document's score is the mean over its tokens of target loss minus background loss, in nats; lower
means closer to the target.

Plan. Chunks of text ask for their distinct bigrams and words by packed rows, buckets sum what all chunks say and answer with both
models' counts, and the answers meet the chunk's text again, where its documents are scored (see ``exchange``); no row stands for a single n-gram.
A chunk without its answers is an error, never a wrong score.

Rows. Null, empty and wordless texts have 0 tokens and score 0. Without target documents the target model falls
back to the uniform unigram. Labels without documents and null labels count for nothing; a repeated label row
counts its document once. Other columns are ignored; repeated documents are counted and scored each.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetgraph.llm.exchange import Plan, bucket_cuts, chunk_name, chunks, of_documents, text_rows, unpacked_chunk
from facetgraph.llm.graph import finished, release, settled, written
from facetgraph.llm.textkit import ALNUM, Words, arrow, emit, mix, pressed, runs, sieve_kernel, sieve_of, unpressed

#: Words of the uniform estimate.
UNIGRAMS = 1 << 18
#: Weights of the bigram, unigram and uniform estimates.
MIXTURE = (0.6, 0.39, 0.01)
ASK = pa.schema([("bucket", pa.int32()), ("role", pa.int32()), ("chunk", pa.binary()), ("piece", pa.binary()), ("tokens", pa.int64())])
ASK_SQL = "bucket int, role int, chunk binary, piece binary, tokens long"
#: Roles of asks: counted by the background model, by the target model, or by neither; the last and the first are answered.
BACKGROUND, TARGET, UNCOUNTED = 0, 1, 2
ANSWER = pa.schema([("chunk", pa.binary()), ("bucket", pa.int32()), ("piece", pa.binary()), ("tokens", pa.int64()), ("target_tokens", pa.int64())])
ANSWER_SQL = "chunk binary, bucket int, piece binary, tokens long, target_tokens long"
SCORE = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("target_loss", pa.float64()), ("background_loss", pa.float64())])
SCORE_SQL = "doc_id long, n_tokens long, target_loss double, background_loss double"


def counted(words: Words, placed: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray | None]:
    """Distinct keys of bigrams and words, sorted; how often each is seen, and, of words, stands before another; a document starts after word 0.

    ``placed``: also where, among the keys, each token's bigram, word and word before are.
    """
    first = words.pos == 0
    before = np.zeros(len(words.hashes), np.uint64)
    before[1:] = words.hashes[:-1]
    before[first] = 0
    pairs = np.unique(mix(before * np.uint64(Words.BASE) + words.hashes), return_inverse=placed, return_counts=True)
    spelt, word, n = np.unique(words.hashes, return_inverse=True, return_counts=True)
    word = word.reshape(-1)
    followed = np.bincount(word[words.pos + 1 < words.lens[words.docs]], minlength=len(spelt))
    keys = np.concatenate([pairs[0], mix(spelt + np.uint64(1)), mix(np.ones(1, np.uint64))])
    order = np.argsort(keys)
    seen = np.concatenate([pairs[-1], n, [0]])[order].astype(np.uint64)
    stands = np.concatenate([np.zeros(len(pairs[0]), np.int64), followed, [np.count_nonzero(first)]])[order].astype(np.uint64)
    if not placed:
        return keys[order], seen, stands, None
    rank = np.empty(len(keys), np.int64)
    rank[order] = np.arange(len(keys))
    own = rank[len(pairs[0]) + word]
    prior = np.append(rank[-1], own[:-1]) if len(own) else own
    return keys[order], seen, stands, np.stack([rank[pairs[1].reshape(-1)], own, np.where(first, rank[-1], prior)])


def ask_kernel(role: int, plan: Plan):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, texts in chunks(batches, plan.chunk_bytes):
            words = Words(texts, ALNUM)
            if not len(words.hashes):
                continue
            keys, seen, before, _ = counted(words)
            cuts = bucket_cuts(keys, plan.bits)
            used = np.flatnonzero(np.diff(cuts))
            name = chunk_name(ids, texts) if role != TARGET else None
            pieces = [pressed(*(x[cuts[b] : cuts[b + 1]] for x in (keys, seen, before))) for b in used]
            tokens = np.where(np.arange(len(used)) == 0, len(words.hashes), 0)
            yield from emit(ASK, [used.astype(np.int32), np.full(len(used), role, np.int32), [name] * len(used), pieces, tokens], 512)

    return run


def sum_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counts of a bucket's n-grams in both models, sent back to all that asked for them."""
    for bucket in runs(batches, ["bucket"]):
        role = bucket.column("role").to_numpy()
        pieces = [unpressed(x) for x in bucket.column("piece").to_pylist()]
        sizes = np.fromiter((len(x[0]) for x in pieces), np.int64, len(pieces))
        keys, seen, before = (np.concatenate(x) for x in zip(*pieces))
        del pieces
        keys, place = np.unique(keys, return_inverse=True)
        by, totals = np.repeat(role, sizes), []
        for model in (BACKGROUND, TARGET):
            mine = np.flatnonzero(by == model)
            for n in (seen, before):
                totals.append(np.zeros(len(keys), np.uint64))
                np.add.at(totals[-1], place[mine], n[mine])
        ends, tokens = np.cumsum(sizes), bucket.column("tokens").to_numpy()
        names, number = bucket.column("chunk").to_pylist(), bucket.column("bucket")[0].as_py()
        yield from emit(ANSWER, [[None], [number], [None], *([int(tokens[role == x].sum())] for x in (BACKGROUND, TARGET))])
        asked = np.flatnonzero(role != TARGET)
        for some in np.array_split(asked, max(1, len(asked) // 64)):
            own = [place[ends[i] - sizes[i] : ends[i]] for i in some]
            zero = np.zeros(len(some), np.int64)
            yield from emit(ANSWER, [[names[i] for i in some], np.full(len(some), number), [pressed(*(t[x] for t in totals)) for x in own], zero, zero])


def losses(counts: np.ndarray, totals: list[int]) -> np.ndarray:
    """Loss of each token in both models. ``counts``: model, (bigram, word, context), token."""
    a, b, c = MIXTURE
    out = []
    for (two, one, seen), total in zip(counts.astype(np.float64), totals):
        word = one / total if total else np.full(len(one), 1 / UNIGRAMS)
        bigram = np.divide(two, seen, out=word.copy(), where=seen > 0)
        out.append(-np.log(a * bigram + b * word + c / UNIGRAMS))
    return np.stack(out)


def score_kernel(totals: list[int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in runs(batches, ["chunk"]):
            number, piece = group.column("bucket").to_numpy(), group.column("piece")
            # equal chunks have equal answers, one set for each
            answers = [unpressed(piece[int(np.flatnonzero(number == b)[0])].as_py()) for b in np.unique(number[number >= 0])]
            told = [np.concatenate(x) for x in zip(*answers)] if answers else [np.empty(0, np.uint64)] * 4
            for i in np.flatnonzero(number < 0):
                ids, texts = unpacked_chunk(piece[int(i)].as_py())
                words = Words(texts, ALNUM)
                keys, _, _, place = counted(words, True)
                if len(words.hashes) and len(told[0]) != len(keys):
                    raise RuntimeError("a chunk of documents did not get the answers it asked for: the documents were read in another order")
                if not len(words.hashes):
                    told = [np.zeros(1, np.uint64)] * 4
                counts = np.stack([[seen[place[0]], seen[place[1]], before[place[2]]] for seen, before in (told[:2], told[2:])])
                lost = losses(counts, totals)
                mean = [np.bincount(words.docs, weights=x, minlength=len(texts)) / np.maximum(1, words.lens) for x in lost]
                yield from emit(SCORE, [ids, words.lens, mean[1], mean[0]])

    return run


def score(documents: DataFrame, targets: DataFrame, scored: DataFrame | None = None) -> DataFrame:
    """doc_id, n_tokens, target_loss, background_loss, score of ``scored`` (by default ``documents``).

    The background model counts ``documents``, the target model those of them whose doc_id ``targets`` has.
    """
    documents = settled(of_documents(documents))
    asked = documents if scored is None else settled(of_documents(scored))
    plan = Plan.of(documents)
    marked = targets.select(F.col("doc_id").cast("long")).where("doc_id is not null")
    good = documents.transform(arrow, sieve_kernel(sieve_of(marked, "doc_id")), "doc_id long, text string").join(marked, "doc_id", "left_semi")
    asks = documents.transform(arrow, ask_kernel(BACKGROUND, plan), ASK_SQL).union(good.transform(arrow, ask_kernel(TARGET, plan), ASK_SQL))
    if scored is not None:
        asks = asks.union(asked.transform(arrow, ask_kernel(UNCOUNTED, plan), ASK_SQL))
    answers = written(asks.repartition(plan.tasks, "bucket").sortWithinPartitions("bucket").transform(arrow, sum_kernel, ANSWER_SQL))
    del asks, good
    release(documents.sparkSession)
    sums = answers.where("chunk is null").agg(F.sum("tokens"), F.sum("target_tokens")).first()
    rows = text_rows(asked, plan, ANSWER, ANSWER_SQL).union(answers.where("chunk is not null"))
    found = rows.repartition(plan.tasks, "chunk").sortWithinPartitions("chunk", "bucket").transform(arrow, score_kernel([sums[0] or 0, sums[1] or 0]), SCORE_SQL)
    return found.withColumn("score", F.col("target_loss") - F.col("background_loss"))


def op10_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = finished(spark, lambda: score(documents, spark.read.parquet(f"{sf_dir}/labels.parquet").where("quality = 1")))
    return found.select("doc_id", "n_tokens", *[F.round(c, 6).alias(c) for c in ("target_loss", "background_loss", "score")])
