"""Benchmark decontamination with a distributed positional inverted index.

``build_index`` stores the training tokens' postings as a table. A row is a shard, some consecutive documents of a
partition: its terms, for each term the sorted places where the shard has it, and where its documents begin. The table is
partitioned by document, so nothing is shuffled to build it, and a frequent term is cut up by shards.

A query is a run of words. On a shard it starts from the list of its rarest word there, shifted by the word's offset to candidate
starts; the other words' lists, shifted likewise, are intersected with them from rare to frequent. Words that the shard lacks
end the search at once. The texts are not looked at again. A proximity query asks instead that every word
has a place near one of the rarest word's.

Test windows (13 consecutive words of an item, or all words of a shorter item) are phrase queries. They travel to the shards in slices of a
checked size, one slice on the driver at a time; with several slices the hits, not the documents, are put together by shard and row.

Rows. Null and wordless texts have no words and no hits. A null benchmark text has no
windows; an item without item_id still makes hits but is not listed. Repeated rows each get a
row. Other columns are ignored by the index and kept by ``clean``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from facetgraph.llm.graph import written
from facetgraph.llm.textkit import ALNUM, Words, arrow, emit, in_sieve, numbers, pressed, sieve_of, text_chunks, unpressed

WINDOW = 13
#: A document is contaminated when SHARE times its hit words reach its words.
SHARE = 20
#: Bytes of benchmark text whose windows travel to the executors at once.
SLICE_BYTES = 16 << 20

#: ``postings``: packed arrays of the documents' first places, the sorted terms, where each term's list begins, and the lists.
SHARD = pa.schema([("shard", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("text_hashes", pa.list_(pa.int64())), ("postings", pa.binary())])
SHARD_SQL = "shard long, doc_ids array<long>, text_hashes array<long>, postings binary"
SPAN = pa.struct([("a", pa.int64()), ("b", pa.int64())])
HITS = pa.schema([("shard", pa.int64()), ("row", pa.int32()), ("doc_id", pa.int64()), ("text_hash", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("items", pa.list_(pa.int64())), ("spans", pa.list_(SPAN))])
HITS_SQL = "shard long, row int, doc_id long, text_hash long, n_words long, n_hit long, items array<long>, spans array<struct<a:long,b:long>>"
FOUND = pa.schema([("query_id", pa.int64()), ("doc_id", pa.int64()), ("start", pa.int64())])


def index_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids, hashes = batch.column(batch.schema.get_field_index("doc_id")), numbers(batch, "text_hash")
        for at, texts in text_chunks(batch):
            words, n = Words(texts, ALNUM), len(texts)
            places = np.argsort(words.hashes, kind="stable").astype(np.int32)
            terms, begin = np.unique(words.hashes[places], return_index=True)
            lists = np.append(begin, len(places)).astype(np.int32)
            rows = [[at], [ids.slice(at, n).to_pylist()], [hashes[at : at + n]], [pressed(words.starts.astype(np.int32), terms, lists, places)]]
            yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(rows, SHARD)], schema=SHARD)


def build_index(documents: DataFrame) -> DataFrame:
    """The stored index: one row for each shard of documents."""
    docs = documents.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).withColumn("text_hash", F.xxhash64("text"))
    return written(docs.transform(arrow, index_kernel, SHARD_SQL).withColumn("shard", F.monotonically_increasing_id()))


class Shard:
    """A row of the index, ready to be searched."""

    def __init__(self, batch: pa.RecordBatch, i: int):
        get = lambda name: batch.column(batch.schema.get_field_index(name))[i].values
        self.shard = batch.column(batch.schema.get_field_index("shard"))[i].as_py()
        self.doc_ids, self.text_hashes = get("doc_ids"), np.asarray(get("text_hashes"))
        starts, self.terms, lists, places = unpressed(batch.column(batch.schema.get_field_index("postings"))[i].as_py())
        self.starts, self.lists, self.places = starts.astype(np.int64), lists.astype(np.int64), places.astype(np.int64)

    def numbers(self, terms: np.ndarray) -> np.ndarray:
        """The shard's numbers of terms, -1 for those that it lacks."""
        if not len(self.terms):
            return np.full(len(terms), -1)
        at = np.minimum(np.searchsorted(self.terms, terms), len(self.terms) - 1)
        return np.where(self.terms[at] == terms, at, -1)

    def list_of(self, number: int) -> np.ndarray:
        return self.places[self.lists[number] : self.lists[number + 1]]

    def document(self, place: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.starts, place, side="right") - 1

    def phrase(self, row: np.ndarray) -> np.ndarray:
        """Places where the terms stand consecutively in one document; ``row``: their numbers, none of them -1."""
        rare = np.argsort(self.lists[row + 1] - self.lists[row], kind="stable").tolist()
        at = self.list_of(row[rare[0]]) - rare[0]
        for j in rare[1:]:
            if not len(at):
                return at
            there = self.list_of(row[j])
            want = at + j
            at = at[there[np.minimum(np.searchsorted(there, want), len(there) - 1)] == want]
        return at[(at >= 0) & (self.document(at) == self.document(at + len(row) - 1))] if len(at) else at

    def proximity(self, row: np.ndarray, within: int) -> np.ndarray:
        """Places of the rarest term with every other term at most ``within`` words away in the same document."""
        rare = np.argsort(self.lists[row + 1] - self.lists[row], kind="stable")
        at = self.list_of(row[rare[0]])
        for j in rare[1:].tolist():
            there = self.list_of(row[j])
            low, high = self.starts[self.document(at)], self.starts[self.document(at) + 1]
            at = at[np.searchsorted(there, np.maximum(low, at - within)) < np.searchsorted(there, np.minimum(high, at + within + 1))]
        return at


@dataclass
class Windows:
    """Test windows as a matrix of term numbers, -1 beyond a short window's end."""

    terms: np.ndarray
    matrix: np.ndarray
    lens: np.ndarray
    items: list[list[int]]

    @classmethod
    def of(cls, items: list[tuple[int | None, str | None]], width: int) -> Windows:
        words = Words([(t or "").encode() for _, t in items], ALNUM)
        terms, number = np.unique(words.hashes, return_inverse=True)
        seen: dict[tuple[int, ...], set] = {}
        for (item, _), a, b in zip(items, words.starts.tolist(), words.starts[1:].tolist()):
            row = number[a:b].tolist()
            for at in range(max(1, len(row) - width + 1) if row else 0):
                seen.setdefault(tuple(row[at : at + width]), set()).add(item)
        matrix = np.full((len(seen), width), -1, np.int64)
        for i, w in enumerate(seen):
            matrix[i, : len(w)] = w
        return cls(terms, matrix, np.fromiter(map(len, seen), np.int64, len(seen)), [[x for x in s if x is not None] for s in seen.values()])


def hits(shard: Shard, windows: Windows) -> tuple[np.ndarray, dict[int, list[tuple[int, int]]], dict[int, set]]:
    """Hit words of each document of the shard, the merged spans and the items of those that have any."""
    own = np.append(shard.numbers(windows.terms), -2)
    rows = own[windows.matrix]
    spans: dict[int, list[tuple[int, int]]] = {}
    items: dict[int, set] = {}
    for w in np.flatnonzero((rows != -1).all(axis=1)):
        n = int(windows.lens[w])
        at = shard.phrase(rows[w, :n])
        for d, p in zip(shard.document(at).tolist(), at.tolist()):
            p -= int(shard.starts[d])
            spans.setdefault(d, []).append((p, p + n))
            items.setdefault(d, set()).update(windows.items[w])
    spans = {d: merge_spans(x) for d, x in spans.items()}
    hit = np.zeros(len(shard.starts) - 1, np.int64)
    for d, x in spans.items():
        hit[d] = sum(b - a for a, b in x)
    return hit, spans, items


def merge_spans(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def hits_kernel(windows: Windows, every: bool):
    """A row for each document, or for those with hits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                shard = Shard(batch, i)
                hit, spans, items = hits(shard, windows)
                rows = np.arange(len(hit)) if every else np.flatnonzero(hit)
                listed = [sorted(items.get(d, ())) for d in rows.tolist()]
                marked = [[{"a": a, "b": b} for a, b in spans.get(d, ())] for d in rows.tolist()]
                yield from emit(HITS, [np.full(len(rows), shard.shard), rows.astype(np.int32), shard.doc_ids.take(pa.array(rows)), shard.text_hashes[rows], np.diff(shard.starts)[rows], hit[rows], listed, marked])

    return run


def united_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        spans = [merge_spans([(x["a"], x["b"]) for x in s]) for s in batch.column(batch.schema.get_field_index("spans")).to_pylist()]
        items = [sorted(set(x)) for x in batch.column(batch.schema.get_field_index("items")).to_pylist()]
        get = lambda name: batch.column(batch.schema.get_field_index(name))
        yield pa.RecordBatch.from_arrays([get("shard"), get("row"), get("doc_id"), get("text_hash"), get("n_words"), pa.array([sum(b - a for a, b in s) for s in spans], pa.int64()), pa.array(items, pa.list_(pa.int64())), pa.array([[{"a": a, "b": b} for a, b in s] for s in spans], pa.list_(SPAN))], schema=HITS)


def slices(benchmark: DataFrame, width: int, slice_bytes: int) -> Iterator[Windows]:
    """The benchmark's windows, in slices that each hold about ``slice_bytes`` of text; one is read at a time."""
    rows = benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string")).where("text is not null")
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(1, -(-int(size) // slice_bytes))
    part = rows.withColumn("part", F.pmod(F.xxhash64("item_id", "text"), F.lit(n)))
    for i in range(n):
        yield Windows.of([(r["item_id"], r["text"]) for r in part.where(F.col("part") == i).collect()], width)


def document_hits(index: DataFrame, benchmark: DataFrame, width: int = WINDOW, slice_bytes: int = SLICE_BYTES) -> DataFrame:
    """shard, row, doc_id, text_hash, n_words, n_hit, items and merged hit spans of every indexed document."""
    parts = slices(benchmark, width, slice_bytes)
    first = next(parts)
    found = index.transform(arrow, hits_kernel(first, True), HITS_SQL)
    # of later slices only the documents with hits
    more = [index.transform(arrow, hits_kernel(w, False), HITS_SQL) for w in parts]
    if not more:
        return found
    for x in more:
        found = found.union(x)
    key = ["shard", "row"]
    whole = found.groupBy(*key).agg(*[F.first(c).alias(c) for c in ("doc_id", "text_hash", "n_words")], F.lit(0).cast("long").alias("n_hit"), F.flatten(F.collect_list("items")).alias("items"), F.flatten(F.collect_list("spans")).alias("spans"))
    return whole.transform(arrow, united_kernel, HITS_SQL)


def contaminated(n_hit: Column, n_words: Column) -> Column:
    return (n_hit > 0) & (SHARE * n_hit >= n_words)


def clean(documents: DataFrame, benchmark: DataFrame, **settings) -> DataFrame:
    """``documents`` without the contaminated ones, with their own columns.

    Rows whose hash the contaminated ones' sieve lacks pass at once; the others are joined with them by doc_id and text hash.
    """
    bad = document_hits(build_index(documents), benchmark, **settings).where(contaminated(F.col("n_hit"), F.col("n_words")))
    bad = written(bad.select(F.col("doc_id").alias("__d"), F.col("text_hash").alias("__t")).distinct())
    table = sieve_of(bad, "__t")

    @F.pandas_udf("boolean")
    def maybe(hashes: pd.Series) -> pd.Series:
        return pd.Series(in_sieve(table, hashes.to_numpy()))

    marked = documents.withColumn("__h", F.xxhash64(F.col("text").cast("string"))).withColumn("__maybe", maybe("__h"))
    held = marked.where("__maybe").join(bad, F.col("doc_id").cast("long").eqNullSafe(F.col("__d")) & (F.col("__h") == F.col("__t")), "left_anti")
    return marked.where(~F.col("__maybe")).select(documents.columns).union(held.select(documents.columns))


def search(index: DataFrame, queries: DataFrame, within: int | None = None) -> DataFrame:
    """(query_id, doc_id, start): where a query's ``words`` stand consecutively, or with ``within`` the places of its rarest word in the shard
    with every other word at most so many words away. Words are taken as documents' words are; a query without words finds nothing.

    Queries are few against the index; they reach the shards in slices of SLICE_BYTES.
    """
    rows = queries.select(F.col("query_id").cast("long"), F.array_join("words", " ").alias("text"))
    n = max(1, -(-int(rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // SLICE_BYTES))
    out = None
    for i in range(n):
        asked = [(r["query_id"], Words([r["text"].encode()], ALNUM).hashes) for r in rows.where(F.pmod(F.xxhash64("query_id"), F.lit(n)) == i).collect()]

        def run(batches: Iterator[pa.RecordBatch], asked=asked) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for j in range(batch.num_rows):
                    shard = Shard(batch, j)
                    for query, terms in asked:
                        row = shard.numbers(terms if within is None else np.unique(terms))
                        if not len(row) or (row < 0).any():
                            continue
                        at = shard.phrase(row) if within is None else shard.proximity(row, within)
                        d = shard.document(at)
                        yield from emit(FOUND, [np.full(len(at), query), shard.doc_ids.take(pa.array(d, pa.int64())), at - shard.starts[d]])

        found = index.transform(arrow, run, "query_id long, doc_id long, start long")
        out = found if out is None else out.union(found)
    return out.distinct()


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = build_index(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    found = document_hits(index, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    listed = F.array_join(F.array_sort(F.transform("items", lambda i: i.cast("string"))), ",")
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(listed, 256).alias("items_sha256"), contaminated(F.col("n_hit"), F.col("n_words")).alias("contaminated"))
