"""Chunks of text that ask for the keys they hold, and buckets that answer them.

A chunk is some consecutive rows of a partition. Its distinct keys are cut into buckets by their first bits, and each piece travels as one
sorted and compressed row, so a key that is everywhere travels once for each chunk and no key has a row of its own. A bucket
holds all that is said of its keys and answers every chunk in the order in which it asked. The answers then meet the chunk's text
again. Buckets grow in number with the text, and chunks with the buckets.

A chunk is known by a hash of its content, so all readings of the documents must chunk them alike: see ``graph.settled``.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetgraph.llm.textkit import arrow, emit

#: Text bytes whose keys one bucket holds; least and most text bytes of a chunk, and those it has for each bucket.
BUCKET_BYTES, LEAST_CHUNK, MOST_CHUNK, CHUNK_SHARE = 8 << 20, 4 << 20, 32 << 20, 4 << 10
#: Tasks of an exchange, at most; one holds its rows in memory, so there are as many as buckets up to this.
MOST_TASKS = 16_384


@dataclass(frozen=True)
class Plan:
    """How many bits name a bucket, and the text bytes of a chunk."""

    bits: int
    chunk_bytes: int

    @property
    def tasks(self) -> int:
        return min(MOST_TASKS, 1 << self.bits)

    @classmethod
    def of(cls, documents: DataFrame) -> Plan:
        size = int(documents.agg(F.sum(F.octet_length("text"))).first()[0] or 0)
        bits = max(0, math.ceil(math.log2(max(1, size / BUCKET_BYTES))))
        return cls(bits, min(MOST_CHUNK, max(LEAST_CHUNK, CHUNK_SHARE << bits)))


def of_documents(documents: DataFrame) -> DataFrame:
    return documents.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))


def chunks(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[tuple[pa.Array, list[bytes]]]:
    """(doc_ids, texts) of consecutive rows, about ``most`` bytes of text each."""
    ids, texts, size = [], [], 0
    for batch in batches:
        own = batch.column(batch.schema.get_field_index("doc_id")).to_pylist()
        for i, t in zip(own, batch.column(batch.schema.get_field_index("text")).cast(pa.binary()).to_pylist()):
            t = t or b""
            if size and size + len(t) > most:
                yield pa.array(ids, pa.int64()), texts
                ids, texts, size = [], [], 0
            ids.append(i)
            texts.append(t)
            size += len(t)
    if ids:
        yield pa.array(ids, pa.int64()), texts


def chunk_name(ids: pa.Array, texts: list[bytes]) -> bytes:
    h = xxhash.xxh3_128(repr(ids.to_pylist()).encode())
    h.update(np.fromiter(map(len, texts), np.int64, len(texts)).tobytes())
    h.update(b"".join(texts))
    return h.digest()


def bucket_cuts(keys: np.ndarray, bits: int) -> np.ndarray:
    """Where each bucket's keys begin among the sorted ``keys``, and their end."""
    return np.append(np.searchsorted(keys, np.arange(1 << bits, dtype=np.uint64) << np.uint64(64 - bits)), len(keys)) if bits else np.array([0, len(keys)])


def packed_chunk(ids: pa.Array, texts: list[bytes]) -> bytes:
    sink = pa.BufferOutputStream()
    table = pa.RecordBatch.from_arrays([ids, pa.array(texts, pa.binary())], ["doc_id", "text"])
    with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
        w.write_batch(table)
    return sink.getvalue().to_pybytes()


def unpacked_chunk(data: bytes) -> tuple[pa.Array, list[bytes]]:
    table = pa.ipc.open_stream(data).read_all()
    return table.column("doc_id").combine_chunks(), table.column("text").to_pylist()


def text_rows(documents: DataFrame, plan: Plan, schema: pa.Schema, sql: str) -> DataFrame:
    """The chunks themselves as rows of ``schema``: their name, bucket -1, their text in ``piece``, and zeros elsewhere, so that they sort before their answers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, texts in chunks(batches, plan.chunk_bytes):
            given = {"chunk": chunk_name(ids, texts), "bucket": -1, "piece": packed_chunk(ids, texts)}
            yield from emit(schema, [[given.get(name, 0)] for name in schema.names])

    return documents.transform(arrow, run, sql)
