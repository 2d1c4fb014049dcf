"""Tokens, hashes and streaming helpers that the Arrow kernels of this subpackage share.

Texts are handled as UTF-8 bytes. ``bytes.lower`` changes A-Z alone and
``bytes.split`` cuts at the six ASCII blanks alone, which is what the
operators' contracts ask for; ``word_bytes`` keeps digits, letters and every
byte of a non-ASCII character.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Every byte that is no digit, lower-case letter or part of a non-ASCII character becomes a blank.
WORD_TABLE = bytes(b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 0x20 for b in range(256))
#: The same with A-Z lowered, and the words between the six ASCII blanks with A-Z lowered.
ALNUM = WORD_TABLE[:0x41] + bytes(range(0x61, 0x7B)) + WORD_TABLE[0x5B:]
BLANK = bytes(0x20 if b in b" \t\n\r\v\f" else b + 0x20 if 0x41 <= b <= 0x5A else b for b in range(256))
#: Text bytes that a kernel tokenises at once; bounds a worker's memory whatever the batch.
CHUNK_BYTES = 2 << 20


def blank_words(text: bytes) -> list[bytes]:
    return text.lower().split()


def alnum_words(text: bytes) -> list[bytes]:
    return text.lower().translate(WORD_TABLE).split()


def text_chunks(batch: pa.RecordBatch, column: str = "text", most: int = CHUNK_BYTES) -> Iterator[tuple[int, list[bytes]]]:
    """(offset, texts) slices of a batch of about ``most`` bytes; null is empty."""
    col = batch.column(batch.schema.get_field_index(column))
    sizes = np.nan_to_num(np.asarray(pa.compute.binary_length(col).to_numpy(zero_copy_only=False), dtype=np.float64)).astype(np.int64)
    ends = np.cumsum(sizes)
    start = 0
    while start < len(sizes):
        base = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, base + most, side="right")))
        yield start, [x or b"" for x in col.slice(start, stop - start).cast(pa.binary()).to_pylist()]
        start = stop


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser on uint64: every bit of the input reaches every bit of the output."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Words:
    """Words of several documents as one array of 64-bit hashes: ``hashes[starts[i]:starts[i+1]]`` are document i's.

    No word becomes a Python object: the texts are one buffer, and a word's hash is the difference of two
    prefix sums of it, a polynomial over its bytes, mixed with its length.
    """

    BASE = 0x9E3779B97F4A7C15
    #: Bytes whose sums are in memory at once; longer words than LONG are hashed by themselves.
    BLOCK, LONG = 1 << 20, 1 << 20

    def __init__(self, texts: list[bytes], table: bytes):
        joined = b" ".join(texts).translate(table)
        data = np.frombuffer(joined + b" ", np.uint8)
        inside = data != 0x20
        edge = np.flatnonzero(inside[1:] != inside[:-1]) + 1
        if inside[0]:
            edge = np.concatenate([[0], edge])
        first, last = edge[::2], edge[1::2]
        self.hashes = np.empty(len(first), np.uint64)
        at = 0
        while at < len(first):
            base = int(first[at])
            stop = max(at + 1, int(np.searchsorted(first, base + self.BLOCK)))
            end = min(int(last[stop - 1]), base + self.BLOCK + self.LONG)
            up, down = self.powers(end - base + 1)
            sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum((data[base:end].astype(np.uint64) + np.uint64(1)) * down[: end - base], dtype=np.uint64)])
            x, y = first[at:stop] - base, np.minimum(last[at:stop], end) - base
            self.hashes[at:stop] = mix((sums[y] - sums[x]) * up[x] + mix((last[at:stop] - first[at:stop]).astype(np.uint64)))
            at = stop
        for i in np.flatnonzero(last - first > self.LONG):
            self.hashes[i] = xxhash.xxh3_64_intdigest(joined[first[i] : last[i]], 3)
        ends = np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)) + 1)
        self.starts = np.concatenate([[0], np.searchsorted(first, ends)]).astype(np.int64)
        self._place()

    @classmethod
    def powers(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        """The first n powers of the base and of its inverse."""
        rise = lambda base: np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(n, base, np.uint64)]), dtype=np.uint64)
        return rise(cls.BASE), rise(pow(cls.BASE, -1, 1 << 64))

    def _place(self) -> None:
        self.lens = np.diff(self.starts)
        self.docs = np.repeat(np.arange(len(self.lens)), self.lens)
        self.pos = np.arange(self.starts[-1]) - self.starts[self.docs]

    def grams(self, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(hash, document, position) of every run of k words inside a document."""
        n = len(self.hashes) - k + 1
        if n <= 0:
            return np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64)
        acc = np.zeros(n, np.uint64)
        for j in range(k):
            acc = acc * np.uint64(self.BASE) + self.hashes[j : j + n]
        keep = self.pos[:n] + k <= self.lens[self.docs[:n]]
        return mix(acc[keep]), self.docs[:n][keep], self.pos[:n][keep]

    def shingles(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(hash, document) of k-word runs; a shorter document has its whole sequence as one."""
        h, d, _ = self.grams(k)
        short = [i for i in np.flatnonzero((self.lens > 0) & (self.lens < k))]
        if short:
            whole = np.fromiter((xxhash.xxh3_64_intdigest(self.hashes[self.starts[i] : self.starts[i + 1]].tobytes(), 7) for i in short), np.uint64, len(short))
            h, d = np.concatenate([h, whole]), np.concatenate([d, np.asarray(short)])
            order = np.argsort(d, kind="stable")
            h, d = h[order], d[order]
        return h, d


class Tokens(Words):
    """Words with their spellings: ``codes`` index ``vocabulary``, the distinct words of the chunk, whose hashes are ``table``."""

    def __init__(self, texts: list[bytes], split=blank_words):
        parts = [split(t) for t in texts]
        self.starts = np.concatenate([[0], np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)))]).astype(np.int64)
        flat: list[bytes] = []
        for p in parts:
            flat += p
        coded = pa.array(flat, pa.binary()).dictionary_encode()
        self.vocabulary: list[bytes] = coded.dictionary.to_pylist()
        self.codes = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
        self.table = np.fromiter((xxhash.xxh3_64_intdigest(w) for w in self.vocabulary), np.uint64, len(self.vocabulary))
        self.hashes = self.table[self.codes] if len(flat) else np.empty(0, np.uint64)
        self._place()


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def pressed(*columns: np.ndarray) -> bytes:
    """Arrays of numbers, each byte plane by byte plane and compressed; sorted keys and small counts shrink most."""
    out = []
    for c in columns:
        width = c.dtype.itemsize
        body = pa.compress(np.ascontiguousarray(c).view(np.uint8).reshape(-1, width).T.tobytes(), "zstd", asbytes=True) if len(c) else b""
        out += [bytes([width]), len(c).to_bytes(4, "little"), len(body).to_bytes(4, "little"), body]
    return b"".join(out)


def unpressed(data: bytes) -> list[np.ndarray]:
    """The arrays, as unsigned numbers of their widths."""
    out, at = [], 0
    while at < len(data):
        width, n, size = data[at], int.from_bytes(data[at + 1 : at + 5], "little"), int.from_bytes(data[at + 5 : at + 9], "little")
        body = pa.decompress(data[at + 9 : at + 9 + size], n * width, "zstd", asbytes=True) if n else b""
        out.append(np.frombuffer(body, np.uint8).reshape(width, -1).T.copy().view(f"u{width}").reshape(-1) if n else np.empty(0, f"u{width}"))
        at += 9 + size
    return out


def runs(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Groups of a stream sorted by ``keys``: one table for each, only one in memory."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(batch.schema.get_field_index(k)).to_numpy(zero_copy_only=False) for k in keys]
        new = np.zeros(batch.num_rows, bool)
        for c in cols:
            new[1:] |= c[1:] != c[:-1]
        cuts = [0, *np.flatnonzero(new), batch.num_rows]
        for a, b in zip(cuts, cuts[1:]):
            key = tuple(c[a] for c in cols)
            if held and key != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = key
    if held:
        yield pa.Table.from_batches(held)


def numbers(table: pa.Table | pa.RecordBatch, name: str) -> np.ndarray:
    return table.column(name).to_numpy() if isinstance(table, pa.Table) else table.column(table.schema.get_field_index(name)).to_numpy(zero_copy_only=False)


def emit(schema: pa.Schema, columns: list, most: int = 200_000) -> Iterator[pa.RecordBatch]:
    arrays = [pa.array(c, type=f.type, from_pandas=False) if not isinstance(c, (pa.Array, pa.ChunkedArray)) else c for c, f in zip(columns, schema)]
    n = len(arrays[0])
    for a in range(0, n, most):
        yield pa.RecordBatch.from_arrays([x.slice(a, most) for x in arrays], schema=schema)


def trim() -> None:
    """Returns what this process has freed to the system."""
    import ctypes

    pa.default_memory_pool().release_unused()
    give = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if give:
        give(0)


def given_back(kernel):
    """``kernel``, which returns its memory to the system when its task ends: workers are kept for other tasks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from kernel(batches)
        finally:
            trim()

    return run


def arrow(df: DataFrame, kernel, schema: str) -> DataFrame:
    """``df.mapInArrow`` with a kernel that gives its memory back; for ``df.transform``."""
    return df.mapInArrow(given_back(kernel), schema)


#: Bits of a sieve: its size is fixed, so it lets more through as its keys grow and never keeps any out.
SIEVE_BITS = 1 << 24


def _sieve_cell(ids: np.ndarray) -> np.ndarray:
    return (mix(ids.astype(np.int64).view(np.uint64)) & np.uint64(SIEVE_BITS - 1)).astype(np.int64)


def sieve_of(rows: DataFrame, column: str) -> np.ndarray:
    """A bit table of ``column``'s values, built in the executors: 512 rows of 4 KB reach the driver, whatever the rows."""

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(_sieve_cell(batch.column(0).to_numpy(zero_copy_only=False)))], ["cell"])

    cell = rows.select(F.col(column).cast("long")).where(F.col(column).isNotNull()).transform(arrow, cells, "cell long")
    parts = cell.groupBy(F.expr("bitmap_bucket_number(cell)").alias("b")).agg(F.expr("bitmap_construct_agg(bitmap_bit_position(cell))").alias("bits")).collect()
    table = np.zeros((SIEVE_BITS // 32768 + 2, 4096), np.uint8)
    for part in parts:
        table[part["b"]] = np.frombuffer(part["bits"], np.uint8)
    return table


def in_sieve(table: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Which ids the sieve lets through."""
    cell = _sieve_cell(ids)
    # bitmap_bucket_number counts from 1: values 1 to 32768 are bucket 1, and 0 is bucket 0
    bucket = np.where(cell > 0, 1 + (cell - 1) // 32768, 0)
    at = np.where(cell > 0, (cell - 1) % 32768, 0)
    return ((table[bucket, at // 8] >> (at % 8).astype(np.uint8)) & 1).astype(bool)


def sieve_kernel(table: np.ndarray, column: str = "doc_id"):
    """Keeps the rows whose ``column`` the sieve has, and few others: it spares a shuffle most of the rows that a join would drop."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            col = batch.column(batch.schema.get_field_index(column))
            yield batch.filter(pa.array(in_sieve(table, col.fill_null(0).to_numpy(zero_copy_only=False))))

    return run
