"""N-gram Jaccard join by T-occurrence search (DivideSkip), as connected components.

A document is its set of distinct five-word shingles. Two link when their Jaccard
similarity reaches the threshold, which is a T-occurrence problem: of the
document's inverted lists a partner must be on at least T. DivideSkip sets some of the
longest lists aside, merges the rest with a heap that skips what cannot reach T, and probes the long ones.

Distribution. List lengths are estimated for all documents by a table of fixed
size, so "shortest lists first" is one global order. A document is posted under its
``n - ceil(t n) + 1`` shortest lists only; linked documents share at least one of
them. A posted list's smallest document leads it, and every document of the list joins the leader's block.

Blocks carry signatures, not sets: bit b of a document's signature says whether an odd number of its shingles
hash to b. The bits in which two signatures differ are at most the shingles in which the sets differ, so pairs whose
signatures are too far apart cannot link, and no link is lost. What remains forms clusters; every
document of a cluster is sent there once with its text, and there the T-occurrence search runs.

A cluster above ``BLOCK_ROWS`` documents is dealt into chunks. Each chunk, with the cluster's first document as a pivot, is searched by itself.
Documents that did not come to the pivot's component are then searched against every chunk; a group of near copies of
any size has next to none of them.

Copies (equal word sequences) are one class from the start, so a group of
copies of any size is one document to the join.

Rows. Null, empty and wordless texts link with nothing and are their own component.
Rows without doc_id have n_shingles, a null component and no links. Rows that share a
doc_id count as one document (their shingles are those of the row with the greatest class hash); each gets a row in the result. Other columns
of the input are ignored.
"""

from __future__ import annotations

import heapq
import math
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetgraph.llm.graph import components, cut, finished, release, written
from facetgraph.llm.textkit import BLANK, Words, arrow, emit, in_sieve, numbers, runs, sieve_kernel, sieve_of, signed, text_chunks

WORDS = 5
#: Jaccard threshold as a fraction of integers.
NUMERATOR, DENOMINATOR = 80, 100
#: Cells of the list-length table; fixed, whatever the corpus.
LENGTH_CELLS = 1 << 16
#: Documents, and shingles, in one search block; larger clusters are searched chunk by chunk.
BLOCK_ROWS, BLOCK_SHINGLES = 1024, 1 << 20
#: DivideSkip's weight of probes against merges, which sets how many lists are set aside.
PROBE_COST = 0.0085
#: Postings up to which short lists are merged by the heap; more are counted by one sort.
HEAP_MOST = 2048

SCAN = pa.schema([("kind", pa.int32()), ("a", pa.int64()), ("b", pa.int64()), ("c", pa.int64()), ("n", pa.int64()), ("sig", pa.binary())])
POSTING = pa.schema([("shingle", pa.int64()), ("doc_id", pa.int64())])
LINK = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def sets_of(texts: list[bytes], k: int, rank: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, Words]:
    """(hash, document) of the distinct shingles, sorted inside each document, and each document's count.

    With ``rank`` a hash is rearranged, without loss, to sort by the length of its list.
    """
    words = Words(texts, BLANK)
    h, d = words.shingles(k)
    if rank is not None:
        h = (rank[(h & np.uint64(LENGTH_CELLS - 1)).astype(np.int64)] << np.uint64(48)) | (h >> np.uint64(16))
    ends = np.cumsum(np.bincount(d, minlength=len(texts)))
    for a, b in zip(ends - np.diff(ends, prepend=0), ends):
        h[a:b].sort()
    first = np.ones(len(h), bool)
    first[1:] = (h[1:] != h[:-1]) | (d[1:] != d[:-1])
    h, d = h[first], d[first]
    return h, d, np.bincount(d, minlength=len(texts)), words


def signatures(h: np.ndarray, d: np.ndarray, n: np.ndarray) -> list[bytes]:
    """A parity bit table for each document, of the power of two of bits from twice its shingles, 64 at least."""
    bits = np.maximum(64, 1 << np.ceil(np.log2(np.maximum(1, 2 * n))).astype(np.int64))
    ends = np.cumsum(bits)
    place = (ends - bits)[d] + ((h >> np.uint64(20)) & (bits[d] - 1).astype(np.uint64)).astype(np.int64)
    packed = np.packbits((np.bincount(place, minlength=int(bits.sum())) & 1).astype(np.uint8), bitorder="little")
    return [packed[a:b].tobytes() for a, b in zip((ends - bits) // 8, ends // 8)]


def scan_kernel(k: int):
    """kind 0: (cell, -, -, occurrences). kind 1: (doc_id, class hash in two halves, set size, signature)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = np.zeros(LENGTH_CELLS, np.int64)
        for batch in batches:
            ids = batch.column(batch.schema.get_field_index("doc_id"))
            for at, texts in text_chunks(batch):
                h, d, n, words = sets_of(texts, k)
                cells += np.bincount((h & np.uint64(LENGTH_CELLS - 1)).astype(np.int64), minlength=LENGTH_CELLS)
                whole = [xxhash.xxh3_128_digest(words.hashes[a:b].tobytes()) for a, b in zip(words.starts, words.starts[1:])]
                two = np.frombuffer(b"".join(whole), np.int64).reshape(-1, 2)
                yield from emit(SCAN, [np.ones(len(n), np.int32), ids.slice(at, len(n)), two[:, 0].copy(), two[:, 1].copy(), n, signatures(h, d, n)])
        full = np.flatnonzero(cells)
        zero = np.zeros(len(full), np.int64)
        yield from emit(SCAN, [zero.astype(np.int32), full, zero, zero, cells[full], pa.nulls(len(full), pa.binary())])

    return run


def posting_kernel(k: int, num: int, den: int, rank: np.ndarray, chosen: np.ndarray):
    """(list, doc_id) for the shortest lists of the documents that the sieve lets through."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            batch = batch.filter(pa.array(in_sieve(chosen, numbers(batch, "doc_id"))))
            ids = numbers(batch, "doc_id")
            for at, texts in text_chunks(batch):
                h, d, n, _ = sets_of(texts, k, rank)
                within = np.arange(len(h)) - (np.cumsum(n) - n)[d]
                short = within < prefix(n, num, den)[d]
                yield from emit(POSTING, [signed(h[short]), ids[at + d[short]]])

    return run


def prefix(n, num: int, den: int):
    """Lists under which a document of n shingles is posted."""
    return n - (n * num + den - 1) // den + 1


class Forest:
    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    def join(self, x: int, y: int) -> None:
        x, y = sorted((self.root(x), self.root(y)))
        self.up[y] = x

    def roots(self) -> np.ndarray:
        return np.asarray([self.root(x) for x in range(len(self.up))], np.int64)


def least_overlap(n, m, num: int, den: int):
    return -(-num * (n + m) // (num + den))


def folded(sig: np.ndarray) -> np.ndarray:
    """Signatures (rows of 64-bit words) as they are in a table of half the bits."""
    half = sig.shape[1] // 2
    return sig[:, :half] ^ sig[:, half:]


def near_by_signature(n: np.ndarray, sigs: list[bytes], num: int, den: int) -> Forest:
    """Components of the pairs whose signatures leave the needed overlap possible; rows come in ascending n."""
    forest = Forest(len(n))
    size = np.fromiter(map(len, sigs), np.int64, len(sigs))
    begin = np.append(np.flatnonzero(np.append(True, size[1:] != size[:-1])), len(size))
    tables = [np.frombuffer(b"".join(sigs[a:b]), np.uint64).reshape(b - a, -1) for a, b in zip(begin, begin[1:])]
    for t, a in enumerate(begin[:-1]):
        mine = tables[t]
        # smaller documents may have smaller tables: down to those of the smallest admissible partner
        for s in range(t, -1, -1):
            while mine.shape[1] > tables[s].shape[1]:
                mine = folded(mine)
            if n[begin[s + 1] - 1] * den < n[a] * num:
                break
            for x in range(a, begin[t + 1]):
                start, stop = max(begin[s], int(np.searchsorted(n, -(-int(n[x]) * num // den)))), min(x, begin[s + 1])
                if start < stop:
                    apart = np.bitwise_count(tables[s][start - begin[s] : stop - begin[s]] ^ mine[x - a]).sum(axis=1, dtype=np.int64)
                    for y in np.flatnonzero(apart <= n[start:stop] + n[x] - 2 * least_overlap(n[start:stop], n[x], num, den)).tolist():
                        forest.join(x, start + y)
    return forest


def candidate_kernel(num: int, den: int):
    """(document, smallest document of its candidates) of each block of a leader."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in runs(batches, ["leader", "i", "j"]):
            if block.num_rows < 2:
                continue
            ids, n = numbers(block, "doc_id"), numbers(block, "n").astype(np.int64)
            order = np.lexsort((ids, n))
            sigs = block.column("sig").to_pylist()
            roots = near_by_signature(n[order], [sigs[i] for i in order], num, den).roots()
            ids = ids[order]
            apart = np.flatnonzero(roots != np.arange(len(ids)))
            if len(apart):
                yield from emit(LINK, [ids[apart], ids[roots[apart]]])

    return run


def merge_skip(lists: list[list[int]], t: int) -> dict[int, int]:
    """How many of the sorted lists hold each document that at least t of them hold."""
    heap = [(x[0], i, 0) for i, x in enumerate(lists)]
    heapq.heapify(heap)
    out = {}
    while len(heap) >= t:
        top, held = heap[0][0], []
        while heap and heap[0][0] == top:
            held.append(heapq.heappop(heap))
        if len(held) >= t:
            out[top] = len(held)
            bound = top + 1
        else:
            # no document before the t-th head can be on t lists
            while heap and len(held) < t - 1:
                held.append(heapq.heappop(heap))
            if not heap:
                break
            bound = heap[0][0]
        for _, i, at in held:
            at = bisect_left(lists[i], bound, at)
            if at < len(lists[i]):
                heapq.heappush(heap, (lists[i][at], i, at))
    return out


def at_least(lists: list[np.ndarray], t: int, heap_most: int) -> dict[int, int]:
    """``merge_skip``; for many postings the same counts from one sort."""
    if sum(map(len, lists)) <= heap_most:
        return merge_skip([x.tolist() for x in lists], t)
    who, count = np.unique(np.concatenate(lists), return_counts=True)
    return dict(zip(who[count >= t].tolist(), count[count >= t].tolist()))


def divide_skip(ids: np.ndarray, sets: list[np.ndarray], side: np.ndarray | None, num: int, den: int, heap_most: int = HEAP_MOST) -> np.ndarray:
    """For each document of a block the smallest doc_id of its component.

    Documents come in the order of their sizes; each is searched for among those before it
    that are not yet of its component. ``side``: only pairs of different sides.
    """
    order = np.lexsort((ids, [len(x) for x in sets]))
    ids, sets = ids[order], [sets[x] for x in order]
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    side = None if side is None else side[order]
    flat, who = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
    by = np.lexsort((who, flat))
    flat, who = flat[by], who[by]
    new = np.ones(len(flat), bool)
    new[1:] = flat[1:] != flat[:-1]
    number = np.cumsum(new) - 1
    starts = np.append(np.flatnonzero(new), len(flat))
    length = np.diff(starts)
    #: (list, document) as one sorted key: a binary probe of any list is a search in this array.
    keys = number * len(sets) + who
    own = np.empty(len(flat), np.int64)
    own[by] = number
    ends = np.cumsum(sizes)
    # rows of one doc_id are one document from the start
    label = np.unique(ids, return_inverse=True)[1]

    def on(lists: np.ndarray, y: int) -> int:
        probe = lists * len(sets) + y
        at = np.searchsorted(keys, probe)
        return int(np.count_nonzero(keys[np.minimum(at, len(keys) - 1)] == probe))

    def join(x: int, y: int) -> None:
        a, b = sorted((label[x], label[y]))
        label[label == b] = a

    for x, n in enumerate(sizes.tolist()):
        mine = own[ends[x] - n : ends[x]]
        mine = mine[length[mine] > 1]
        least = -(-n * num // den)
        alive = np.zeros(len(sets), bool)
        alive[np.searchsorted(sizes, least) : x] = True
        if side is not None:
            alive &= side != side[x]
        # the overlap T that the smallest admissible partner must reach
        t = max(1, int(least_overlap(n, least, num, den)))
        if len(mine) < t or not alive.any():
            continue
        # the first admissible document of each of the largest components is tried beforehand: near copies need no search
        heads, first, count = np.unique(label[alive], return_index=True, return_counts=True)
        for y in np.flatnonzero(alive)[first[np.argsort(-count, kind="stable")[:4]]].tolist():
            if on(mine, y) >= least_overlap(n, int(sizes[y]), num, den):
                join(x, y)
        alive &= label != label[x]
        if not alive.any():
            continue
        ranked = mine[np.argsort(length[mine], kind="stable")]
        aside = min(t - 1, int(t / (PROBE_COST * math.log2(max(2, int(length[ranked[-1]]))) + 1)))
        short, long = ranked[: len(ranked) - aside], ranked[len(ranked) - aside :]
        parts = [who[starts[i] : starts[i + 1]] for i in short.tolist()]
        parts = [q for q in (q[alive[q]] for q in parts) if len(q)]
        for y, shared in sorted(at_least(parts, t - aside, heap_most).items(), key=lambda z: -z[1]) if len(parts) >= t - aside else ():
            if label[x] == label[y]:
                continue
            need = least_overlap(n, int(sizes[y]), num, den)
            if shared + len(long) >= need and shared + on(long, y) >= need:
                join(x, y)
    smallest = np.full(len(sets), np.iinfo(np.int64).max)
    np.minimum.at(smallest, label, ids)
    out = np.empty(len(sets), np.int64)
    out[order] = smallest[label]
    return out


def block_kernel(k: int, num: int, den: int, heap_most: int):
    """(document, smallest of its component) of each block, blocks of one member left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in runs(batches, ["cluster", "i", "j"]):
            ids = numbers(block, "doc_id")
            if len(ids) < 2:
                continue
            batch = block.select(["text"]).combine_chunks().to_batches()[0]
            sets: list[np.ndarray] = []
            for _, texts in text_chunks(batch):
                h, _, n, _ = sets_of(texts, k)
                sets += np.split(h, np.cumsum(n)[:-1])
            side = numbers(block, "side")
            found = divide_skip(ids, sets, None if (side == side[0]).all() else side, num, den, heap_most)
            yield from emit(LINK, [ids, found])

    return run


def sql_schema(schema: pa.Schema) -> str:
    names = {pa.int64(): "long", pa.int32(): "int", pa.binary(): "binary", pa.float64(): "double", pa.string(): "string", pa.bool_(): "boolean"}
    return ", ".join(f"{f.name} {names[f.type]}" for f in schema)


def with_chunks(rows: DataFrame, key: str, chunks: DataFrame, salts: int = 64) -> DataFrame:
    """``rows`` with the ``chunks`` of their key (1 where the table has none) and their own, ``c``; a key of very many rows is spread over ``salts`` tasks."""
    salted = chunks.select(F.col(key).alias("__k"), "chunks", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("__s"))
    joined = rows.withColumn("__salt", F.pmod(F.xxhash64(F.lit(3), "doc_id"), F.lit(salts)).cast("int")).join(salted, (F.col(key) == F.col("__k")) & (F.col("__salt") == F.col("__s")), "left")
    filled = joined.withColumn("chunks", F.coalesce("chunks", F.lit(1)))
    return filled.withColumn("c", F.pmod(F.xxhash64("doc_id"), F.col("chunks")).cast("int")).drop("__k", "__s", "__salt")


def upto(n: str):
    return F.explode(F.sequence(F.lit(0), F.col(n) - 1))


def searched(docs: DataFrame, deals: DataFrame, k: int, num: int, den: int, heap_most: int) -> DataFrame:
    """DivideSkip in every block that ``deals`` (doc_id, cluster, i, j, side) makes; texts are read once and sent where they are dealt."""
    near = docs.transform(arrow, sieve_kernel(sieve_of(deals, "doc_id")), "doc_id long, text string")
    keys = ["cluster", "i", "j"]
    return near.join(deals, "doc_id").repartition(*keys).sortWithinPartitions(*keys, "doc_id", "side").transform(arrow, block_kernel(k, num, den, heap_most), sql_schema(LINK))


def chunk_count(rows: str, shingles: str, block_rows: int):
    return F.greatest(F.ceil(F.col(rows) / block_rows), F.ceil(F.col(shingles) / BLOCK_SHINGLES)).cast("int")


def large_clusters(docs: DataFrame, members: DataFrame, search, block_rows: int) -> DataFrame:
    """(node, component) of clusters with several chunks; ``members``: doc_id, cluster, n, chunks, c."""
    pivots = members.where("doc_id = cluster").select("doc_id", "cluster", F.col("c").alias("own"), upto("chunks").alias("c")).where("c <> own")
    deals = members.select("doc_id", "cluster", "c").unionByName(pivots.drop("own"))
    links = cut(search(docs, deals.select("doc_id", "cluster", F.col("c").alias("i"), F.col("c").alias("j"), F.lit(0).alias("side"))))
    found = components(links)
    # a cluster's first document is its pivot, so the pivot's component bears the cluster's name
    marked = cut(members.join(found.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("rest", F.coalesce("component", "doc_id") != F.col("cluster")).drop("component"))
    rest = marked.where("rest").groupBy("cluster").agg(F.count("*").alias("rows"), F.sum("n").alias("shingles"))
    rest = cut(rest.select("cluster", chunk_count("rows", "shingles", block_rows).alias("parts")))
    if rest.isEmpty():
        return found
    open_ = marked.join(rest, "cluster").withColumn("own", F.pmod(F.xxhash64(F.lit(5), "doc_id"), F.col("parts")).cast("int"))
    main = open_.where("not rest").select("doc_id", "cluster", F.col("c").alias("i"), upto("parts").alias("j"), F.lit(0).alias("side"))
    left = open_.where("rest")
    across = left.select("doc_id", "cluster", upto("chunks").alias("i"), F.col("own").alias("j"), F.lit(1).alias("side"))
    among = left.select("doc_id", "cluster", "own", upto("parts").alias("o")).select("doc_id", "cluster", (-1 - F.least("own", "o")).alias("i"), F.greatest("own", "o").alias("j"), F.lit(2).alias("side"))
    return components(cut(links.union(search(docs, main.union(across).union(among)))))


def near_duplicate_components(documents: DataFrame, k: int = WORDS, num: int = NUMERATOR, den: int = DENOMINATOR, block_rows: int = BLOCK_ROWS, heap_most: int = HEAP_MOST) -> DataFrame:
    """doc_id, n_shingles, component_id (the smallest doc_id that links reach), a row for each row of ``documents``."""
    docs = documents.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    scan = written(docs.transform(arrow, scan_kernel(k), sql_schema(SCAN)))
    cells = scan.where("kind = 0").groupBy("a").agg(F.sum("n").alias("n")).collect()  # LENGTH_CELLS rows at most
    length = np.zeros(LENGTH_CELLS, np.int64)
    for row in cells:
        length[row["a"]] = row["n"]
    rank = np.empty(LENGTH_CELLS, np.uint64)
    rank[np.argsort(length, kind="stable")] = np.arange(LENGTH_CELLS, dtype=np.uint64)

    each = scan.where("kind = 1").select(F.col("a").alias("doc_id"), F.col("b").alias("k1"), F.col("c").alias("k2"), "n")
    # written down, so that the join below shares no stage with this aggregate and a hot class can be split
    classes = written(each.where("n > 0 and doc_id is not null").groupBy("k1", "k2").agg(F.min("doc_id").alias("first")))
    known = docs.where("doc_id is not null and text is not null")

    postings = known.transform(arrow, posting_kernel(k, num, den, rank, sieve_of(classes, "first")), sql_schema(POSTING))
    leaders = postings.groupBy("shingle").agg(F.min("doc_id").alias("leader"), F.max("doc_id").alias("last")).where("leader < last").select("shingle", "leader")
    posted = written(postings.join(leaders, "shingle").select("leader", "doc_id").distinct())
    del postings, leaders
    release(documents.sparkSession)
    signed_ = scan.where("kind = 1 and n > 0").select(F.col("a").alias("doc_id"), "n", "sig").dropDuplicates(["doc_id", "n", "sig"])
    several = lambda rows, key, most: rows.groupBy(key).agg(F.ceil(F.count("*") / most).cast("int").alias("chunks")).where("chunks > 1")
    members = with_chunks(posted, "leader", several(posted, "leader", block_rows))
    pairs = F.transform(F.sequence(F.lit(0), F.col("chunks") - 1), lambda o: F.struct(F.least("c", o).cast("int").alias("i"), F.greatest("c", o).cast("int").alias("j")))
    blocks = members.withColumn("at", F.explode(pairs)).select("leader", "doc_id", "at.i", "at.j").join(signed_, "doc_id")
    near = blocks.repartition("leader", "i", "j").sortWithinPartitions("leader", "i", "j").transform(arrow, candidate_kernel(num, den), sql_schema(LINK))
    clusters = components(cut(near.distinct())).select(F.col("node").alias("doc_id"), F.col("component").alias("cluster"))

    sizes = scan.where("kind = 1").groupBy(F.col("a").alias("doc_id")).agg(F.max("n").alias("n"))
    inside = cut(clusters.join(sizes, "doc_id"))
    load = inside.groupBy("cluster").agg(F.count("*").alias("rows"), F.sum("n").alias("shingles"))
    several = cut(load.select("cluster", chunk_count("rows", "shingles", block_rows).alias("chunks")).where("chunks > 1"))
    inside = with_chunks(inside, "cluster", several)
    search = lambda d, deals: searched(d, deals, k, num, den, heap_most)
    zero = [F.lit(0).alias(c) for c in ("i", "j", "side")]
    found = search(known, inside.where("chunks = 1").select("doc_id", "cluster", *zero)).distinct().select(F.col("a").alias("node"), F.col("b").alias("component"))
    if not several.isEmpty():
        found = found.union(large_clusters(known, cut(inside.where("chunks > 1")), search, block_rows))

    first = each.join(classes, ["k1", "k2"], "left").select("doc_id", "n", F.when(F.col("n") > 0, F.col("first")).otherwise(F.col("doc_id")).alias("first"))
    return first.join(cut(found).withColumnRenamed("node", "first"), "first", "left").select(
        "doc_id",
        F.col("n").alias("n_shingles"),
        F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "first")).alias("component_id"),
    )


def one_of_each(documents: DataFrame, **settings) -> DataFrame:
    """``documents`` with one row for each component: that of the smallest doc_id, and of its rows the first by hashes of text and other columns.

    Rows without doc_id take part under numbers from 2^62 made of their texts, so that one stays where no row with a doc_id does;
    those without words all stay.
    """
    wordless = F.col("doc_id").isNull() & ~F.coalesce(F.col("text").rlike(r"[^\x20\x09-\x0D]"), F.lit(False))
    number = F.coalesce(F.col("doc_id").cast("long"), F.lit(1 << 62) + F.xxhash64("text").bitwiseAND((1 << 62) - 1))
    numbered = documents.where(~wordless).withColumn("__id", number)
    found = near_duplicate_components(numbered.select(F.col("__id").alias("doc_id"), "text"), **settings)
    row = F.struct(F.xxhash64("text").alias("t"), F.xxhash64(*[c for c in documents.columns if c != "text"]).alias("o"))
    # what to keep is chosen by hashes, so that texts travel to one join alone and reruns agree
    least = numbered.select("__id", row.alias("__r")).groupBy("__id").agg(F.min("__r").alias("__least"), F.count("*").alias("__rows"))
    kept = found.where("doc_id = component_id").select(F.col("doc_id").alias("__id")).distinct().join(least, "__id")
    single = numbered.join(cut(kept), "__id").where((F.col("__rows") == 1) | (F.col("__least") == row))
    again = single.where("__rows > 1").dropDuplicates(["__id"])
    return single.where("__rows = 1").select(documents.columns).union(again.select(documents.columns)).union(documents.where(wordless))


def op9_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return finished(spark, lambda: near_duplicate_components(spark.read.parquet(f"{sf_dir}/documents.parquet")))
