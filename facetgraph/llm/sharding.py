"""A uniform shuffle into shards of exact sizes, by a hypergeometric communication matrix.

The partitions are taken as they lie. How many rows each sends to each shard is drawn as in a
uniform random arrangement: row by row of the matrix, a multivariate hypergeometric draw from
the shards' free places, so that partitions are used up and shards filled exactly.
Each partition permutes its rows (a sort inside the partition, by random keys) and deals them out by its matrix row; after the one
exchange each shard permutes again, in buckets of random keys whose offsets make the slots gapless.

Native: DataFrame functions only. The driver sees one count for each partition (MAX_BLOCKS at most; more partitions are first put together
without a shuffle) and draws the matrix from them; no row reaches Python. The counts and the deal read the partitions twice, so rows
that come out of a shuffle are written down first.

Rows. All rows are placed, repeated rows too. A null text has 0 bytes (and the checksum of the empty
text), a null doc_id is a key like any other. An empty table gives an empty
result. ``shard_rows`` keeps every column and adds ``__shard`` and ``__slot``.
"""

from __future__ import annotations

import json
import math
import random

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from facetgraph.llm.graph import settled

SHARDS, SEED = 24, 20_240
#: Partitions whose matrix rows are drawn, at most.
MAX_BLOCKS = 16_384
#: Rows of one bucket of a shard's second permutation, about.
CELL_ROWS = 20_000


def hypergeometric(rng: random.Random, good: int, bad: int, sample: int) -> int:
    """Marked items among ``sample`` drawn without replacement, by inversion from the mode outwards."""
    low, high = max(0, sample - bad), min(good, sample)
    if low == high:
        return low
    log = lambda n, k: math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)
    mode = min(high, max(low, (sample + 1) * (good + 1) // (good + bad + 2)))
    top = math.exp(log(good, mode) + log(bad, sample - mode) - log(good + bad, sample))
    u = rng.random() - top
    a, b, pa, pb = mode, mode, top, top
    while u > 0:
        more = False
        if b < high:
            pb *= (good - b) * (sample - b) / ((b + 1) * (bad - sample + b + 1))
            b, u, more = b + 1, u - pb, True
            if u <= 0:
                return b
        if a > low:
            pa *= a * (bad - sample + a) / ((good - a + 1) * (sample - a + 1))
            a, u, more = a - 1, u - pa, True
            if u <= 0:
                return a
        if not more or (pa < 1e-300 and pb < 1e-300):
            return mode
    return mode


def communication_matrix(rows: list[int], shards: int, seed: int) -> list[list[int]]:
    """rows[b] items of block b dealt to shards whose sizes differ by one at most."""
    rng, total = random.Random(seed), sum(rows)
    extra = set(rng.sample(range(shards), total % shards))
    free = [total // shards + (s in extra) for s in range(shards)]
    out = []
    for n in rows:
        left, rest, row = sum(free), n, []
        for s in range(shards):
            left -= free[s]
            row.append(hypergeometric(rng, free[s], left, rest))
            rest -= row[-1]
        free = [f - x for f, x in zip(free, row)]
        out.append(row)
    return out


def row_key(seed: int) -> Column:
    return F.xxhash64(F.lit(seed), F.col("doc_id"), F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")))


def shard_rows(documents: DataFrame, shards: int = SHARDS, seed: int = SEED, key: Column | None = None, cell_rows: int = CELL_ROWS) -> DataFrame:
    """``documents`` with __shard (0 to shards - 1) and __slot (gapless from 0 in each shard).

    ``key``: a hash of the row; by default of doc_id and text. Equal rows have equal keys and are told apart by their place in the partition.
    """
    lying, count = settled(documents), lambda df: dict(df.groupBy(F.spark_partition_id().alias("b")).count().limit(MAX_BLOCKS + 1).collect())
    counts = count(lying)
    if len(counts) > MAX_BLOCKS:
        lying = lying.coalesce(MAX_BLOCKS)
        counts = count(lying)
    blocks, n = max(counts, default=-1) + 1, sum(counts.values())
    cumulated = []
    for row in communication_matrix([counts.get(b, 0) for b in range(blocks)], shards, seed):
        total, ends = 0, []
        for x in row:
            total += x
            ends.append(total)
        cumulated.append(ends)
    matrix = documents.sparkSession.range(1).select(F.posexplode(F.from_json(F.lit(json.dumps(cumulated)), "array<array<long>>")).alias("__block", "__ends"))

    place = F.monotonically_increasing_id()
    own = row_key(seed) if key is None else key
    # a row's place in the partition makes its key its own; the places after the sort are the permutation
    keyed = lying.withColumn("__key", own).withColumn("__key", F.xxhash64(F.lit(seed + 1), "__key", place))
    permuted = keyed.sortWithinPartitions("__key").withColumn("__at", F.monotonically_increasing_id())
    within = F.col("__at").bitwiseAND((1 << 33) - 1) + 1
    dealt = permuted.withColumn("__block", F.shiftright("__at", 33).cast("int")).join(F.broadcast(matrix), "__block")
    dealt = dealt.withColumn("__shard", F.size(F.filter("__ends", lambda e: e < within))).drop("__ends", "__block", "__at")

    bits = max(1, math.ceil(math.log2(max(1, n / shards / cell_rows))))
    dealt = dealt.withColumn("__key", F.xxhash64(F.lit(seed + 2), "__key", "__shard")).withColumn("__cell", F.shiftrightunsigned("__key", 64 - bits))
    cells = dealt.groupBy("__shard", "__cell").agg(F.count("*").alias("__n"))
    before = Window.partitionBy("__shard").orderBy("__cell").rowsBetween(Window.unboundedPreceding, -1)
    offsets = cells.select("__shard", "__cell", F.coalesce(F.sum("__n").over(before), F.lit(0).cast("long")).alias("__offset"))
    rank = F.row_number().over(Window.partitionBy("__shard", "__cell").orderBy("__key"))
    placed = dealt.withColumn("__slot", rank).join(offsets, ["__shard", "__cell"])
    return placed.select(*documents.columns, "__shard", (F.col("__slot") + F.col("__offset") - 1).alias("__slot"))


def op3_shard_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    text = F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary")
    slim = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    placed = shard_rows(slim, key=F.xxhash64(F.lit(SEED), "doc_id", "text_crc32"))
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.col("__shard").cast("int").alias("shard"), F.col("__slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
