"""Mixing sources to target weights with hash-threshold histograms.

A document takes whole copies of itself and, when its hash lies below its source's
threshold, one more. Thresholds come from histograms of words by source and hash
bucket: cumulated bucket by bucket they bracket the source's budget, only the
boundary bucket is split further, and after a few rounds the threshold stands at
a single hash. Nothing is sorted but the histograms, and the mix is a
filter: it can be applied to any scan of the same documents.

Native: DataFrame functions only; no row reaches Python.

Rows. A null or wordless text has size 0 and takes 0. Null is a source, ordered last.
Rows with equal doc_id share one hash and are taken together. An
empty table gives an empty result. Other columns are ignored by the query; ``mix`` keeps them
and its own columns start with two underscores.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from facetgraph.llm.graph import cut

#: Weights that the sources take in turn, ordered by name.
WEIGHTS = (3, 1, 2)
#: The mix has SHARE_NUM / SHARE_DEN of all words; no source more than MOST times its own.
SHARE_NUM, SHARE_DEN, MOST = 3, 2, 2
HASH_BITS, LEVEL_BITS = 52, 13
#: Sources up to which their table of thresholds is broadcast; beyond, it is joined by shuffle.
BROADCAST_SOURCES = 100_000


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")).cast("long"), F.lit(0).cast("long"))


def document_hash(doc_id: Column) -> Column:
    """52 bits that any SQL engine with md5 can repeat."""
    return F.conv(F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.lit(""))), 1, HASH_BITS // 4), 16, 10).cast("long")


def targets(sizes: DataFrame, weights=WEIGHTS, num: int = SHARE_NUM, den: int = SHARE_DEN, most: int = MOST) -> DataFrame:
    """(source, source_size) → also target: the budget shared by weight, capped, the excess reshared until nothing is above.

    Filling by weight up to caps has a closed form: with sources ordered by cap over weight, those before the first
    uncapped one get their caps and the others the rest by weight. One row for each source.
    """
    scale = 1
    for w in weights:
        scale *= w
    rank = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    pick = lambda values: F.element_at(F.array(*[F.lit(v).cast("long") for v in values]), (rank % len(weights)) + 1)
    s = sizes.select("source", "source_size", pick(weights).alias("w"), pick([scale // w for w in weights]).alias("inverse"))
    order = (F.col("source_size") * F.col("inverse")).asc(), F.col("source").asc_nulls_last()
    before = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    after = Window.orderBy(*order).rowsBetween(Window.currentRow, Window.unboundedFollowing)
    every = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    left = F.lit(num) * F.sum("source_size").over(every) - F.lit(den * most) * F.coalesce(F.sum("source_size").over(before), F.lit(0))
    s = s.withColumn("left", left).withColumn("active", F.sum("w").over(after))
    s = s.withColumn("open", F.lit(den * most) * F.col("source_size") * F.col("active") >= F.col("left") * F.col("w"))
    level = F.first(F.when(F.col("open"), F.struct("left", "active")), ignorenulls=True).over(every)
    s = s.withColumn("level", level)
    capped = F.lit(den * most) * F.col("source_size") * F.col("level.active") < F.col("level.left") * F.col("w")
    fill = (F.col("level.left") * F.col("w")).cast("double") / (F.lit(den) * F.col("level.active")).cast("double")
    return s.select("source", "source_size", F.when(F.col("level").isNull() | capped, (F.lit(most) * F.col("source_size")).cast("double")).otherwise(fill).alias("target"))


def plan(documents: DataFrame, **settings) -> DataFrame:
    """For each source: source_size, target, whole copies, and the threshold of the copy beyond (``at``, and whether a hash equal to it is in)."""
    slim = cut(documents.select("source", document_hash(F.col("doc_id")).alias("h"), words(F.col("text")).alias("size")).where("size > 0"))
    sizes = documents.select("source").distinct().join(slim.groupBy(F.col("source").alias("s")).agg(F.sum("size").alias("source_size")), F.col("source").eqNullSafe(F.col("s")), "left")
    budget = cut(targets(sizes.select("source", F.coalesce("source_size", F.lit(0).cast("long")).alias("source_size")), **settings))
    small = budget.count() <= BROADCAST_SOURCES
    copies = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    budget = budget.withColumn("copies", copies).withColumn("rest", F.col("target") - F.col("copies") * F.col("source_size"))
    state = budget.select("source", "rest", F.lit(0).cast("long").alias("at"), F.lit(0).cast("long").alias("below"))
    for shift in range(HASH_BITS - LEVEL_BITS, -1, -LEVEL_BITS):
        bound = state.select(F.col("source").alias("s"), "rest", "at", "below")
        inside = slim.join(F.broadcast(bound) if small else bound, F.col("source").eqNullSafe(F.col("s")) & (F.shiftright("h", shift + LEVEL_BITS) == F.col("at")))
        cells = inside.groupBy("source", F.shiftright("h", shift).alias("cell")).agg(F.sum("size").alias("n"), F.first("rest").alias("rest"), F.first("below").alias("below"))
        upto = cells.withColumn("upto", F.col("below") + F.sum("n").over(Window.partitionBy("source").orderBy("cell")))
        state = upto.where("upto > rest").groupBy("source").agg(F.first("rest").alias("rest"), F.min("cell").alias("at"), F.min_by(F.col("upto") - F.col("n"), "cell").alias("below"), F.min("upto").alias("upto"))
    last = state.select(F.col("source").alias("s"), "at", ((F.col("upto") - F.col("rest")) < (F.col("rest") - F.col("below"))).alias("with_at"))
    return budget.join(last, F.col("source").eqNullSafe(F.col("s")), "left").select("source", "source_size", "target", "copies", "at", "with_at")


def with_times(documents: DataFrame, **settings) -> DataFrame:
    """``documents`` with __size, __source_size, __target and __times, the copies of each that the mix takes."""
    bounds = cut(plan(documents.select("doc_id", "source", "text"), **settings))
    bounds = bounds.select(*[F.col(c).alias(f"__{c}") for c in bounds.columns])
    h = document_hash(F.col("doc_id"))
    more = F.coalesce((h < F.col("__at")) | ((h == F.col("__at")) & F.col("__with_at")), F.lit(False))
    joined = documents.join(F.broadcast(bounds) if bounds.count() <= BROADCAST_SOURCES else bounds, F.col("source").eqNullSafe(F.col("__source")))
    return joined.withColumn("__size", words(F.col("text"))).withColumn("__times", F.least(F.col("__copies") + more.cast("long"), F.lit(settings.get("most", MOST)).cast("long"))).drop("__source", "__copies", "__at", "__with_at")


def mix(documents: DataFrame, **settings) -> DataFrame:
    """The mix itself: each document as many times as its source's budget takes it, with its own columns."""
    taken = with_times(documents, **settings).where("__times > 0")
    return taken.withColumn("__copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("__times")))).select(documents.columns)


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = with_times(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", "text"))
    return rows.select("doc_id", F.col("__size").alias("size"), F.col("__source_size").alias("source_size"), F.col("__target").alias("target"), (F.col("__size") * F.col("__times")).alias("taken"))


#: The same mix by sorting: words cumulated in the order of the hashes, the boundary document in when that is nearer.
OP2_SQL = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 13))::BIGINT AS h FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS r FROM d GROUP BY source),
w AS (SELECT source, source_size, CASE r % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS w FROM s),
o AS (
  SELECT *, 3 * sum(source_size) OVER () - 4 * coalesce(sum(source_size) OVER (ORDER BY source_size * (6 // w), source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS rest_2,
         sum(w) OVER (ORDER BY source_size * (6 // w), source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS active,
         row_number() OVER (ORDER BY source_size * (6 // w), source NULLS LAST) AS k FROM w),
f AS (SELECT rest_2, active FROM o WHERE 4 * source_size * active >= rest_2 * w ORDER BY k LIMIT 1),
t AS (
  SELECT o.source, o.source_size, CASE WHEN 4 * o.source_size * f.active < f.rest_2 * o.w THEN (2 * o.source_size)::DOUBLE
         ELSE (f.rest_2 * o.w)::DOUBLE / (2 * f.active)::DOUBLE END AS target FROM o, f),
c AS (
  SELECT d.*, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN floor(t.target / t.source_size) ELSE 0 END AS copies,
         sum(size) OVER (PARTITION BY d.source ORDER BY h RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto,
         sum(size) OVER (PARTITION BY d.source, h) AS own
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target,
       (size * (copies + CASE WHEN upto <= target - copies * source_size THEN 1
                              WHEN upto - own <= target - copies * source_size
                                   AND upto - (target - copies * source_size) < (target - copies * source_size) - (upto - own) THEN 1 ELSE 0 END))::BIGINT AS taken
FROM c
"""
