"""Joins, aggregates and windows that users of filtered search need around it."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, left_ts: str, right_ts: str, keep: str, bucket: str = "day") -> DataFrame:
    """The latest right row at or before each left row; of several at one time the greatest ``keep``.

    Both sides are one stream, sorted inside time buckets, where each left row takes the last right row before it; a bucket without
    one takes it from the buckets before, by a running maximum over one row for each bucket. Work is linear in the rows but for the sort.
    """
    b = lambda c: F.date_trunc(bucket, F.col(c)).alias("__b")
    hit = F.struct(F.col(right_ts).alias("__ts"), F.col(keep).alias("__keep"))
    r = right.select(b(right_ts), F.col(right_ts).alias("__at"), F.lit(0).alias("__side"), hit.alias("__hit"))
    l = left.select(b(left_ts), F.col(left_ts).alias("__at"), F.lit(1).alias("__side"), F.struct(*left.columns).alias("__row"))
    both = r.unionByName(l, allowMissingColumns=True)
    order = Window.partitionBy("__b").orderBy("__at", "__side", "__hit").rowsBetween(Window.unboundedPreceding, 0)
    met = both.withColumn("__own", F.last("__hit", ignorenulls=True).over(order)).where("__side = 1")
    ends = both.groupBy("__b").agg(F.max("__hit").alias("__last"))
    carried = ends.select("__b", F.max("__last").over(Window.orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)).alias("__before"))
    found = met.join(carried, "__b", "left").select("__row", F.coalesce("__own", "__before").alias("__hit"))
    return found.select(*[F.col("__row")[c].alias(c) for c in left.columns], F.col("__hit.__ts").alias(right_ts), F.col("__hit.__keep").alias(keep))


def range_join(points: DataFrame, ranges: DataFrame, at: str, low: str, high: str, unit: str = "month") -> DataFrame:
    """Points within [low, high]: an equi-join on time buckets and a residual test."""
    b = points.withColumn("__b", F.date_trunc(unit, F.col(at)))
    step = F.expr(f"interval 1 {unit}")
    spread = ranges.withColumn("__b", F.explode(F.sequence(F.date_trunc(unit, F.col(low)), F.date_trunc(unit, F.col(high)), step)))
    return b.join(spread, "__b").where(F.col(at).between(F.col(low), F.col(high))).drop("__b")


def semi(left: DataFrame, right: DataFrame, on) -> DataFrame:
    return left.join(right, on, "left_semi")


def anti(left: DataFrame, right: DataFrame, on) -> DataFrame:
    return left.join(right, on, "left_anti")


def lateral_topk(left: DataFrame, right: DataFrame, on: str, order: str, k: int) -> DataFrame:
    """For each left row the first k right rows by ``order``."""
    w = Window.partitionBy(on).orderBy(F.col(order).desc())
    return left.join(right.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= k).drop("__r"), on)


def running(df: DataFrame, part: str, order: str, value: str) -> DataFrame:
    w = Window.partitionBy(part).orderBy(order)
    return df.withColumn("running", F.sum(value).over(w.rowsBetween(Window.unboundedPreceding, 0))).withColumn("previous", F.lag(value).over(w)).withColumn("place", F.rank().over(w))
