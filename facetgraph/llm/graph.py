"""Cutting lineage, and connected components, on DataFrames."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetgraph.llm.textkit import trim


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that all executors share: ``spark.checkpoint.dir``, or a temporary one in a local session without it."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared = sc.getConf().get("spark.checkpoint.dir")
        if not shared:
            if not sc.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
            shared = tempfile.mkdtemp(prefix="checkpoint")
        sc.setCheckpointDir(shared)
    return sc.getCheckpointDir()


#: Tables that ``written`` made, in order.
_TABLES: list[str] = []


def written(df: DataFrame) -> DataFrame:
    """``df`` as a Parquet table in the shared folder: as safe as a checkpoint against lost executors, and compressed."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    _TABLES.append(path)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Cuts lineage.
cut = written


def tables_written() -> int:
    return len(_TABLES)


def remove(spark: SparkSession, *paths: str) -> None:
    for path in paths:
        place = spark._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def sweep(spark: SparkSession, since: int, upto: int | None = None) -> None:
    """Removes the tables written since, or those up to number ``upto`` of them; nothing may read them any more."""
    remove(spark, *_TABLES[since:upto])
    del _TABLES[since:upto]


def release(spark: SparkSession) -> None:
    """Lets Spark remove the shuffle files that no plan needs any more: it does so when the driver collects garbage, which an idle driver seldom does.

    A DataFrame that is still named keeps the shuffles of what was written from it.
    """
    for _ in range(2):
        # the plans of a finished job are let go a moment after it ends
        gc.collect()
        spark._jvm.java.lang.System.gc()
        time.sleep(0.3)
    trim()


def finished(spark: SparkSession, make: Callable[[], DataFrame]) -> DataFrame:
    """What ``make`` gives, written down, and the tables and shuffles that it took removed."""
    since = tables_written()
    out = written(make())
    last = _TABLES.pop()
    sweep(spark, since)
    _TABLES.append(last)
    release(spark)
    return out


def settled(df: DataFrame) -> DataFrame:
    """``df`` if every reading of it gives the same rows in the same order, as a plain scan does; else a written copy."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return written(df) if "Exchange" in plan or "MapIn" in plan else df


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component): the smallest node that edges (a, b) reach, for every node of an edge.

    Each round takes the smallest label among the neighbours and then the label's
    own label (pointer jumping), so rounds grow with the logarithm of the diameter.
    A node with very many neighbours meets only a partial aggregate and a join
    that adaptive execution can split.
    """
    both = cut(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct())
    labels = cut(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("component")))
    for _ in range(max_rounds):
        near = both.join(labels.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node")).agg(F.min("component").alias("m"))
        step = labels.join(near, "node").select("node", F.col("component").alias("old"), F.least("component", "m").alias("c"))
        top = labels.select(F.col("node").alias("c"), F.col("component").alias("up"))
        fresh = cut(step.join(top, "c", "left").select("node", "old", F.least("c", F.coalesce("up", "c")).alias("component")))
        changed = fresh.where("old <> component").limit(1).count()
        labels = fresh.select("node", "component")
        if not changed:
            return labels
    raise RuntimeError("components did not settle")
