"""A corpus pipeline: toxicity, near duplicates, decontamination, mixing, sharding.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, which ``run`` writes as Parquet to the shared
folder and rereads as the next stage's docs; what a stage read and wrote on the way is removed once its result stands. All stages but the last
return the columns of ``documents``; the last adds shard and slot.

Every stage keeps all columns that docs has, whatever their names and nulls, and gives no rows for an empty table.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from facetgraph.llm.decontaminate import clean
from facetgraph.llm.graph import release, remove, shared_folder, sweep, tables_written
from facetgraph.llm.mixing import mix
from facetgraph.llm.ngram_join import one_of_each
from facetgraph.llm.sharding import shard_rows
from facetgraph.llm.toxicity import train, without_toxic


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops what the machine, fitted on the training folds, scores at its cut or above.

    Each row is judged by its own text: null and empty texts as texts without terms, very long ones whole, repeated rows alike, rows without doc_id
    too. Where no label of a kind is known every row gets that share as its score. A score equal to the cut goes.
    """
    return without_toxic(docs, train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps of each component the document of the smallest doc_id.

    Null and wordless texts are linked with nothing: one row of each doc_id stays. Of rows that share the kept doc_id one stays, chosen by
    hashes of its columns, the same in any order of rows. A row without doc_id stays only if no linked row has one; wordless rows without doc_id all stay.
    """
    return one_of_each(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents with a twentieth or more of their words in benchmark windows.

    Each row is judged by its own text, also where doc_id is null or repeated; texts without words stay. Null benchmark texts have no windows;
    with an empty benchmark all rows stay.
    """
    return clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats or drops documents so that sources come to their targets.

    Null is a source. Null and wordless texts weigh nothing and are taken as their source's other rows are. Rows that share a doc_id, null too, are taken together.
    """
    return mix(docs)


def sharding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places every row in a shard; adds shard and slot (named with underscores where docs has such columns).

    All rows are placed, with any nulls; equal rows, which the mix makes, get places of their own.
    """
    placed = shard_rows(docs)
    for name in ("shard", "slot"):
        placed = placed if name in docs.columns else placed.withColumnRenamed(f"__{name}", name)
    return placed


STAGES = [
    ("toxicity", toxicity),
    ("near_duplicates", near_duplicates),
    ("decontaminate", decontaminate),
    ("mixing", mixing),
    ("sharding", sharding),
]

#: The stages of the classifier and of the component search have no SQL form; tests compare them with plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    docs, last = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for i, (name, stage) in enumerate(STAGES):
        path, before = f"{folder}/{i}-{name}", tables_written()
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        sweep(spark, before)
        release(spark)
        if last:
            remove(spark, last)
        last = path
    return docs


QUERIES = {"pipeline": run}
