"""The base tables, the entity views on them, and query sets; each view also as SQL for the oracles."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from facetgraph.functions import vectors as V

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
ANCHORS, KEYWORDS, BUCKETS = 30, 3, 128
#: Every QUERY_STEP-th entity is also a query; anchors never are.
QUERY_STEP = 5


def cut(df: DataFrame) -> DataFrame:
    """``df`` written to the checkpoint folder, so that loops and repeated reads start from there."""
    import tempfile

    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        shared = sc.getConf().get("spark.checkpoint.dir")
        if not shared and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="checkpoint"))
    return df.checkpoint()


def load(spark: SparkSession, directory: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{directory}/{name}.parquet")


def load_text(spark: SparkSession, path: str, schema: str, form: str = "csv") -> DataFrame:
    """A table from CSV with a header, or from JSON lines. Arrays in CSV are written as JSON in one field; null and bad rows are told by ``_bad``."""
    if form == "json":
        return spark.read.schema(f"{schema}, _bad string").option("columnNameOfCorruptRecord", "_bad").json(path)
    if form != "csv":
        raise ValueError("form must be csv or json")
    wanted = spark.createDataFrame([], schema).schema
    nested = {f.name for f in wanted.fields if f.dataType.typeName() in ("array", "struct", "map")}
    flat = ", ".join(f"`{f.name}` {'string' if f.name in nested else f.dataType.simpleString()}" for f in wanted.fields)
    raw = spark.read.schema(f"{flat}, _bad string").option("header", True).option("columnNameOfCorruptRecord", "_bad").option("escape", '"').csv(path)
    return raw.select(*[F.from_json(f.name, f.dataType.simpleString()).alias(f.name) if f.name in nested else F.col(f.name) for f in wanted.fields], "_bad")


def views(spark: SparkSession, directory: str) -> dict[str, DataFrame]:
    out = {name: load(spark, directory, name) for name in TABLES}
    for name, df in out.items():
        df.createOrReplaceTempView(name)
    return out


def cat12(key) -> F.Column:
    return (F.lit(1) + F.pmod(F.pmod(key * F.lit(2654435761), F.lit(4294967296)), F.lit(12))).cast("int")


def brands_of_order(spark: SparkSession, directory: str, wanted: DataFrame | None = None) -> DataFrame:
    """Of each order, or of those in ``wanted`` (id): its brands."""
    lines = load(spark, directory, "lineitem").select("l_orderkey", "l_partkey")
    lines = lines if wanted is None else lines.join(wanted.select(F.col("id").alias("l_orderkey")), "l_orderkey", "left_semi")
    part = load(spark, directory, "part").select("p_partkey", "p_brand")
    return lines.join(part, F.col("l_partkey") == F.col("p_partkey")).groupBy(F.col("l_orderkey").alias("order_id")).agg(F.sort_array(F.collect_set("p_brand")).alias("brands"))


def keywords_of(vectors: DataFrame) -> DataFrame:
    """id, keywords, worst: of the first ANCHORS vectors the KEYWORDS with the largest inner product, ties by id, and the last one; the anchors are few and travel as a literal."""
    anchors = vectors.where(F.col("id") < ANCHORS).orderBy("id").select("id", "vec").collect()
    literal = F.array(*[F.struct(F.lit(a["id"]).cast("long").alias("a"), F.array(*[F.lit(float(x)) for x in a["vec"]]).alias("v")) for a in anchors])
    scored = F.transform(literal, lambda z: F.struct((-V.inner_product(F.col("vec"), z["v"])).alias("s"), z["a"].alias("a")))
    ranked = vectors.select("id", F.array_sort(scored).alias("r"))
    return ranked.select("id", F.transform(F.slice("r", 1, KEYWORDS), lambda z: z["a"]).alias("keywords"), F.get("r", F.size("r") - 1)["a"].alias("worst"))


def entity_vec(spark: SparkSession, directory: str, keywords: bool = False) -> DataFrame:
    """id, vec, label, cat12, o_date, o_totalprice, brands, caption, lang, source, props_k, ev_ts and, on request, keywords and worst."""
    emb = load(spark, directory, "embeddings")
    docs = load(spark, directory, "documents")
    n = docs.count()
    base = emb.select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"), "label", cat12(F.col("vec_id")).alias("cat12"), F.pmod(F.col("vec_id"), F.lit(max(n, 1))).alias("doc"))
    orders = load(spark, directory, "orders").select(F.col("o_orderkey").alias("id"), F.col("o_orderdate").alias("o_date"), "o_totalprice")
    events = load(spark, directory, "events").select(F.col("event_id").alias("id"), F.get_json_object("props", "$.k").cast("int").alias("props_k"), F.col("ts").alias("ev_ts"))
    captions = docs.select(F.col("doc_id").alias("doc"), F.col("text").alias("caption"), "lang", "source")
    brands = brands_of_order(spark, directory, base).withColumnRenamed("order_id", "id")
    out = base.join(orders, "id", "left").join(brands, "id", "left").join(events, "id", "left").join(captions, "doc", "left").drop("doc")
    return out.join(keywords_of(base.select("id", "vec")), "id", "left") if keywords else out


class Cells(dict):
    """The cell of each word, by its MD5; a table of bounded size."""

    def __missing__(self, word: bytes) -> int:
        cell = int.from_bytes(hashlib.md5(word).digest()[:4], "big") % BUCKETS
        if len(word) <= 64:
            if len(self) >= 200_000:
                self.clear()
            self[word] = cell
        return cell


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, counts of the cells as packed numbers) of each (key, text as bytes) that has words."""
    cells = Cells()
    for b in batches:
        for at in range(0, b.num_rows, 1000):
            some = b.slice(at, 1000)
            # bytes split at the six ASCII blanks, as Java's \s has them
            words = [(text.as_py() or b"").split() for text in some.column(1)]
            has = [i for i, w in enumerate(words) if w]
            packed = [np.bincount([*map(cells.__getitem__, words[i])], minlength=BUCKETS).astype(np.int32).tobytes() for i in has]
            yield pa.RecordBatch.from_arrays([some.column(0).take(pa.array(has, pa.int64())), pa.array(packed, pa.binary())], ["key", "counts"])


def _units(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, vec): the summed counts divided by their norm; squares of counts sum exactly."""
    for b in batches:
        for at in range(0, b.num_rows, 1000):
            some = b.slice(at, 1000)
            x = np.zeros((some.num_rows, BUCKETS))
            for i, parts in enumerate(some.column(1)):
                for part in parts:
                    x[i] += np.frombuffer(part.as_py(), np.int32)
            x /= np.sqrt((x * x).sum(axis=1))[:, None]
            cuts = pa.array(np.arange(some.num_rows + 1, dtype=np.int32) * BUCKETS)
            yield pa.RecordBatch.from_arrays([some.column(0), pa.ListArray.from_arrays(cuts, pa.array(x.reshape(-1)))], ["key", "vec"])


def text_vector(rows: DataFrame, key: str, text: str) -> DataFrame:
    """``key`` and vec: counts of hashed words in BUCKETS cells, divided by their norm; rows of one key count together."""
    kind = rows.schema[key].dataType.simpleString()
    counts = rows.select(F.col(key).alias("key"), F.col(text).cast("binary")).mapInArrow(_counts, f"key {kind}, counts binary")
    return counts.groupBy("key").agg(F.collect_list("counts").alias("counts")).mapInArrow(_units, f"key {kind}, vec array<double>").withColumnRenamed("key", key)


def entity_doc(spark: SparkSession, directory: str) -> DataFrame:
    docs, labels = load(spark, directory, "documents"), load(spark, directory, "labels")
    vecs = text_vector(docs.select(F.col("doc_id").alias("id"), "text"), "id", "text")
    rest = docs.select(F.col("doc_id").alias("id"), "lang", "source", "n_chars", cat12(F.col("doc_id")).alias("cat12"), "text").join(labels.withColumnRenamed("doc_id", "id"), "id", "left")
    return vecs.join(rest, "id")


def query_conv(spark: SparkSession, directory: str) -> DataFrame:
    """query_id, qvec of the user turns; query_id numbers them by conversation and turn."""
    turns = load(spark, directory, "conversations").where("role = 'user'").select((F.col("conv_id") * 1000 + F.col("turn")).alias("query_id"), "text")
    return text_vector(turns, "query_id", "text").withColumnRenamed("vec", "qvec")


def query_set(entities: DataFrame, pred_id, step: int = QUERY_STEP, first: int = ANCHORS) -> DataFrame:
    """query_id, qvec, pred_id: the stated query set, every ``step``-th entity from ``first``."""
    chosen = entities.where((F.pmod(F.col("id"), F.lit(step)) == 0) & (F.col("id") >= first))
    return chosen.select(F.col("id").alias("query_id"), F.col("vec").alias("qvec"), pred_id.cast("int").alias("pred_id"))


SQL_BRANDS = "SELECT l_orderkey AS order_id, list_sort(list(DISTINCT p_brand)) AS brands FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1"

SQL_ENTITY_VEC = f"""brand_lists AS ({SQL_BRANDS}),
base AS (SELECT vec_id AS id, embedding::DOUBLE[] AS vec, label, (1 + ((vec_id * 2654435761) % 4294967296) % 12)::INT AS cat12 FROM embeddings),
anchors AS (SELECT id AS a, vec AS av FROM base WHERE id < {ANCHORS}),
kw AS (SELECT id, list(a ORDER BY r) FILTER (WHERE r <= {KEYWORDS}) AS keywords, arg_max(a, r) AS worst FROM (
  SELECT id, a, row_number() OVER (PARTITION BY id ORDER BY {V.sql_distance('inner_product', 'vec', 'av')}, a) AS r FROM base, anchors) GROUP BY id),
entity AS (SELECT b.*, o.o_orderdate AS o_date, o.o_totalprice, l.brands, d.text AS caption, d.lang, d.source, json_extract_string(e.props, '$.k')::INT AS props_k, e.ts AS ev_ts, kw.keywords, kw.worst
  FROM base b LEFT JOIN orders o ON o.o_orderkey = b.id LEFT JOIN brand_lists l ON l.order_id = b.id LEFT JOIN events e ON e.event_id = b.id
  LEFT JOIN documents d ON d.doc_id = b.id % (SELECT count(*) FROM documents) LEFT JOIN kw ON kw.id = b.id)"""


def sql_text_vector(name: str, source: str, key: str) -> str:
    """CTEs that give ``name`` (key, vec) from ``source`` (key, text)."""
    return f"""{name}_cells AS (SELECT {key}, (('0x' || substr(md5(t), 1, 8))::UBIGINT % {BUCKETS})::INT AS cell, count(*)::DOUBLE AS c FROM (
  SELECT {key}, unnest(regexp_split_to_array(text, '\\s+')) AS t FROM ({source})) WHERE t <> '' GROUP BY 1, 2),
{name}_full AS (SELECT {key}, list(coalesce(c, 0.0) ORDER BY i) AS v FROM (SELECT k.{key}, i.i, c.c FROM (SELECT DISTINCT {key} FROM {name}_cells) k CROSS JOIN (SELECT unnest(range({BUCKETS})) AS i) i
  LEFT JOIN {name}_cells c ON c.{key} = k.{key} AND c.cell = i.i) GROUP BY {key}),
{name} AS (SELECT {key}, list_transform(v, lambda x: x / sqrt({V.sql_fold('v', 'v', 'z[1] * z[2]')})) AS vec FROM {name}_full)"""


def sql_queries(pred: str, step: int = QUERY_STEP, entity: str = "entity", first: int = ANCHORS) -> str:
    return f"queries AS (SELECT id AS query_id, vec AS qvec, ({pred})::INT AS pred_id FROM {entity} WHERE id % {step} = 0 AND id >= {first})"
