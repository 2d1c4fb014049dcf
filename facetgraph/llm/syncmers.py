"""Document fingerprints from closed syncmers.

A run of K words is an anchor when, of its inner runs of S words, the one with the smallest
hash is the first or the last. That depends on the run alone, so an edit disturbs only the anchors that it
touches and a passage keeps its anchors wherever it stands. ``anchors`` gives them with their positions, for positional
matching; the fingerprint keeps the KEEP smallest anchor hashes, whose overlap estimates the
likeness of two texts' anchor sets.

Native: DataFrame functions only.

Rows. A null text is empty. A text with fewer than K words has its whole word sequence as one anchor; a wordless text has an
empty fingerprint, and two of these are alike (1). Rows are paired with the next in ascending doc_id (without doc_id first, ties by text hash), the last
with the first; a lone row with itself. Other columns are ignored.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

K, S, KEEP = 6, 2, 128
BLANKS = r"[\x20\x09-\x0D]+"
#: Rows of one id range, and the ranges at most.
RANGE_ROWS, MAX_RANGES = 2_000, 4_096
LOWEST = -(1 << 63)


def barrier(df: DataFrame, name: str, value: Column) -> DataFrame:
    """``df`` with a column that later expressions read and never compute again."""
    return df.select(*df.columns, F.inline(F.array(F.struct(value.alias(name)))))


def word_hashes(text: Column) -> Column:
    return F.transform(F.filter(F.split(F.coalesce(text, F.lit("")), BLANKS), lambda w: w != ""), lambda w: F.xxhash64(w))


def _spread(n: Column) -> Column:
    return F.sequence(F.lit(0), n - 1)


def syncmers(df: DataFrame, text: Column, name: str, k: int = K, s: int = S) -> DataFrame:
    """``df`` with ``name``: array of (position, hash) of the text's anchors."""
    df = barrier(df, "__h", word_hashes(text))
    inner = F.when(F.size("__h") >= s, F.transform(_spread(F.size("__h") - (s - 1)), lambda i: F.xxhash64(*[F.get("__h", i + j) for j in range(s)])))
    df = barrier(df, "__s", inner)
    edges = k - s
    run = lambda i: F.xxhash64(*[F.get("__h", i + j) for j in range(k)])
    first, last = lambda i: F.get("__s", i), lambda i: F.get("__s", i + edges)
    least = lambda i: F.least(*[F.get("__s", i + j) for j in range(edges + 1)])
    chosen = F.filter(_spread(F.size("__h") - (k - 1)), lambda i: least(i).isin(first(i), last(i)))
    found = F.when(F.size("__h") >= k, F.transform(chosen, lambda i: F.struct(i.alias("at"), run(i).alias("hash"))))
    whole = F.when(F.size("__h") > 0, F.array(F.struct(F.lit(0).alias("at"), F.xxhash64("__h").alias("hash")))).otherwise(F.array().cast("array<struct<at:int,hash:long>>"))
    return barrier(df, name, F.coalesce(found, whole)).drop("__h", "__s")


def sketch(found: Column, keep: int = KEEP) -> Column:
    """The ``keep`` smallest distinct anchor hashes, cut to 32 bits."""
    return F.slice(F.sort_array(F.array_distinct(F.transform(found, lambda x: F.shiftrightunsigned(x["hash"], 32)))), 1, keep)


def likeness(a: Column, b: Column, keep: int = KEEP) -> Column:
    """Share of the smallest hashes of both sketches that both have."""
    union = F.slice(F.sort_array(F.array_union(a, b)), 1, keep)
    both = F.size(F.array_intersect(F.array_intersect(a, b), union))
    return F.when(F.size(union) == 0, F.lit(1.0)).otherwise(both / F.size(union))


def as_string(a: Column) -> Column:
    return F.array_join(F.transform(a, lambda x: F.lower(F.lpad(F.hex(x), 8, "0"))), "")


def anchors(documents: DataFrame) -> DataFrame:
    """(doc_id, at, hash): the anchors of whole texts as rows."""
    return syncmers(documents.select("doc_id", "text"), F.col("text"), "__a").select("doc_id", F.inline("__a"))


def positional_matches(left: DataFrame, right: DataFrame, least: int = 2) -> DataFrame:
    """(doc_id, other_id, shift, matches): anchors that two sets of documents share at one shift; ``left`` and ``right`` are ``anchors``.

    Join a stated query set against all rows; anchors within ``left`` are counted once for each place.
    """
    other = right.select(F.col("doc_id").alias("other_id"), F.col("at").alias("other_at"), "hash")
    pairs = left.join(other, "hash").where("doc_id <> other_id")
    return pairs.groupBy("doc_id", "other_id", (F.col("other_at") - F.col("at")).alias("shift")).agg(F.count("*").alias("matches")).where(F.col("matches") >= least)


def with_next(documents: DataFrame, columns: list[str], ids: DataFrame | None = None) -> DataFrame:
    """doc_id and ``columns``, and of each column next_<column>: its value in the row of the next doc_id.

    ``ids``: the same rows' doc_ids, from which alone the ranges are found, so that costly columns are computed once.

    Rows go to id ranges of about RANGE_ROWS rows; each range also receives the first row of the range after it, so that
    every row meets its successor inside one range and no range is more than a share of the table, also where very many rows have one doc_id or none.
    """
    spark = documents.sparkSession
    rows = documents.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LOWEST)).alias("__key"), "doc_id", *columns)
    keys = (documents if ids is None else ids).select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LOWEST)).alias("__key"))
    n = keys.count()
    ranges = min(MAX_RANGES, max(64, n // RANGE_ROWS))
    bounds = keys.agg(F.percentile_approx("__key", [i / ranges for i in range(1, ranges)], 100_000)).first()[0] or [0]
    bounds = sorted(set(bounds))
    edges, steps = F.lit(bounds), len(bounds).bit_length() + 1
    half = F.lit(2).cast("int")
    found = F.aggregate(
        F.sequence(F.lit(1), F.lit(steps)),
        F.struct(F.lit(0).alias("lo"), F.lit(len(bounds)).alias("hi")),
        lambda s, _: F.when(s["lo"] >= s["hi"], s).when(F.get(edges, ((s["lo"] + s["hi"]) / half).cast("int")) <= F.col("__key"), F.struct((((s["lo"] + s["hi"]) / half).cast("int") + 1).alias("lo"), s["hi"].alias("hi"))).otherwise(F.struct(s["lo"].alias("lo"), ((s["lo"] + s["hi"]) / half).cast("int").alias("hi"))),
    )
    # a range begins with the id that bounds it; one that very many rows share is cut further, by their texts' hashes, in the order of the window
    first_id = F.get(edges, F.col("__range") - 1)
    known = barrier(keys, "__range", found["lo"]).groupBy("__range").agg(F.min("__key").alias("first"), F.count_if(F.col("__key") == first_id).alias("hot")).orderBy("__range").collect()  # MAX_RANGES rows at most
    share = max(RANGE_ROWS, n // MAX_RANGES)
    parts = {r["__range"]: -(-r["hot"] // share) for r in known if r["hot"] > 4 * share}
    cuts = F.create_map(*[F.lit(x) for pair in parts.items() for x in pair]) if parts else None
    place = F.xxhash64("text")
    sub = F.lit(0)
    if parts:
        own = F.coalesce(F.element_at(cuts, F.col("__range")), F.lit(0))
        sub = F.when(own == 0, 0).when(F.col("__key") > first_id, own).otherwise(F.least(own - 1, F.floor((place.cast("double") / 2.0**64 + 0.5) * own))).cast("int")
    ranged = rows.withColumn("__range", found["lo"]).withColumn("__sub", sub)
    heads = [(r["__range"], 0, r["first"], None) for r in known]
    if parts:
        texts = documents.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LOWEST)).alias("__key"), "text").withColumn("__range", found["lo"]).where(F.col("__range").isin(list(parts)))
        inner = texts.withColumn("__sub", sub).groupBy("__range", "__sub").agg(F.min(F.struct("__key", place.alias("h"))).alias("least")).collect()
        heads = [h for h in heads if h[0] not in parts] + [(r["__range"], r["__sub"], r["least"]["__key"], r["least"]["h"]) for r in inner]
    heads.sort(key=lambda h: h[:2])
    listed = json.dumps([{"__key": h[2], "__hash": h[3], "__r": heads[i - 1][0], "__s": heads[i - 1][1]} for i, h in enumerate(heads)])
    copies = spark.range(1).select(F.inline(F.from_json(F.lit(listed), "array<struct<__key:long,__hash:long,__r:int,__s:int>>"))).groupBy("__key").agg(F.collect_list(F.struct("__hash", "__r", "__s")).alias("__heads"))
    both = ranged.join(F.broadcast(copies), "__key", "left")
    mine = F.array(F.struct(F.col("__range").alias("r"), F.col("__sub").alias("s"), F.lit(0).alias("g")))
    guests = F.transform(F.filter("__heads", lambda h: h["__hash"].isNull() | (h["__hash"] == place)), lambda h: F.struct(h["__r"].alias("r"), h["__s"].alias("s"), F.lit(1).alias("g")))
    placed = both.withColumn("__at", F.explode(F.concat(mine, F.coalesce(guests, F.array().cast("array<struct<r:int,s:int,g:int>>")))))
    placed = placed.select("__key", "doc_id", *columns, F.col("__at.r").alias("__range"), F.col("__at.s").alias("__sub"), F.col("__at.g").alias("__guest"))
    order = Window.partitionBy("__range", "__sub").orderBy("__guest", "__key", place)
    led = placed.select("__guest", "doc_id", *columns, *[F.lead(c).over(order).alias(f"next_{c}") for c in columns])
    return led.where("__guest = 0")


def op5_syncmer_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    own = syncmers(documents, F.col("text"), "__a").select("doc_id", "text", sketch(F.col("__a")).alias("sketch"))
    pairs = with_next(own, ["text", "sketch"], documents)
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - half), F.substring(F.col("next_text"), F.lit(1), half))
    pairs = barrier(pairs.withColumn("n_chars", n.cast("long")), "edited", edited).drop("text", "next_text")
    pairs = pairs.withColumn("edited_sha256", F.sha2(F.col("edited"), 256))
    both = syncmers(pairs, F.col("edited"), "__e").drop("edited")
    both = barrier(both, "edited_sketch", sketch(F.col("__e"))).drop("__e")
    return both.select(
        "doc_id",
        "n_chars",
        "edited_sha256",
        as_string(F.col("sketch")).alias("fingerprint"),
        as_string(F.col("edited_sketch")).alias("edited_fingerprint"),
        likeness(F.col("sketch"), F.col("edited_sketch")).alias("near_edited"),
        likeness(F.col("sketch"), F.col("next_sketch")).alias("near_next"),
    )
