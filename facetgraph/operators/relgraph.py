"""Graph methods as relations: exact kNN lists, lookups, pruning tests, search in rounds. Edges are (shard, level, src, pos, dst, dist), pos from 0."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from facetgraph.functions import vectors as V
from facetgraph.operators import blocks
from facetgraph.operators.index import level_of


def nodes_of(vectors: DataFrame, m: int, seed: int, shards: int = 1) -> DataFrame:
    return vectors.select("id", "vec", level_of(F.col("id"), m, seed).alias("top_level"), F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int").alias("shard"))


def knn_join(left: DataFrame, right: DataFrame, k: int) -> DataFrame:
    """(shard, src, pos, dst, dist): the k nearest of each left row within its shard."""
    a = left.select("shard", F.col("id").alias("src"), F.col("vec").alias("a"))
    b = right.select("shard", F.col("id").alias("dst"), F.col("vec").alias("b"))
    pairs = a.join(b, "shard").where("src <> dst").select("shard", "src", "dst", V.l2_squared(F.col("a"), F.col("b")).alias("dist"))
    w = Window.partitionBy("src").orderBy("dist", "dst")
    return pairs.withColumn("pos", (F.row_number().over(w) - 1).cast("int")).where(F.col("pos") < k).select("shard", "src", "pos", "dst", "dist")


def knn_graph(nodes: DataFrame, level: int, width: int) -> DataFrame:
    """One level's lists before compression."""
    on = nodes.where(F.col("top_level") >= level)
    return knn_join(on, on, width).withColumn("level", F.lit(level))


def knn_of(left: DataFrame, right: DataFrame, k: int) -> DataFrame:
    """(src, pos, dst, dist): the k nearest right rows of each left row, of (id, vec), by blocks."""
    tagged = lambda rows: rows.select("id", "vec", F.array().cast("array<int>").alias("tags"))
    return blocks.meet(tagged(left), tagged(right), blocks.parts_for(left), lambda own: blocks.Nearest(own, k), "src long, pos int, dst long, dist double")


def blocked_join(vectors: DataFrame, k: int, blocks: int, overlap: int = 2) -> DataFrame:
    """Approximate kNN: every row is in the ``overlap`` nearest of ``blocks`` cells around spread-out rows and meets the rows of its cells."""
    pivots = vectors.orderBy(F.xxhash64("id")).limit(blocks).collect()
    cells = F.array(*[F.struct(V.l2_squared(F.col("vec"), F.array(*[F.lit(float(x)) for x in p["vec"]])).alias("d"), F.lit(i).alias("c")) for i, p in enumerate(pivots)])
    rows = vectors.select("id", "vec", F.explode(F.transform(F.slice(F.array_sort(cells), 1, overlap), lambda z: z["c"])).alias("shard"))
    w = Window.partitionBy("src").orderBy("dist", "dst")
    found = knn_join(rows, rows, k).select("src", "dst", "dist").distinct()
    return found.withColumn("pos", (F.row_number().over(w) - 1).cast("int")).where(F.col("pos") < k)


def refine(lists: DataFrame, vectors: DataFrame, k: int) -> DataFrame:
    """One round of neighbours' neighbours on (src, dst, dist, pos)."""
    hop = lists.alias("a").join(lists.alias("b"), F.col("a.dst") == F.col("b.src")).select(F.col("a.src").alias("src"), F.col("b.dst").alias("dst")).where("src <> dst").distinct()
    new = hop.join(lists.select("src", "dst"), ["src", "dst"], "left_anti")
    scored = new.join(vectors.select(F.col("id").alias("src"), F.col("vec").alias("a")), "src").join(vectors.select(F.col("id").alias("dst"), F.col("vec").alias("b")), "dst")
    both = lists.select("src", "dst", "dist").union(scored.select("src", "dst", V.l2_squared(F.col("a"), F.col("b"))))
    w = Window.partitionBy("src").orderBy("dist", "dst")
    return both.withColumn("pos", (F.row_number().over(w) - 1).cast("int")).where(F.col("pos") < k)


def _first(rows: DataFrame, m: int, order: list[str]) -> DataFrame:
    """Of each src: its distinct passing dst by first place, the first m."""
    first = rows.where("src <> dst").groupBy("src", "dst").agg(F.min(F.struct(*order)).alias("o"))
    w = Window.partitionBy("src").orderBy("o")
    return first.withColumn("pos", (F.row_number().over(w) - 1).cast("int")).where(F.col("pos") < m).select("src", "pos", "dst")


def lookup_filtered(edges: DataFrame, passing: DataFrame, m: int) -> DataFrame:
    """``passing``: ids."""
    ok = passing.select(F.col("id").alias("dst"))
    return _first(edges.join(ok, "dst", "left_semi").withColumn("hop", F.lit(-1)), m, ["pos", "hop"])


def lookup_compressed(edges: DataFrame, passing: DataFrame, m: int, m_beta: int) -> DataFrame:
    ok = passing.select(F.col("id").alias("dst"))
    one = edges.select("src", "dst", "pos", F.lit(-1).alias("hop"))
    tail = edges.where(F.col("pos") >= m_beta).select("src", F.col("dst").alias("mid"), "pos")
    two = tail.join(edges.select(F.col("src").alias("mid"), "dst", F.col("pos").alias("hop")), "mid").select("src", "dst", "pos", "hop")
    return _first(one.union(two).join(ok, "dst", "left_semi"), m, ["pos", "hop"])


def lookup_two_hop(edges: DataFrame, passing: DataFrame, m: int) -> DataFrame:
    ok = passing.select(F.col("id").alias("dst"))
    one = edges.select("src", "dst", F.lit(0).alias("far"), "pos", F.lit(-1).alias("hop"))
    two = edges.select("src", F.col("dst").alias("mid"), "pos").join(edges.select(F.col("src").alias("mid"), "dst", F.col("pos").alias("hop")), "mid")
    return _first(one.union(two.select("src", "dst", F.lit(1).alias("far"), "pos", "hop")).join(ok, "dst", "left_semi"), m, ["far", "pos", "hop"])


def rng_graph(lists: DataFrame, vectors: DataFrame) -> DataFrame:
    """Relative-neighbour edges among candidate lists: no other candidate of src is nearer to dst and to src than dst is."""
    a = lists.select("src", F.col("dst").alias("c"), F.col("dist").alias("dc"))
    b = lists.select("src", F.col("dst").alias("a"), F.col("dist").alias("da"))
    pairs = a.join(b, "src").where("da < dc").join(vectors.select(F.col("id").alias("c"), F.col("vec").alias("cv")), "c").join(vectors.select(F.col("id").alias("a"), F.col("vec").alias("av")), "a")
    beaten = pairs.where(V.l2_squared(F.col("cv"), F.col("av")) < F.col("dc")).select("src", F.col("c").alias("dst")).distinct()
    return lists.select("src", "dst").join(beaten, ["src", "dst"], "left_anti")


def rng_kept(lists: DataFrame, vectors: DataFrame, most: int) -> DataFrame:
    """(src, pos, dst): relative-neighbour pruning as builders do it. Candidates are met nearest first; one stays unless some that stayed is nearer to it than src is, until ``most`` stayed.

    A fold over each list, in the JVM; lists are as wide as an index's, not as the table.
    """
    rows = lists.select("src", "pos", "dst", "dist").join(vectors.select(F.col("id").alias("dst"), "vec"), "dst")
    row = F.struct("pos", F.col("dst").alias("dst"), "dist", "vec")
    walk = rows.groupBy("src").agg(F.array_sort(F.collect_list(row)).alias("c"))
    near = lambda x: lambda a: V.l2_squared(a["vec"], x["vec"]) < x["dist"]
    start = F.slice("c", 1, 0)
    kept = F.aggregate("c", start, lambda s, x: F.when((F.size(s) < most) & ~F.exists(s, near(x)), F.concat(s, F.array(x))).otherwise(s))
    return walk.select("src", F.posexplode(F.transform(kept, lambda x: x["dst"])).alias("pos", "dst"))


def scc(edges: DataFrame, nodes: DataFrame, cut=lambda df: df, rounds: int = 40) -> DataFrame:
    """(id, component): strongly connected components by smallest labels passed forwards and backwards; settled parts leave and the rest repeats.

    ``cut`` shortens the lineage, for instance a checkpoint.
    """
    left, out = cut(nodes.select("id")), None
    for _ in range(rounds):
        e = cut(edges.select("src", "dst").join(left.select(F.col("id").alias("src")), "src", "left_semi").join(left.select(F.col("id").alias("dst")), "dst", "left_semi"))
        sides = []
        for a, b in (("src", "dst"), ("dst", "src")):
            label = cut(left.select("id", F.col("id").alias("c")))
            while True:
                near = e.join(label.select(F.col("id").alias(a), "c"), a).groupBy(F.col(b).alias("id")).agg(F.min("c").alias("m"))
                fresh = cut(label.join(near, "id", "left").select("id", F.col("c").alias("old"), F.least("c", F.coalesce("m", "c")).alias("c")))
                done = not fresh.where("old <> c").limit(1).count()
                label = fresh.select("id", "c")
                if done:
                    break
            sides.append(label)
        both = cut(sides[0].join(sides[1].withColumnRenamed("c", "d"), "id"))
        settled = both.where("c = d").select("id", F.col("c").alias("component"))
        out = settled if out is None else out.union(settled)
        left = cut(both.where("c <> d").select("id"))
        if not left.limit(1).count():
            return out
    raise RuntimeError("components did not settle")


def search_rounds(edges: DataFrame, vectors: DataFrame, passing: DataFrame, queries: DataFrame, entry: int, m: int, ef: int, k: int, cut=lambda df: df, expand: int = 8, rounds: int = 60) -> DataFrame:
    """Level-0 beam search of all queries together, a few nodes of each a round; for graphs larger than any executor.

    ``passing``: (pred_id, id). The beam is (query_id, pred_id, id, dist, ok, open); a round expands each query's nearest open
    nodes, keeps of their lists the first m passing unseen nodes, and cuts the beam to its ef nearest.
    """
    vec = vectors.select(F.col("id"), F.col("vec"))
    start = queries.join(vec.where(F.col("id") == entry)).select("query_id", "pred_id", "qvec", "id", V.l2_squared(F.col("vec"), F.col("qvec")).alias("dist"))
    mark = passing.select("pred_id", "id", F.lit(True).alias("p"))
    beam = cut(start.join(mark, ["pred_id", "id"], "left").select("query_id", "pred_id", "id", "dist", F.coalesce("p", F.lit(False)).alias("ok"), F.lit(True).alias("open")))
    seen = beam.select("query_id", "id")
    by = Window.partitionBy("query_id")
    for _ in range(rounds):
        ranked = beam.withColumn("r", F.row_number().over(by.orderBy(F.col("open").desc(), "dist", "id")))
        chosen = cut(ranked.where((F.col("r") <= expand) & F.col("open")).select("query_id", "pred_id", "id"))
        if not chosen.limit(1).count():
            break
        near = chosen.join(edges.select(F.col("src").alias("id"), "dst", "pos"), "id").select("query_id", "pred_id", F.col("id").alias("src"), F.col("dst").alias("id"), "pos")
        near = near.join(passing, ["pred_id", "id"], "left_semi")
        near = near.withColumn("r", F.row_number().over(Window.partitionBy("query_id", "src").orderBy("pos"))).where(F.col("r") <= m)
        fresh = near.select("query_id", "pred_id", "id").distinct().join(seen, ["query_id", "id"], "left_anti")
        scored = fresh.join(queries.select("query_id", "qvec"), "query_id").join(vec, "id").select("query_id", "pred_id", "id", V.l2_squared(F.col("vec"), F.col("qvec")).alias("dist"), F.lit(True).alias("ok"), F.lit(True).alias("open"))
        closed = beam.join(chosen.select("query_id", "id", F.lit(True).alias("c")), ["query_id", "id"], "left").select("query_id", "pred_id", "id", "dist", "ok", (F.col("open") & F.col("c").isNull()).alias("open"))
        scored = cut(scored)
        seen = cut(seen.union(scored.select("query_id", "id")))
        order = by.orderBy(F.col("ok").desc(), "dist", "id")
        beam = cut(closed.where("ok or open").unionByName(scored).withColumn("r", F.row_number().over(order)).where(F.col("r") <= ef).drop("r"))
    w = by.orderBy("dist", "id")
    return beam.where("ok and id <> query_id").withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "id", "dist")
