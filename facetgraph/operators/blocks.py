"""Joins of every row with every row by blocks: rows travel packed, a task keeps the left rows of one part and reads the right ones block by block."""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetgraph.operators.kernel import squares

#: Rows of one packed block; distances that a task holds at once.
BLOCK_ROWS, CELLS = 2048, 2_000_000
#: Left rows of a part, at most.
PART_ROWS = 8192
PACKED = pa.schema([("part", pa.int32()), ("kind", pa.int32()), ("payload", pa.binary())])


class Rows:
    """id, vec and tag of some rows; tags are lists of numbers."""

    def __init__(self, ids: np.ndarray, vecs: np.ndarray, tags: np.ndarray, cuts: np.ndarray):
        self.ids, self.vecs, self.tags, self.cuts = ids, vecs, tags, cuts

    def has(self, tag: int) -> np.ndarray:
        out = np.zeros(len(self.ids), bool)
        out[np.repeat(np.arange(len(self.ids)), np.diff(self.cuts))[self.tags == tag]] = True
        return out

    @staticmethod
    def joined(parts: list[Rows]) -> Rows:
        sizes = np.concatenate([np.diff(p.cuts) for p in parts])
        return Rows(np.concatenate([p.ids for p in parts]), np.concatenate([p.vecs for p in parts]), np.concatenate([p.tags for p in parts]), np.append(0, np.cumsum(sizes)))


def _pack(kind: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, BLOCK_ROWS):
                b = whole.slice(at, BLOCK_ROWS)
                part, ids, lists = b.column("part").to_numpy(), b.column("id").to_numpy(), b.column("tags")
                vecs = np.asarray(b.column("vec").flatten(), np.float64).reshape(b.num_rows, -1)
                sizes, flat = np.asarray(pa.compute.list_value_length(lists)), np.asarray(lists.flatten())
                begin = np.cumsum(sizes) - sizes
                for p in np.unique(part):
                    mine = np.flatnonzero(part == p)
                    tags = np.concatenate([flat[begin[i] : begin[i] + sizes[i]] for i in mine])
                    payload = pickle.dumps((ids[mine], vecs[mine], tags, np.append(0, np.cumsum(sizes[mine]))), 5)
                    yield pa.RecordBatch.from_arrays([pa.array([p], pa.int32()), pa.array([kind], pa.int32()), pa.array([payload], pa.binary())], schema=PACKED)

    return run


def meet(left: DataFrame, right: DataFrame, parts: int, state: Callable[[Rows], object], schema: str) -> DataFrame:
    """``left`` and ``right`` are (id, vec, tags); of each part of the left rows ``state`` makes an object that is shown all right rows (``add``) and then gives record batches (``done``)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, mine, now = [], None, None
        for b in batches:
            for part, kind, payload in zip(*(b.column(i).to_pylist() for i in range(3))):
                if part != now:
                    if mine is not None:
                        yield from mine.done()
                    own, mine, now = [], None, part
                rows = Rows(*pickle.loads(payload))
                if kind == 0:
                    own.append(rows)
                elif own:
                    if mine is None:
                        mine = state(Rows.joined(own))
                    mine.add(rows)
        if mine is not None:
            yield from mine.done()

    sql = "part int, kind int, payload binary"
    asks = left.where("vec is not null").select(F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int").alias("part"), "id", "vec", "tags").mapInArrow(_pack(0), sql)
    all_ = right.where("vec is not null").select(F.lit(0).alias("part"), "id", "vec", "tags").mapInArrow(_pack(1), sql)
    sent = all_.select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), "kind", "payload")
    return asks.union(sent).repartition(4 * parts, "part").sortWithinPartitions("part", "kind").mapInArrow(run, schema)


def parts_for(left: DataFrame, rows: int = PART_ROWS) -> int:
    """Parts of at most about ``rows`` left rows; of few left rows as many as there are cores, since each part reads all right rows."""
    n = left.count()
    return max(1, -(-n // rows), min(left.sparkSession.sparkContext.defaultParallelism, n // 256))


def near_of(left: Rows, right: Rows, a: int, b: int) -> np.ndarray:
    """Squared distances of the left rows from a to b by matrix product, infinite for a row and itself; small ones, where the product loses digits, anew in full."""
    x, y = left.vecs[a:b], right.vecs
    xx, yy = np.einsum("ij,ij->i", x, x), np.einsum("ij,ij->i", y, y)
    d = xx[:, None] - 2 * x @ y.T + yy[None, :]
    at, to = np.nonzero(d < 1e-4 * xx[:, None])
    if len(at):
        d[at, to] = squares(x[at], y[to])
    np.maximum(d, 0, out=d)
    if len(np.intersect1d(left.ids[a:b], right.ids)):
        d[left.ids[a:b][:, None] == right.ids[None, :]] = np.inf
    return d


def steps(left: Rows, right: Rows) -> Iterator[tuple[int, int]]:
    step = max(1, CELLS // max(1, len(right.ids)))
    return ((a, min(a + step, len(left.ids))) for a in range(0, len(left.ids), step))


class Nearest:
    """The k nearest right rows of each left row, ties by id: (src, pos, dst, dist)."""

    def __init__(self, left: Rows, k: int):
        self.left, self.k = left, k
        self.dist, self.ids = np.full((len(left.ids), 0), np.inf), np.zeros((len(left.ids), 0), np.int64)

    def add(self, right: Rows) -> None:
        most = min(self.k, self.dist.shape[1] + len(right.ids))
        dist, ids = np.full((len(self.left.ids), most), np.inf), np.full((len(self.left.ids), most), -1)
        for a, b in steps(self.left, right):
            d = near_of(self.left, right, a, b)
            take = min(self.k, d.shape[1])
            bound = np.partition(d, take - 1, axis=1)[:, take - 1]
            if self.dist.shape[1] >= self.k:
                bound = np.minimum(bound, self.dist[a:b, self.k - 1])
            at, to = np.nonzero(d <= (bound * (1 + 1e-9) + 1e-12)[:, None])
            old = np.isfinite(self.dist[a:b])
            row = np.concatenate([np.nonzero(old)[0], at])
            value = np.concatenate([self.dist[a:b][old], np.where(np.isfinite(d[at, to]), squares(self.left.vecs[a + at], right.vecs[to]), np.inf)])
            other = np.concatenate([self.ids[a:b][old], right.ids[to]])
            order = np.lexsort((other, value, row))
            order = order[np.isfinite(value[order])]
            row, value, other = row[order], value[order], other[order]
            n = np.bincount(row, minlength=b - a)
            pos = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)
            ok = pos < most
            dist[a + row[ok], pos[ok]], ids[a + row[ok], pos[ok]] = value[ok], other[ok]
        self.dist, self.ids = dist, ids

    def done(self) -> Iterator[pa.RecordBatch]:
        for a in range(0, len(self.left.ids), 1024):
            at, pos = np.nonzero(np.isfinite(self.dist[a : a + 1024]))
            yield pa.RecordBatch.from_arrays([pa.array(self.left.ids[a + at]), pa.array(pos.astype(np.int32)), pa.array(self.ids[a + at, pos]), pa.array(self.dist[a + at, pos])], ["src", "pos", "dst", "dist"])


class Closest:
    """The distance of each left row to its nearest right row with a tag, and to its nearest right row: (id, inside, any)."""

    def __init__(self, left: Rows):
        self.left, self.best = left, np.full((2, len(left.ids)), np.inf)

    def add(self, right: Rows) -> None:
        tagged = np.diff(right.cuts) > 0
        for a, b in steps(self.left, right):
            d = near_of(self.left, right, a, b)
            for i, ok in enumerate((tagged, np.ones(len(tagged), bool))):
                if ok.any():
                    to = np.flatnonzero(ok)[np.argmin(d[:, ok], axis=1)]
                    full = np.where(np.isfinite(d[np.arange(b - a), to]), squares(self.left.vecs[a:b], right.vecs[to]), np.inf)
                    self.best[i, a:b] = np.minimum(self.best[i, a:b], full)

    def done(self) -> Iterator[pa.RecordBatch]:
        inside, any_ = (pa.array(np.sqrt(x), mask=~np.isfinite(x)) for x in self.best)
        yield pa.RecordBatch.from_arrays([pa.array(self.left.ids), inside, any_], ["id", "inside", "any"])


class Subsets:
    """Of each left row, whose tag is a predicate's number: the nearest t right rows that pass it, summed, and what the nearest t of a random subset as large would sum to.

    The weight of the i-th nearest row is the chance that it is among the subset's nearest t. Weights fall with i, and from ``ranks[predicate]`` on
    they add up to less than a double can tell: as many distances are kept, all where the subset is small.
    """

    def __init__(self, left: Rows, weights: dict[int, np.ndarray], t: int):
        self.left, self.weights, self.t = left, weights, t
        self.near = {p: np.full((int((left.tags == p).sum()), 0), np.inf) for p in weights}
        self.true = {p: np.full((len(x), 0), np.inf) for p, x in self.near.items()}
        self.own = {p: left.has(p) for p in weights}

    def add(self, right: Rows) -> None:
        for p, w in self.weights.items():
            mine = np.flatnonzero(self.own[p])
            if not len(mine):
                continue
            group, ok = Rows(self.left.ids[mine], self.left.vecs[mine], self.left.tags[:0], self.left.cuts[:1]), right.has(p)
            for name, limit, only in (("near", len(w), slice(None)), ("true", self.t, ok)):
                old = getattr(self, name)[p]
                some = right if name == "near" else Rows(right.ids[ok], right.vecs[ok], right.tags, right.cuts)
                if not len(some.ids):
                    continue
                most = min(limit, old.shape[1] + len(some.ids))
                fresh = np.empty((len(mine), most))
                step = max(1, CELLS // (old.shape[1] + len(some.ids)))
                for a in range(0, len(mine), step):
                    both = np.concatenate([old[a : a + step], near_of(group, some, a, min(a + step, len(mine)))], axis=1)
                    fresh[a : a + step] = both if most == both.shape[1] else np.partition(both, most - 1, axis=1)[:, :most]
                getattr(self, name)[p] = fresh

    def done(self) -> Iterator[pa.RecordBatch]:
        for p, w in self.weights.items():
            mine = np.flatnonzero(self.own[p])
            for a in range(0, len(mine), 256):
                near, true = np.sqrt(np.sort(self.near[p][a : a + 256], axis=1)), np.sqrt(np.sort(self.true[p][a : a + 256], axis=1))
                # a row itself stands last, at an infinite distance
                expected = [float(np.cumsum(x[: min(len(w), np.isfinite(x).sum())] * w[: np.isfinite(x).sum()])[-1]) for x in near]
                nearest = np.where(np.isfinite(true), true, 0).sum(axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(self.left.ids[mine[a : a + 256]]), pa.array(expected), pa.array(nearest)], ["query_id", "expected", "nearest"])


class Before:
    """How many right rows come before a place in each left row's order of distance and id; the left vectors end with the place's distance and id."""

    def __init__(self, left: Rows):
        self.at, self.id = left.vecs[:, -2], left.vecs[:, -1]
        self.left, self.count = Rows(left.ids, np.ascontiguousarray(left.vecs[:, :-2]), left.tags, left.cuts), np.zeros(len(left.ids), np.int64)

    def add(self, right: Rows) -> None:
        for a, b in steps(self.left, right):
            d, at = near_of(self.left, right, a, b), self.at[a:b]
            edge = 1e-9 * (1 + at**2)[:, None]
            self.count[a:b] += (d < at[:, None] ** 2 - edge).sum(axis=1)
            row, to = np.nonzero(np.abs(d - at[:, None] ** 2) <= edge)
            full = np.sqrt(squares(self.left.vecs[a + row], right.vecs[to]))
            before = (full < at[row]) | (full == at[row]) & (right.ids[to] < self.id[a + row])
            np.add.at(self.count, a + row[before], 1)

    def done(self) -> Iterator[pa.RecordBatch]:
        yield pa.RecordBatch.from_arrays([pa.array(self.left.ids), pa.array(self.count)], ["query_id", "before"])
