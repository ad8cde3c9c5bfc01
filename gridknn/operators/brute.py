"""The quadratic baseline: every query against every training point, block against block."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.metrics import Metric, metric
from .local import NN, _nearest, _norm, _numpy_dist, lists, no_neighbours, train_blocks, unify

#: Queries of a block, and blocks of training points that a task goes through for each of them.
QUERIES, BLOCKS = 1024, 256
#: Distances held at once, and queries and points of a matrix in single precision.
MATRIX, SINGLE = 1 << 18, (256, 512)


def all_knn(query: DataFrame, train: DataFrame, d: int, k: int, which: str = "euclidean", physical: str = "arrow", exclude_self: bool = False) -> DataFrame:
    """pid, nn: exact by construction.

    The training points become blocks of bounded size. A task takes a block of queries through
    them one after another and keeps k neighbours of each, so neither pairs nor lists of single
    blocks are written anywhere. Of training points at one place only the first k by tid can be
    neighbours; the others stay out. The cost is |I| * |T| all the same, where places differ.
    """
    if physical == "arrow":
        blocks = _blocks(_firsts(train, d, k + 1 if exclude_self else k), d)
        n = blocks.count()
        if not n:
            return query.select("pid", no_neighbours().alias("nn"))
        return _met(query, blocks, n, d, k, metric(which), exclude_self)
    parts = -(-train.count() // 4096) or 1
    blocks = _blocks(train, d, parts)
    fanned = query.withColumn("cell", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(parts - 1).cast("long"))))
    return unify(lists(fanned, blocks, d, k, which, physical, exclude_self=exclude_self, keep_empty=True), k, [], wide=parts > 64)


def _blocks(train: DataFrame, d: int, parts: int | None = None) -> DataFrame:
    parts = parts or -(-train.count() // 4096) or 1
    return train_blocks(train.withColumn("cell", F.pmod(F.xxhash64("tid"), F.lit(parts)).cast("long")), d)


def _firsts(train: DataFrame, d: int, k: int) -> DataFrame:
    """Of the training points at one place the k that come first among equal distances."""
    place = Window.partitionBy(*[f"t{i}" for i in range(d)]).orderBy("tid")
    return train.withColumn("rank", F.row_number().over(place)).filter(F.col("rank") <= k).drop("rank")


def _met(query: DataFrame, blocks: DataFrame, n: int, d: int, k: int, m: Metric, exclude_self: bool) -> DataFrame:
    """Each block of queries with each of the n blocks of points, those of one block of queries in a row."""
    names = ["pid", *[f"q{i}" for i in range(d)]]
    query = query.select(*names)
    packed = query.mapInArrow(_packed, "qs array<struct<" + ", ".join(f"{f.name}: {f.dataType.simpleString()}" for f in query.schema) + ">>")
    packed = packed.repartition(4 * query.sparkSession.sparkContext.defaultParallelism)
    sides = -(-n // BLOCKS)
    points = blocks.select("pts").coalesce(1) if sides == 1 else blocks.select("pts").repartition(sides)
    met = packed.hint("shuffle_replicate_nl").crossJoin(points).mapInArrow(_running(d, k, m, exclude_self), f"pid bigint, nn {NN}")
    return met if sides == 1 else unify(met, k, [], wide=sides > 64)


def _packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows as arrays of at most QUERIES of them."""
    for batch in batches:
        for x in range(0, batch.num_rows, QUERIES):
            rows = batch.slice(x, QUERIES).to_struct_array()
            yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array([0, len(rows)], pa.int32()), rows)], names=["qs"])


class _Nearest:
    """The k nearest so far of each query of a block."""

    def __init__(self, qs: pa.StructArray, d: int, k: int, m: Metric, exclude_self: bool):
        self.pid = qs.field("pid").to_numpy(zero_copy_only=False)
        self.q = [qs.field(f"q{i}").to_numpy(zero_copy_only=False) for i in range(d)]
        self.k, self.m, self.exclude_self = k, m, exclude_self
        shape = (len(qs), k)
        self.dist, self.tid, self.cls = np.full(shape, np.inf), np.zeros(shape, np.int64), np.zeros(shape, np.int64)

    def meet(self, t: list[np.ndarray], tid: np.ndarray, cls: np.ndarray) -> None:
        close = self._close(t) if self.m.p == 2 and not np.isinf(self.dist[:, -1]).any() else None
        if close:
            i, j = close
            dist = _norm(self.m, [a[i] - b[j] for a, b in zip(self.q, t, strict=True)])
            near = dist <= self.dist[i, -1]
            if self.exclude_self:
                near &= tid[j] != self.pid[i]
            if near.any():
                self._take(0, i[near], dist[near], tid[j[near]], cls[j[near]])
            return
        step = max(1, MATRIX // max(1, len(tid)))
        for x in range(0, len(self.pid), step):
            at = slice(x, x + step)
            dist = _numpy_dist(self.m, [c[at] for c in self.q], t)
            other = tid[None, :] != self.pid[at, None] if self.exclude_self else None
            last = self.dist[at, -1:]
            if np.isinf(last).any():
                i, j = _nearest(dist, self.k, other)
            else:
                i, j = np.nonzero(dist <= last if other is None else (dist <= last) & other)
            if len(i):
                self._take(x, i, dist[i, j], tid[j], cls[j])

    def _close(self, t: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray] | None:
        """All pairs that single precision can't rule out of the k nearest so far: squares as one product of matrices, with room for its error.

        None where squares are beyond what it can hold.
        """
        mid = [(c.min() + c.max()) / 2 for c in t]
        q, p = (np.stack([c - x for c, x in zip(side, mid, strict=True)]) for side in (self.q, t))
        squares, own = (p * p).sum(axis=0), (q * q).sum(axis=0)
        most = (np.sqrt(squares.max()) + np.sqrt(own.max())) ** 2
        if not 1e-20 < most < 1e30:
            return None
        room = (len(q) + 4) * 2.0**-23 * most
        left = np.vstack([-2 * q, np.ones(q.shape[1])]).T.astype(np.float32)
        right = np.vstack([p, squares]).astype(np.float32)
        most = np.minimum(self.dist[:, -1] ** 2 * (1 + 1e-9) - own + room, 4 * most).astype(np.float32)
        found = []
        out = np.empty(SINGLE, np.float32)
        for x in range(0, left.shape[0], SINGLE[0]):
            mine, last = left[x : x + SINGLE[0]], most[x : x + SINGLE[0]]
            for y in range(0, right.shape[1], SINGLE[1]):
                some = right[:, y : y + SINGLE[1]]
                made = np.matmul(mine, some, out=out) if (len(mine), some.shape[1]) == SINGLE else mine @ some
                rows = np.flatnonzero(made.min(axis=1) <= last)
                if len(rows):
                    i, j = np.nonzero(made[rows] <= last[rows, None])
                    found.append((rows[i] + x, j + y))
        if not found:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        return tuple(np.concatenate(c) for c in zip(*found, strict=True))

    def _take(self, x: int, i: np.ndarray, dist: np.ndarray, tid: np.ndarray, cls: np.ndarray) -> None:
        rows = np.unique(i)
        old, slot = np.nonzero(self.dist[x + rows] < np.inf)
        old = rows[old]
        row = np.concatenate([old, i])
        dist, tid, cls = (np.concatenate([was[x + old, slot], new]) for was, new in ((self.dist, dist), (self.tid, tid), (self.cls, cls)))
        order = np.lexsort((tid, dist, row))
        row = row[order]
        rank = np.arange(len(row)) - np.searchsorted(row, row)
        order, row, rank = order[rank < self.k], row[rank < self.k], rank[rank < self.k]
        for kept, new in ((self.dist, dist), (self.tid, tid), (self.cls, cls)):
            kept[x + row, rank] = new[order]

    def batch(self, classes: list[str | None]) -> pa.RecordBatch:
        full = self.dist < np.inf
        values = pa.StructArray.from_arrays([pa.array(self.dist[full]), pa.array(self.tid[full]), pa.array(classes, pa.string()).take(pa.array(self.cls[full]))], names=["dist", "tid", "cls"])
        nn = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(full.sum(axis=1))]).astype(np.int32)), values)
        return pa.RecordBatch.from_arrays([pa.array(self.pid), nn], names=["pid", "nn"])


def _running(d: int, k: int, m: Metric, exclude_self: bool):
    """Rows (qs, pts), of which those of one block of queries follow each other, to its lists."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, best, codes = None, None, {}
        for batch in batches:
            for row in range(batch.num_rows):
                qs, pts = batch.column(0)[row].values, batch.column(1)[row].values
                if qs.field("pid")[0].as_py() != now:
                    if best:
                        yield best.batch(list(codes))
                    now, best, codes = qs.field("pid")[0].as_py(), _Nearest(qs, d, k, m, exclude_self), {}
                named = pts.field("cls").dictionary_encode(null_encoding="encode")
                code = np.array([codes.setdefault(c, len(codes)) for c in named.dictionary.to_pylist()])
                best.meet([pts.field(f"t{i}").to_numpy(zero_copy_only=False) for i in range(d)], pts.field("tid").to_numpy(zero_copy_only=False), code[named.indices.to_numpy(zero_copy_only=False)])
        if best:
            yield best.batch(list(codes))

    return scan
