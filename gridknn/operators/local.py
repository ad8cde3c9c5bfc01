"""Neighbour lists from one block of training points at a time.

Lists are array<struct<dist double, tid bigint, cls string>>, nearest first, ties by tid.
Training points of a cell are dealt into chunks of about CHUNK points, so a hot cell is
spread over tasks and no array grows with the data; lists of chunks are unified later.
"""

from __future__ import annotations

import math
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.metrics import SLACK, SLACK_ABS, Metric, metric
from ..sources.shared import stored

#: Points of a block, and queries of a block.
CHUNK, QUERIES = 1 << 16, 1 << 15
#: Points and queries of a tile, and distances that are held at once (more would be mapped and faulted in anew each time).
LEAF, TILE, MATRIX = 32, 64, 1 << 14
#: Groups of lists that are united first where a query may have very many.
WIDE = 64
NN = "array<struct<dist:double,tid:bigint,cls:string>>"
PHYSICAL = ("pairs", "blocked", "arrow")


def no_neighbours() -> Column:
    return F.array().cast(NN)


def top(nn: Column, k: int) -> Column:
    return F.slice(F.array_sort(nn), 1, k)


def chunks(counts: DataFrame) -> int:
    """Chunks that the fullest cell needs, from counts (cell, n): one number for the driver."""
    return -(-(counts.agg(F.max("n").alias("m")).first()["m"] or 0) // CHUNK) or 1


def _chunked(points: DataFrame, counts: DataFrame, id: str, size: int) -> DataFrame:
    """points with the column chunk: as many chunks of about `size` for each cell as its own points need."""
    parts = F.ceil(F.col("n") / size)
    return points.join(counts.select("cell", "n"), "cell").withColumn("chunk", F.pmod(F.xxhash64(id), parts).cast("int")).drop("n")


def train_blocks(train: DataFrame, d: int, counts: DataFrame | None = None) -> DataFrame:
    """cell, chunk, pts: the training points as rows of bounded arrays by tid, stored and read by every later probe."""
    counts = train.groupBy("cell").agg(F.count("*").alias("n")) if counts is None else counts
    point = F.struct("tid", *[F.col(f"t{i}") for i in range(d)], "cls")
    return stored(_chunked(train, counts, "tid", CHUNK).groupBy("cell", "chunk").agg(F.sort_array(F.collect_list(point)).alias("pts")), "train-blocks")


def query_blocks(queries: DataFrame, names: list[str]) -> DataFrame:
    """cell, qs: queries of a cell in bounded arrays, so that a block of points is sent once for each of them."""
    counts = queries.groupBy("cell").agg(F.count("*").alias("n"))
    return _chunked(queries, counts, "pid", QUERIES).groupBy("cell", "chunk").agg(F.collect_list(F.struct(*names)).alias("qs")).select("cell", "qs")


def lists(queries: DataFrame, blocks: DataFrame, d: int, k: int, which: str = "euclidean", physical: str = "arrow", within: bool = False, exclude_self: bool = False, keep_empty: bool = False) -> DataFrame:
    """pid, q0.., nn: for each (query, cell) row the k best of that cell's points, one row for each chunk.

    within: only points no farther than the query's r. keep_empty: queries of cells without
    training points stay, with an empty list.
    """
    if physical not in PHYSICAL:
        raise ValueError(f"unknown physical form {physical}")
    m = metric(which)
    q = [F.col(f"q{i}") for i in range(d)]
    names = ["pid", *[f"q{i}" for i in range(d)]] + (["r"] if within else [])
    how = "left" if keep_empty else "inner"
    if physical == "arrow":
        joined = query_blocks(queries.select(*names, "cell"), names).join(blocks, "cell", how)
        return _numpy_lists(joined, queries.select(*names, "cell"), d, k, m, within, exclude_self)
    joined = queries.select(*names, "cell").join(blocks, "cell", how)

    def keep(x: Column) -> Column:
        ok = F.lit(True)
        if within:
            ok = ok & (x["dist"] <= F.col("r") * (1 + SLACK) + SLACK_ABS)
        return ok & (x["tid"] != F.col("pid")) if exclude_self else ok

    if physical == "blocked":
        seen = F.transform("pts", lambda p: F.struct(m.dist(q, [p[f"t{i}"] for i in range(d)]).alias("dist"), p["tid"].alias("tid"), p["cls"].alias("cls")))
        seen = F.filter(seen, keep) if within or exclude_self else seen
        return joined.select(*names, "cell", F.coalesce(top(seen, k), no_neighbours()).alias("nn"))
    if physical == "pairs":
        pairs = joined.select(*names, "cell", F.explode_outer("pts").alias("p"))
        hit = F.struct(m.dist(q, [F.col(f"p.t{i}") for i in range(d)]).alias("dist"), F.col("p.tid").alias("tid"), F.col("p.cls").alias("cls"))
        pairs = pairs.withColumn("x", F.when(F.col("p").isNotNull() & keep(hit), hit))
        if not keep_empty:
            pairs = pairs.filter("x is not null")
        best = Window.partitionBy("pid", "cell").orderBy(F.col("x.dist").asc_nulls_last(), "x.tid")
        ranked = pairs.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k)
    first = [F.first(c).alias(c) for c in names[1:]]
    return ranked.groupBy("pid", "cell").agg(*first, F.array_sort(F.collect_list("x")).alias("nn")).select(*names, "cell", F.col("nn").cast(NN).alias("nn"))


def _norm(m: Metric, parts: Iterable[np.ndarray]) -> np.ndarray:
    """The norm of per-axis differences, summed in the order of the axes."""
    if m.p == 2:
        parts = (x * x for x in parts)
    else:
        parts = (np.abs(x) for x in parts)
        if m.p not in (1, np.inf):
            parts = (x**m.p for x in parts)
    parts = iter(parts)
    total = next(parts)
    for x in parts:
        total = np.maximum(total, x) if m.p == np.inf else total + x
    return np.sqrt(total) if m.p == 2 else total if m.p in (1, np.inf) else total ** (1.0 / m.p)


def _numpy_dist(m: Metric, q: list[np.ndarray], t: list[np.ndarray]) -> np.ndarray:
    """Distances of all queries (rows) to all points (columns)."""
    return _norm(m, (a[:, None] - b[None, :] for a, b in zip(q, t, strict=True)))


def _nearest(dist: np.ndarray, k: int, allowed: np.ndarray | None, few: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of the k smallest of each row, by row and distance; ties go to the smaller column.

    few: not many more than k of a row are allowed.
    """
    if allowed is not None and not few:
        dist = np.where(allowed, dist, np.inf)
    near = allowed if few else dist < np.inf if allowed is not None else np.ones(dist.shape, bool)
    if dist.shape[1] > k and not few:
        near &= dist <= np.partition(dist, k - 1, axis=1)[:, k - 1 : k]
    row, column = np.nonzero(near)
    order = np.lexsort((column, dist[row, column], row))
    row, column = row[order], column[order]
    rank = np.arange(len(row)) - np.searchsorted(row, row)
    return row[rank < k], column[rank < k]


def _tiled(at: list[np.ndarray], size: int) -> np.ndarray:
    """An order of points in which each run of `size` lies close together: sorted along the first axis, strips of that along the next."""
    n, d = len(at[0]), len(at)
    order = np.argsort(at[0], kind="stable")
    strips = max(1, math.ceil((n / size) ** (1 / d)))
    for i in range(1, d):
        strip = np.arange(n) // (size * strips ** (d - i))
        order = order[np.lexsort((at[i][order], strip))]
    return order


class Tiles:
    """The points of a block in tiles, each with its box, so that a tile of queries meets only those that can matter."""

    def __init__(self, t: list[np.ndarray], tid: np.ndarray):
        self.t, self.tid, self.order = t, tid, _tiled(t, LEAF)
        self.starts = np.arange(0, len(tid), LEAF)
        self.lo, self.hi = ([f.reduceat(c[self.order], self.starts) for c in t] for f in (np.minimum, np.maximum))

    def holds(self, t: list[np.ndarray], tid: np.ndarray) -> bool:
        return np.array_equal(tid, self.tid) and all(np.array_equal(a, b) for a, b in zip(t, self.t, strict=True))

    def near(self, q: list[np.ndarray], k: int, m: Metric, most: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ascending places of points, among them the k nearest of each query, with ties, as far as they are within `most`, and how far the k-th can be."""
        low, high = [c.min() for c in q], [c.max() for c in q]
        gap = _norm(m, [np.maximum(np.maximum(a - y, x - b), 0.0) for x, y, a, b in zip(low, high, self.lo, self.hi, strict=True)])
        # all tiles but the last are full
        need = -(-k // LEAF) + 1
        if need <= len(gap):
            far = _norm(m, [np.maximum(b - x, y - a) for x, y, a, b in zip(low, high, self.lo, self.hi, strict=True)])
            first = self._places(np.argpartition(far, need - 1)[:need])
            dist = _numpy_dist(m, q, [c[first] for c in self.t])
            most = np.minimum(most, np.partition(dist, k - 1, axis=1)[:, k - 1])
        return np.sort(self._places(np.flatnonzero(gap <= most.max() * (1 + SLACK) + SLACK_ABS))), most

    def _places(self, tiles: np.ndarray) -> np.ndarray:
        at = (self.starts[tiles, None] + np.arange(LEAF)).ravel()
        return self.order[at[at < len(self.order)]]


def _block_lists(q: list[np.ndarray], pid: np.ndarray, r: np.ndarray | None, t: list[np.ndarray], tid: np.ndarray, tiles: Tiles | None, k: int, m: Metric, exclude_self: bool) -> Iterator[tuple[np.ndarray, ...]]:
    """(places of queries, lengths of their lists, distances, places of points), some queries at a time."""
    order = np.arange(len(pid)) if tiles is None else _tiled(q, TILE)
    step = max(1, MATRIX // max(1, len(tid))) if tiles is None else TILE
    for x in range(0, len(pid), step):
        at = order[x : x + step]
        mine, reach = [c[at] for c in q], None if r is None else r[at] * (1 + SLACK) + SLACK_ABS
        some = slice(None)
        if tiles is not None:
            some, reach = tiles.near(mine, k + exclude_self, m, np.full(len(at), np.inf) if reach is None else reach)
        dist = _numpy_dist(m, mine, [c[some] for c in t])
        allowed = None if reach is None else dist <= reach[:, None]
        if exclude_self:
            other = tid[None, some] != pid[at, None]
            allowed = other if allowed is None else allowed & other
        i, j = _nearest(dist, k, allowed, tiles is not None)
        yield at, np.bincount(i, minlength=len(at)), dist[i, j], j if tiles is None else some[j]


def _tiles_of(t: list[np.ndarray], tid: np.ndarray, q: list[np.ndarray], made: list[Tiles]) -> Tiles | None:
    """Tiles of a block, kept in `made` for the next queries; none for a small block, or where boxes or ids don't bound what is near."""
    if len(tid) <= 8 * LEAF or len(q[0]) < 8 or (tid[1:] == tid[:-1]).any() or not all(np.isfinite(c).all() for c in (*t, *q)):
        return None
    for tiles in made:
        if tiles.holds(t, tid):
            return tiles
    made.append(Tiles(t, tid))
    del made[:-4]
    return made[-1]


def _numpy_lists(joined: DataFrame, queries: DataFrame, d: int, k: int, m: Metric, within: bool, exclude_self: bool) -> DataFrame:
    """A block of queries against a block of points, in small matrices: no row for each pair, and no copy of points for each query.

    In a large block both lie in tiles, and a tile of queries meets those tiles of points whose boxes are near enough.
    """
    names = queries.columns
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in queries.schema) + f", nn {NN}"
    nn_type = pa.list_(pa.struct([("dist", pa.float64()), ("tid", pa.int64()), ("cls", pa.string())]))

    def rows(q: list[np.ndarray], cell: np.ndarray, tid: np.ndarray, cls: pa.Array, found: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
        at, sizes, dists, take = (np.concatenate(c) for c in zip(*found, strict=True))
        values = pa.StructArray.from_arrays([pa.array(dists), pa.array(tid[take]), cls.take(pa.array(take))], names=["dist", "tid", "cls"])
        nn = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), values).cast(nn_type)
        return pa.RecordBatch.from_arrays([*(pa.array(c[at]) for c in q), pa.array(cell[at]), nn], names=[*names, "nn"])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made: list[Tiles] = []
        for batch in batches:
            qs, pts = batch.column(0), batch.column(1)
            flat, points = qs.values, pts.values
            q_at, t_at = qs.offsets.to_numpy(), pts.offsets.to_numpy()
            cell = np.zeros(len(flat), np.int64)
            cell[q_at[0] : q_at[-1]] = np.repeat(batch.column(2).to_numpy(), np.diff(q_at))
            q = [flat.field(c).to_numpy(zero_copy_only=False) for c in names[:-1]]
            t = [points.field(f"t{i}").to_numpy(zero_copy_only=False) for i in range(d)]
            tid, cls = points.field("tid").to_numpy(zero_copy_only=False), points.field("cls")
            found: list[tuple[np.ndarray, ...]] = []
            held = 0
            for row in range(batch.num_rows):
                some, block = slice(int(q_at[row]), int(q_at[row + 1])), slice(int(t_at[row]), int(t_at[row + 1]))
                mine, near, ids = [c[some] for c in q], [c[block] for c in t], tid[block]
                tiles = _tiles_of(near, ids, mine[1 : 1 + d], made)
                for at, sizes, dists, take in _block_lists(mine[1 : 1 + d], mine[0], mine[1 + d] if within else None, near, ids, tiles, k, m, exclude_self):
                    found.append((at + some.start, sizes, dists, take + block.start))
                    held += len(at)
                    if held >= QUERIES:
                        yield rows(q, cell, tid, cls, found)
                        found, held = [], 0
            if found:
                yield rows(q, cell, tid, cls, found)

    empty = F.array().cast(joined.schema["pts"].dataType)
    return joined.select("qs", F.coalesce("pts", empty).alias("pts"), "cell").mapInArrow(scan, schema)


def unify(parts: DataFrame, k: int, carry: list[str], wide: bool = False) -> DataFrame:
    """All lists of a query into one of its k nearest; carry: columns that are equal in all of them.

    wide: a query may have very many lists, so groups of them are united first.
    """
    firsts = [F.first(c).alias(c) for c in carry]
    flat = top(F.array_distinct(F.flatten(F.collect_list("nn"))), k).alias("nn")
    if wide:
        parts = parts.withColumn("part", F.pmod(F.xxhash64("nn"), F.lit(WIDE))).groupBy("pid", "part").agg(*firsts, flat)
    return parts.groupBy("pid").agg(*firsts, flat)
