"""Best-fit-decreasing packing of tokenised documents into sequences.

Best fit looks at nothing but lengths, and lengths are bounded by the capacity. So the plan
is made from a histogram with at most `capacity` rows: longest first, each length goes to
the tightest open bins, which a segment tree over the remaining capacities finds in
logarithmic time. Bins of one history are kept as a run of consecutive sequence numbers, so
the plan's size depends on the capacity and not on the number of documents. The documents
are then numbered inside each length, in many salted groups, and look up their places.

The result equals best-fit decreasing run document by document. Null text: empty (one
token, the end mark). Repeated rows are packed as documents of their own.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textscan as ts
from .storage import saved
from .wordbpe import opened, public_path

CAPACITY = 4096
END_ID = 1
RANK_BITS = 45


class RemainingTree:
    """Segment tree over capacities 0..capacity: counts of what is open, and the tightest that fits."""

    def __init__(self, capacity: int):
        self.leaves = 1 << (capacity + 1 - 1).bit_length()
        self.held = [0] * (2 * self.leaves)

    def add(self, remaining: int, n: int = 1) -> None:
        i = self.leaves + remaining
        while i:
            self.held[i] += n
            i >>= 1

    def tightest(self, needed: int) -> int | None:
        """The smallest remaining capacity >= needed that an open bin has."""
        i = self.leaves + needed
        if self.held[i]:
            return needed
        while i > 1:
            if not i & 1 and self.held[i + 1]:
                i += 1
                while i < self.leaves:
                    i = 2 * i if self.held[2 * i] else 2 * i + 1
                return i - self.leaves
            i >>= 1
        return None


def best_fit_plan(histogram: dict[int, int], capacity: int = CAPACITY) -> np.ndarray:
    """Rows (length, first rank, documents, per sequence, first sequence, first offset), by length and rank.

    The j-th of a row's documents goes to sequence first + j // per, at offset
    first offset + (j % per) * length.
    """
    tree = RemainingTree(capacity)
    runs: dict[int, list[tuple[int, int]]] = {}
    sequences, rows = 0, []

    def open_run(first: int, count: int, remaining: int) -> None:
        if count and remaining:
            runs.setdefault(remaining, []).append((first, count))
            tree.add(remaining)

    for length in sorted(histogram, reverse=True):
        if not 0 < length <= capacity:
            raise ValueError(f"a piece of {length} tokens doesn't fit {capacity}")
        rank, left = 0, histogram[length]
        while left:
            remaining = tree.tightest(length)
            if remaining is None:
                remaining, first, count = capacity, sequences, -(-left // (capacity // length))
                sequences += count
            else:
                first, count = runs[remaining].pop()
                tree.add(remaining, -1)
            per = remaining // length
            placed = min(left, per * count)
            rows.append((length, rank, placed, per, first, capacity - remaining))
            full, over = divmod(placed, per)
            open_run(first, full, remaining - per * length)
            if over:
                open_run(first + full, 1, remaining - over * length)
            used = full + bool(over)
            open_run(first + used, count - used, remaining)
            rank, left = rank + placed, left - placed
    return np.array(sorted(rows), np.int64).reshape(-1, 6)


def tokenize(docs: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """Pieces of at most capacity tokens: key, piece, start, length, ids_crc32 (and ids)."""
    path = path or public_path()
    fields = [T.StructField(key, docs.schema[key].dataType), T.StructField("piece", T.IntegerType()), *(T.StructField(n, T.LongType()) for n in ("start", "length", "ids_crc32"))]
    schema = T.StructType(fields + [T.StructField("ids", T.ArrayType(T.IntegerType()))] * with_ids)

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = opened(path)
        for batch in batches:
            data, offsets = ts.buffers(batch.column(1))
            for a, b, ids, place in bpe.encode(data, offsets):
                ids = np.insert(ids, place[1:], END_ID).astype("<u4")
                place = place + np.arange(len(place))
                sizes = np.diff(place)
                pieces = -(-sizes // capacity)
                rows, piece = np.repeat(np.arange(b - a), pieces), ts.ragged(pieces)
                start = piece * capacity
                length = np.minimum(sizes[rows] - start, capacity)
                first = place[rows] + start
                crc = [zlib.crc32(ids[i : i + n]) for i, n in zip(first.tolist(), length.tolist(), strict=True)]
                out = [batch.column(0).take(pa.array(a + rows)), pa.array(piece.astype(np.int32)), pa.array(start), pa.array(length), pa.array(crc, pa.int64())]
                if with_ids:
                    out.append(pa.ListArray.from_arrays(pa.array(np.append(first, len(ids)).astype(np.int32)), pa.array(ids.astype(np.int32))))
                yield pa.RecordBatch.from_arrays(out, names=schema.names)

    return docs.select(key, text).mapInArrow(scan, schema)


def place_pieces(pieces: DataFrame, key: str = "doc_id", capacity: int = CAPACITY) -> DataFrame:
    """pieces (read twice, so better a stored table) with sequence_id and offset."""
    spark = pieces.sparkSession
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    plan = spark.sparkContext.broadcast(best_fit_plan(histogram, capacity))
    salts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64(key, "piece"), F.lit(salts)).cast("int"))
    inside = salted.withColumn("rank", F.row_number().over(Window.partitionBy("length", "salt").orderBy(key, "piece")) - 1)
    sizes = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    bases = sizes.select("length", "salt", (F.sum("n").over(before) - F.col("n")).alias("base"))
    ranked = inside.join(bases, ["length", "salt"]).select(*pieces.columns, (F.col("rank") + F.col("base")).alias("rank"))
    schema = T.StructType(pieces.schema.fields + [T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])
    at = pieces.columns.index("length")

    def look_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = plan.value
        keys = rows[:, 0] << RANK_BITS | rows[:, 1]
        for batch in batches:
            length, rank = batch.column(at).to_numpy(), batch.column(batch.num_columns - 1).to_numpy()
            row = rows[np.searchsorted(keys, length << RANK_BITS | rank, "right") - 1] if len(rows) else np.zeros((0, 6), np.int64)
            j = rank - row[:, 1]
            sequence, offset = row[:, 4] + j // np.maximum(row[:, 3], 1), row[:, 5] + j % np.maximum(row[:, 3], 1) * length
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(sequence), pa.array(offset)], names=schema.names)

    return ranked.mapInArrow(look_up, schema)


def pack_documents(docs: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """One row per piece: key, piece, start, length, ids_crc32, sequence_id, offset."""
    return place_pieces(saved(tokenize(docs, key, text, path, capacity), "pieces"), key, capacity)


def sequences(docs: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """The packed sequences themselves: sequence_id, ids, and where each document's piece lies."""
    placed = place_pieces(saved(tokenize(docs, key, text, path, capacity, with_ids=True), "pieces"), key, capacity)
    parts = F.array_sort(F.collect_list(F.struct("offset", F.col(key), "piece", "length", "ids")))
    return placed.groupBy("sequence_id").agg(parts.alias("p")).select("sequence_id", F.flatten(F.transform("p", lambda x: x["ids"])).alias("ids"), F.transform("p", lambda x: x.dropFields("ids")).alias("pieces"))
