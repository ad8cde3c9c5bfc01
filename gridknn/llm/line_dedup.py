"""Line dedup over levelled sorted runs of line hashes.

A line's key is the line stripped of blanks at both ends, A-Z lower-cased. Keys are 128-bit
hashes. Documents come in batches; a batch's keys are counted (documents that hold them, and
the largest of their ids) and merge-anti-joined with the runs: keys that no run holds become
a run of their own, the others raise the counts of keys seen before. When a level has
`fanout` runs they are merged into one run of the next level, so a key is rewritten only a
logarithmic number of times. Runs and batches are sorted and bucketed by key, so that these
joins move no run.

Keys of at least `least` code points that `copies` or more documents hold lose all their
lines except in the document with the largest id. Keys that more than one in HEAVY_SHARE of
all lines bear are few by that very bound and are broadcast; rows of the others meet their
key in a shuffle, after a filter of fixed size has left out the lines that don't repeat.

Null or empty text: one empty line. Repeated rows count as documents of their own and are
treated alike. Rows whose id is null count as documents but lose no line. All columns pass
through dedup_lines; line_dedup_report reads the id and the text only.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textscan as ts
from .keyfilter import key_filter, passes
from .storage import bucketed, discard, saved

LEAST, COPIES, FANOUT, BATCHES = 20, 3, 4, 4
HEAVY_SHARE, HEAVY_LEAST = 100_000, 1_000
_second = ts.Powers(np.uint64(0xA0761D6478BD642F))


class Lines:
    """Lines of a block of rows: byte places, keys' byte places and hashes, and which keys count.

    breaks: the places of the bytes between lines, if they aren't the newlines.
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray, least: int = LEAST, breaks: np.ndarray | None = None):
        breaks = np.flatnonzero(data == 10) if breaks is None else breaks
        owner = np.searchsorted(offsets, breaks, "right") - 1
        self.counts = np.bincount(owner, minlength=len(offsets) - 1) + 1
        self.first = np.concatenate([[0], np.cumsum(self.counts)])
        self.start, self.end = np.empty(self.first[-1], np.int64), np.empty(self.first[-1], np.int64)
        inner = np.ones(self.first[-1], bool)
        inner[self.first[:-1]] = False
        self.start[self.first[:-1]] = offsets[:-1]
        self.start[inner] = breaks + 1
        self.end[self.first[1:] - 1] = offsets[1:]
        self.end[:-1][inner[1:]] = breaks
        ink = np.flatnonzero(ts.SPACED_WORD[data])
        if len(ink):
            a, b = np.searchsorted(ink, self.start), np.searchsorted(ink, self.end)
            some = a < b
            self.key_start = np.where(some, ink[np.minimum(a, len(ink) - 1)], self.start)
            self.key_end = np.where(some, ink[np.maximum(b, 1) - 1] + 1, self.start)
        else:
            self.key_start = self.key_end = self.start
        points = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
        self.counted = points[self.key_end] - points[self.key_start] >= least
        low = ts.LOWER[data]
        self.h1 = ts.hash_spans(low, self.key_start, self.key_end).view(np.int64)
        self.h2 = ts.hash_spans(low, self.key_start, self.key_end, _second).view(np.int64)


def line_keys(docs: DataFrame, key: str = "doc_id", text: str = "text", least: int = LEAST) -> DataFrame:
    """key, h1, h2: each counted key of each document once."""
    schema = T.StructType([T.StructField(key, docs.schema[key].dataType), T.StructField("h1", T.LongType()), T.StructField("h2", T.LongType())])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = ts.buffers(batch.column(1))
            for a, b in ts.row_blocks(offsets):
                lines = Lines(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], least)
                at = np.flatnonzero(lines.counted)
                rows = np.repeat(np.arange(a, b), lines.counts)[at]
                h1, h2 = lines.h1[at], lines.h2[at]
                order = np.lexsort((h2, h1, rows))
                rows, h1, h2 = rows[order], h1[order], h2[order]
                new = np.ones(len(rows), bool)
                new[1:] = (rows[1:] != rows[:-1]) | (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows[new])), pa.array(h1[new]), pa.array(h2[new])], names=schema.names)

    return docs.select(key, text).mapInArrow(scan, schema)


class LineRuns:
    """Levels of runs (h1, h2, holders, largest), sorted and dealt alike, so that they join without a shuffle.

    Every key has a row in one run only: that of the batch which brought it first. What later
    batches add to its holders, and larger ids, lie beside the runs as raises.
    """

    def __init__(self, spark: SparkSession, fanout: int = FANOUT):
        self.spark, self.fanout = spark, fanout
        self.buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.levels: list[list[DataFrame]] = [[]]
        self.raises: list[DataFrame] = []
        self.names: dict[int, str] = {}

    def _write(self, rows: DataFrame, name: str) -> DataFrame:
        """A table bucketed and sorted by key, in the shared folder."""
        name = f"{name}_{uuid.uuid4().hex}"
        out = bucketed(rows.repartition(self.buckets, "h1", "h2"), name, self.buckets, ["h1", "h2"])
        self.names[id(out)] = name
        return out

    def add(self, keys: DataFrame, key: str = "doc_id") -> None:
        """Takes in a batch's (key, h1, h2) rows: unseen keys become a run, the others raises; full levels are compacted."""
        counted = keys.groupBy("h1", "h2").agg(F.count("*").alias("holders"), F.max(key).alias("largest"))
        if not self.runs():
            self.levels[0].append(self._write(counted, "line_run"))
            return
        batch = self._write(counted, "line_batch")
        fresh = self._write(self.unseen(batch), "line_run")
        self.raises.append(saved(batch.join(fresh, ["h1", "h2"], "left_anti"), "line-raises"))
        self._drop(batch)
        self.levels[0].append(fresh)
        level = 0
        while len(self.levels[level]) >= self.fanout:
            full, self.levels[level] = self.levels[level], []
            merged = self._write(_union(full), "line_run")
            self._drop(*full)
            level += 1
            if level == len(self.levels):
                self.levels.append([])
            self.levels[level].append(merged)

    def runs(self) -> list[DataFrame]:
        return [r for level in self.levels for r in level]

    def unseen(self, keys: DataFrame) -> DataFrame:
        """The rows whose key no run holds: merge-anti-joined run by run."""
        for run in self.runs():
            keys = keys.join(run, ["h1", "h2"], "left_anti")
        return keys

    def at_least(self, copies: int) -> DataFrame:
        """The keys with so many holders, summed up; a key that was never raised has them all in its run."""
        runs = _union(self.runs())
        if not self.raises:
            return runs.filter(F.col("holders") >= copies)
        raised = _union(self.raises).groupBy("h1", "h2").agg(F.sum("holders").alias("more"), F.max("largest").alias("later"))
        both = runs.join(raised, ["h1", "h2"], "left")
        whole = both.select("h1", "h2", (F.col("holders") + F.coalesce("more", F.lit(0))).alias("holders"), F.greatest("largest", "later").alias("largest"))
        return whole.filter(F.col("holders") >= copies)

    def _drop(self, *runs: DataFrame) -> None:
        for r in runs:
            self.spark.sql(f"DROP TABLE IF EXISTS {self.names.pop(id(r))}")
            discard(r)

    def close(self) -> None:
        """Removes all runs and raises."""
        self._drop(*self.runs())
        discard(*self.raises)
        self.levels, self.raises = [[]], []


def _union(runs: list[DataFrame]) -> DataFrame:
    every = runs[0]
    for r in runs[1:]:
        every = every.unionByName(r)
    return every


def dropped_keys(docs: DataFrame, key: str = "doc_id", text: str = "text", least: int = LEAST, copies: int = COPIES, batches: int = BATCHES, fanout: int = FANOUT) -> DataFrame:
    """key and gone: the hashes of the keys whose lines this document loses; documents that lose none are left out."""
    part = F.pmod(F.xxhash64(key), F.lit(batches)).cast("int")
    keys = saved(line_keys(docs, key, text, least).withColumn("batch", part), "line-keys", "batch")
    store = LineRuns(docs.sparkSession, fanout)
    for b in range(batches):
        store.add(keys.filter(F.col("batch") == b), key)
    every, keys = keys, keys.drop("batch")
    repeated = saved(store.at_least(copies), "repeated-lines")
    store.close()
    total = repeated.agg(F.coalesce(F.sum("holders"), F.lit(0)).alias("n")).first()["n"]
    heavy = F.col("holders") >= max(HEAVY_LEAST, total // HEAVY_SHARE)
    wanted = key_filter(repeated.filter(~heavy), "h1")
    schema = keys.schema

    def sift(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(passes(wanted.value, batch.column(1).to_numpy())))

    lose = F.col(key) < F.col("largest")
    few = keys.join(F.broadcast(repeated.filter(heavy)), ["h1", "h2"]).filter(lose).select(key, "h1", "h2")
    rest = keys.mapInArrow(sift, schema).join(repeated.filter(~heavy), ["h1", "h2"]).filter(lose).select(key, "h1", "h2")
    lost = saved(few.unionByName(rest).groupBy(key).agg(F.collect_set(F.struct("h1", "h2")).alias("gone")), "line-losses")
    discard(every, repeated)
    return lost


def small(batches: Iterator[pa.RecordBatch], rows: int = 256) -> Iterator[pa.RecordBatch]:
    """The batches in slices, so that few rows at a time are Python objects."""
    for batch in batches:
        for i in range(0, batch.num_rows, rows):
            yield batch.slice(i, rows)


def _kept(text: str, gone: list[dict], least: int) -> tuple[str, int, int]:
    """The text without the lost lines, its number of lines, and how many went."""
    raw = text.encode()
    data = np.frombuffer(raw, np.uint8)
    lines = Lines(data, np.array([0, len(raw)]), least)
    lost = {(g["h1"], g["h2"]) for g in gone}
    stay = [not c or (a, b) not in lost for c, a, b in zip(lines.counted.tolist(), lines.h1.tolist(), lines.h2.tolist(), strict=True)]
    kept = b"\n".join(raw[s:e] for s, e, ok in zip(lines.start.tolist(), lines.end.tolist(), stay, strict=True) if ok)
    return kept.decode(), len(stay), len(stay) - sum(stay)


def _with_losses(docs: DataFrame, key: str, text: str, least: int, **options) -> tuple[DataFrame, DataFrame]:
    """docs that surely lose nothing, and the others with their array gone (null where nothing is lost)."""
    losses = dropped_keys(docs, key, text, least, **options)
    marked = key_filter(losses.select(F.xxhash64(key).alias("k")), "k")
    hashed, names = docs.withColumn("__key_hash", F.xxhash64(key)), docs.columns

    def sift(wanted: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                may = passes(marked.value, batch.column(batch.num_columns - 1).to_numpy())
                keep = batch.filter(pa.array(may == wanted))
                yield pa.RecordBatch.from_arrays(keep.columns[:-1], names=names)

        return hashed.mapInArrow(run, docs.schema)

    return sift(False), sift(True).join(losses.select(F.col(key).alias("__key"), F.col("gone").alias("__gone")), F.col(key) == F.col("__key"), "left").drop("__key")


def line_dedup_report(docs: DataFrame, key: str = "doc_id", text: str = "text", least: int = LEAST, **options) -> DataFrame:
    """key, n_lines, n_dropped, kept_sha256 of every document."""
    docs = docs.select(key, text)
    untouched, others = _with_losses(docs, key, text, least, **options)
    value = F.coalesce(F.col(text), F.lit(""))
    whole = untouched.select(key, (F.length(value) - F.length(F.replace(value, F.lit("\n"), F.lit(""))) + 1).cast("long").alias("n_lines"), F.lit(0).cast("long").alias("n_dropped"), F.sha2(value, 256).alias("kept_sha256"))

    names = whole.columns

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches):
            rows = [_kept(t or "", g or [], least) for t, g in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)]
            out = [pa.array([n for _, n, _ in rows], pa.int64()), pa.array([d for _, _, d in rows], pa.int64()), pa.array([hashlib.sha256(k.encode()).hexdigest() for k, _, _ in rows], pa.string())]
            yield pa.RecordBatch.from_arrays([batch.column(0), *out], names=names)

    return whole.unionByName(others.mapInArrow(cut, whole.schema))


def dedup_lines(docs: DataFrame, key: str = "doc_id", text: str = "text", least: int = LEAST, length: str = "n_chars", **options) -> DataFrame:
    """docs with their remaining lines joined by newlines; where a text changes, the column length (if there is one) follows."""
    untouched, others = _with_losses(docs, key, text, least, **options)
    names, at, gone = docs.columns, docs.columns.index(text), len(docs.columns)
    counted = docs.columns.index(length) if length in docs.columns else None

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches):
            columns = batch.columns[:gone]
            texts = [_kept(t or "", g, least)[0] if g else t for t, g in zip(batch.column(at).to_pylist(), batch.column(gone).to_pylist(), strict=True)]
            columns[at] = pa.array(texts, columns[at].type)
            if counted is not None:
                sizes = [len(t) if g else n for t, g, n in zip(texts, batch.column(gone).to_pylist(), columns[counted].to_pylist(), strict=True)]
                columns[counted] = pa.array(sizes, columns[counted].type)
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return untouched.unionByName(others.mapInArrow(cut, docs.schema))
