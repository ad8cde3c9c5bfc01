r"""Substring dedup by hashing units of text.

Units are lines, and the sentences inside them (a sentence ends at . ! or ? before a blank);
a unit's key is the unit stripped of blanks, A-Z lower-cased, as 128 bits of hash. Keys of
lines count from LINE code points, those of sentences from SENTENCE on. The earliest ranked
occurrence of a key stays: that in the document of smallest id, and there the first one. All
others are repeated. Repeated units with nothing but text too short to count between them are
a run; runs of at least RUN words are removed, so a common sentence by itself stays where it
is. What stays is described by its offsets in the original text.

The keys that more than one in HEAVY_SHARE of all bear are few and broadcast; the others meet
their group in a shuffle, after a filter of fixed size has left out keys that don't repeat.

Null or empty text: nothing to remove. Rows of one id are one document, so that exact
repetitions of a row keep what the document keeps. Rows whose id is null rank last and among
themselves as one document. Extra columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textscan as ts
from .keyfilter import key_filter, passes
from .line_dedup import HEAVY_LEAST, HEAVY_SHARE, Lines, small
from .storage import discard, saved

LINE, SENTENCE, RUN = 12, 12, 20
LAST = (1 << 63) - 1
STOPS = ts.byte_class(b".!?")
BLANKS = ts.byte_class(ts.SPACE)


def sentence_breaks(data: np.ndarray) -> np.ndarray:
    """Newlines, and blanks right after the end of a sentence."""
    cut = data == 10
    cut[1:] |= BLANKS[data[1:]] & STOPS[data[:-1]]
    return np.flatnonzero(cut)


class Units:
    """Counted units of a block, by row and place: rows, start, end (bytes of the stripped unit), h1, h2."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, line: int = LINE, sentence: int = SENTENCE):
        parts = []
        for lines in (Lines(data, offsets, line), Lines(data, offsets, sentence, sentence_breaks(data))):
            at = np.flatnonzero(lines.counted)
            rows = np.repeat(np.arange(len(offsets) - 1), lines.counts)[at]
            parts.append(np.stack([rows, lines.key_start[at], lines.key_end[at], lines.h1[at], lines.h2[at]]))
        every = np.concatenate(parts, axis=1)
        every = every[:, np.lexsort((every[2], every[1], every[0]))]
        new = np.ones(every.shape[1], bool)
        new[1:] = (np.diff(every[:3], axis=1) != 0).any(axis=0)
        self.rows, self.start, self.end, self.h1, self.h2 = every[:, new]


def unit_keys(docs: DataFrame, key: str, text: str, line: int, sentence: int) -> DataFrame:
    """(rank, h1, h2): each key of each document once; rank: the id, null last."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = ts.buffers(batch.column(1))
            for a, b in ts.row_blocks(offsets):
                u = Units(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], line, sentence)
                order = np.lexsort((u.h2, u.h1, u.rows))
                rows, h1, h2 = u.rows[order], u.h1[order], u.h2[order]
                new = np.ones(len(rows), bool)
                new[1:] = (rows[1:] != rows[:-1]) | (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(a + rows[new])), pa.array(h1[new]), pa.array(h2[new])], names=["rank", "h1", "h2"])

    return docs.select(F.coalesce(F.col(key), F.lit(LAST)).alias("rank"), text).mapInArrow(scan, "rank long, h1 long, h2 long")


def later_occurrences(docs: DataFrame, key: str, text: str, line: int, sentence: int) -> DataFrame:
    """rank and gone: the keys that an earlier document holds."""
    keys = saved(unit_keys(docs, key, text, line, sentence), "unit-keys")
    groups = keys.groupBy("h1", "h2").agg(F.count("*").alias("holders"), F.min("rank").alias("first"), F.max("rank").alias("last"))
    repeated = saved(groups.filter("first < last").drop("last"), "repeated-units")
    total = repeated.agg(F.coalesce(F.sum("holders"), F.lit(0)).alias("n")).first()["n"]
    heavy = F.col("holders") >= max(HEAVY_LEAST, total // HEAVY_SHARE)
    wanted = key_filter(repeated.filter(~heavy), "h1")

    def sift(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(passes(wanted.value, batch.column(1).to_numpy())))

    few = keys.join(F.broadcast(repeated.filter(heavy)), ["h1", "h2"])
    rest = keys.mapInArrow(sift, keys.schema).join(repeated.filter(~heavy), ["h1", "h2"])
    lost = few.unionByName(rest).filter("rank > first")
    gone = saved(lost.groupBy("rank").agg(F.collect_set(F.struct("h1", "h2")).alias("gone")), "later-units")
    discard(keys, repeated)
    return gone


def removed_spans(raw: bytes, gone: list, line: int, sentence: int, run: int = RUN) -> tuple[int, list[tuple[int, int]]]:
    """Number of units and byte spans that go: runs of units of gone keys and of repetitions inside the text."""
    units = Units(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]), line, sentence)
    lost, seen, spans = {(g["h1"], g["h2"]) for g in gone}, set(), []
    short = lambda gap: len(gap.strip(ts.SPACE).decode()) < sentence
    for s, e, a, b in zip(units.start.tolist(), units.end.tolist(), units.h1.tolist(), units.h2.tolist(), strict=True):
        if (a, b) in lost or (a, b) in seen:
            if spans and (s <= spans[-1][1] or run and short(raw[spans[-1][1] : s])):
                spans[-1] = (spans[-1][0], max(e, spans[-1][1]))
            else:
                spans.append((s, e))
        seen.add((a, b))
    return len(units.start), [(s, e) for s, e in spans if len(raw[s:e].split()) >= run]


def substring_dedup(docs: DataFrame, key: str = "doc_id", text: str = "text", line: int = LINE, sentence: int = SENTENCE, run: int = RUN, with_text: bool = False) -> DataFrame:
    """key, n_units, removed and kept (start:end in code points of the original), n_removed_chars, kept_sha256 (and kept_text)."""
    lost = later_occurrences(docs, key, text, line, sentence)
    ranked = docs.select(F.col(key).alias("k"), text, F.coalesce(F.col(key), F.lit(LAST)).alias("rank"))
    marked = key_filter(lost.select(F.xxhash64("rank").alias("h")), "h")
    hashed = ranked.withColumn("h", F.xxhash64("rank"))
    plain = ranked.schema

    def sift(wanted: bool) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                keep = batch.filter(pa.array(passes(marked.value, batch.column(3).to_numpy()) == wanted))
                yield pa.RecordBatch.from_arrays(keep.columns[:3], names=plain.names)

        return hashed.mapInArrow(run, plain)

    gone_type = lost.schema["gone"].dataType
    clean = sift(False).select("k", text, F.lit(None).cast(gone_type).alias("gone"))
    others = sift(True).join(lost, "rank", "left").select("k", text, "gone")
    fields = [T.StructField(key, docs.schema[key].dataType), T.StructField("n_units", T.LongType()), T.StructField("removed", T.StringType()), T.StructField("kept", T.StringType()), T.StructField("n_removed_chars", T.LongType()), T.StructField("kept_sha256", T.StringType())]
    schema = T.StructType(fields + [T.StructField("kept_text", T.StringType())] * with_text)
    kinds = [pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string()][: len(schema) - 1]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shown = lambda spans: ",".join(f"{s}:{e}" for s, e in spans)
        for batch in small(batches):
            rows = []
            for value, gone in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                raw = (value or "").encode()
                n, spans = removed_spans(raw, gone or [], line, sentence, run)
                edges = [0, *(x for s in spans for x in s), len(raw)]
                stay = [(s, e) for s, e in zip(edges[::2], edges[1::2], strict=True) if s < e]
                kept = b"".join(raw[s:e] for s, e in stay)
                if len(raw) == len(value or ""):
                    points = list
                else:
                    place = np.concatenate([[0], np.cumsum((np.frombuffer(raw, np.uint8) & 0xC0) != 0x80)])
                    points = lambda spans, place=place: [(int(place[s]), int(place[e])) for s, e in spans]
                went = points(spans)
                row = (n, shown(went), shown(points(stay)), sum(e - s for s, e in went), hashlib.sha256(kept).hexdigest())
                rows.append((*row, kept.decode()) if with_text else row)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds))], names=schema.names)

    return clean.unionByName(others).mapInArrow(cut, schema)
