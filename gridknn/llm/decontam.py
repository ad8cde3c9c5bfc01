"""Benchmark decontamination with a broadcast hash set of normalised test n-grams.

Words are runs of digits, ASCII letters (lower-cased) and everything beyond ASCII. Each
benchmark item gives its windows of `window` consecutive words; an item with fewer words is
one window. Documents are scanned once: rolling hashes of their word windows are looked up,
every hit is verified on the words themselves, and the words inside verified windows are hit.

The windows' size in memory is checked before they are broadcast. Beyond `max_bytes` only a
filter of fixed size is, and what it lets pass is verified by a join with the stored windows.

Null or empty text: no words, nothing hit. An empty benchmark, or null items: nothing hit.
Repeated documents are judged one by one; repeated or clashing extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textscan as ts
from .keyfilter import key_filter, passes
from .storage import saved

WINDOW = 13
#: A document is contaminated when at least one word in SHARE is hit.
SHARE = 20
#: What the windows may take in each Python process if they are broadcast, and what one takes besides its words.
MAX_BROADCAST_BYTES, WINDOW_BYTES = 128 << 20, 160
TABLE_BITS = 22


def window_table(benchmark: DataFrame, item_key: str, text: str, window: int = WINDOW) -> DataFrame:
    """(n, h, item, words): every window of every item: its number of words, its hash and its words."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names = batch.column(0).to_pylist()
            data, offsets = ts.buffers(batch.column(1))
            for a, b in ts.row_blocks(offsets):
                words = ts.Words(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], ts.ALNUM_WORD)
                hashes = words.hashes()
                for n in {min(window, int(c)) for c in words.counts} - {0}:
                    whole = ts.hash_windows(hashes, n)
                    rows = [(j, i) for i, (at, count) in enumerate(zip(words.first[:-1], words.counts, strict=True)) if count == n or count > n == window for j in range(at, at + count - n + 1)]
                    for k in range(0, len(rows), 4096):
                        part = rows[k : k + 4096]
                        found = [pa.array([n] * len(part)), pa.array([int(whole[j]) for j, _ in part], pa.uint64()).view(pa.int64()), pa.array([names[a + i] for _, i in part], pa.string()), pa.array([words.text(j, j + n) for j, _ in part], pa.binary())]
                        yield pa.RecordBatch.from_arrays(found, names=["n", "h", "item", "words"])

    items = benchmark.select(F.coalesce(F.col(item_key).cast("string"), F.lit("None")).alias("k"), F.col(text).alias("t"))
    return items.mapInArrow(cut, "n long, h long, item string, words binary")


class WindowIndex:
    """Hash set of benchmark windows: for each window length sorted hashes with their items and words."""

    def __init__(self, windows: pa.Table):
        length, hashes = windows.column("n").to_numpy(), windows.column("h").to_numpy().view(np.uint64)
        items, texts = windows.column("item").to_pylist(), windows.column("words").to_pylist()
        self.by_length = {}
        for n in np.unique(length).tolist():
            at = np.flatnonzero(length == n)
            at = at[np.argsort(hashes[at], kind="stable")]
            table = np.zeros(1 << TABLE_BITS, bool)
            table[(hashes[at] >> np.uint64(64 - TABLE_BITS)).astype(np.int64)] = True
            self.by_length[n] = (hashes[at], [items[k] for k in at], [texts[k] for k in at], table)

    def hits(self, words: ts.Words) -> Iterator[tuple[int, int, int, str]]:
        """(row, first word, number of words, item) of each verified window in a block."""
        hashes = words.hashes()
        for n, (keys, items, texts, table) in self.by_length.items():
            at = ts.hash_windows(hashes, n)
            near = np.flatnonzero(table[(at >> np.uint64(64 - TABLE_BITS)).astype(np.int64)])
            low = np.searchsorted(keys, at[near], "left")
            high = np.searchsorted(keys, at[near], "right")
            rows = np.searchsorted(words.first, near, "right") - 1
            for j, a, b, row in zip(near[low < high], low[low < high], high[low < high], rows[low < high], strict=True):
                if j + n > words.first[row + 1]:
                    continue
                text = words.text(j, j + n)
                for k in range(a, b):
                    if texts[k] == text:
                        yield int(row), int(j), n, items[k]


class WindowFilter:
    """The same windows as a filter of fixed size over their hashes: what it lets pass is still to be verified."""

    def __init__(self, lengths: list[int], marks: np.ndarray):
        self.lengths, self.marks = lengths, marks

    def hits(self, words: ts.Words) -> Iterator[tuple[int, int, int, int]]:
        """(row, first word, number of words, hash) of each window in a block that may be one."""
        hashes = words.hashes()
        for n in self.lengths:
            at = ts.hash_windows(hashes, n)
            near = np.flatnonzero(passes(self.marks, at))
            rows = np.searchsorted(words.first, near, "right") - 1
            inside = near + n <= words.first[rows + 1]
            for j, row in zip(near[inside].tolist(), rows[inside].tolist(), strict=True):
                yield row, j, n, int(at[j].view(np.int64))


_LONGS = T.ArrayType(T.LongType())
#: Hit word ranges (first, last exclusive), their byte ranges and the items they come from.
SPANS = T.StructType([T.StructField("n_words", T.LongType()), *(T.StructField(c, _LONGS) for c in ("hit_first", "hit_last", "char_from", "char_to")), T.StructField("items", T.ArrayType(T.StringType()))])
#: A window that the filter let pass: its first word, words, byte range and hash.
WINDOWS = "array<struct<at:long,n:long,s:long,e:long,h:long,words:binary>>"


def _merge(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def _spans(found: list[tuple[int, int, int, int, str]]) -> tuple[list[int], list[int], list[int], list[int], list[str]]:
    """Columns of SPANS from windows (first word, last word, first byte, last byte, item)."""
    words = _merge([w[:2] for w in found])
    starts = {w[0]: w[2] for w in found}
    ends = {w[1]: w[3] for w in found}
    chars = [(starts[a], ends[b]) for a, b in words]
    return [a for a, _ in words], [b for _, b in words], [a for a, _ in chars], [b for _, b in chars], sorted({w[4] for w in found})


def scan_batch(texts: pa.Array, index: WindowIndex) -> pa.StructArray:
    """SPANS of each row."""
    data, offsets = ts.buffers(texts)
    n_words, cols = [], [[], [], [], [], []]
    for a, b in ts.row_blocks(offsets):
        words = ts.Words(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], ts.ALNUM_WORD)
        n_words.append(words.counts)
        found: dict[int, list[tuple[int, int, int, int, str]]] = {}
        for row, j, n, item in index.hits(words):
            first, base = words.first[row], offsets[a + row] - offsets[a]
            found.setdefault(row, []).append((int(j - first), int(j + n - first), int(words.start[j] - base), int(words.end[j + n - 1] - base), item))
        for row in range(b - a):
            for c, v in zip(cols, _spans(found[row]) if row in found else [[]] * 5, strict=True):
                c.append(v)
    counts = np.concatenate(n_words) if n_words else np.zeros(0, np.int64)
    longs = pa.list_(pa.int64())
    arrays = [pa.array(counts, pa.int64()), *(pa.array(c, longs) for c in cols[:4]), pa.array(cols[4], pa.list_(pa.string()))]
    return pa.StructArray.from_arrays(arrays, names=SPANS.names)


def _free(name: str, taken: list[str]) -> str:
    while name in taken:
        name = "_" + name
    return name


def with_spans(docs: DataFrame, benchmark: DataFrame, text: str, item_key: str = "item_id", item_text: str = "text", window: int = WINDOW, max_bytes: int = MAX_BROADCAST_BYTES) -> tuple[DataFrame, str]:
    """docs with a column of SPANS, and its name (one that docs doesn't have).

    Windows that need less than max_bytes in a Python process are broadcast, and docs are
    scanned once. Otherwise the scan only marks what a filter of fixed size lets pass, and a
    join with the stored windows verifies it, by a number given to each row.
    """
    windows = saved(window_table(benchmark, item_key, item_text, window), "benchmark-windows")
    size = windows.agg(F.coalesce(F.sum(F.octet_length("words") + F.octet_length("item") + WINDOW_BYTES), F.lit(0)).alias("n")).first()["n"]
    name = _free("__spans", docs.columns)
    if size > max_bytes:
        return _joined(docs, windows, text, name), name
    index = docs.sparkSession.sparkContext.broadcast(WindowIndex(windows.toArrow()))
    column = docs.columns.index(text)
    schema = T.StructType(docs.schema.fields + [T.StructField(name, SPANS)])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, scan_batch(batch.column(column), index.value)], names=schema.names)

    return docs.mapInArrow(scan, schema), name


def _joined(docs: DataFrame, windows: DataFrame, text: str, name: str) -> DataFrame:
    row, at = _free("__row", docs.columns), docs.columns.index(text)
    lengths = [r["n"] for r in windows.select("n").distinct().collect()]  # at most `window` numbers
    marks = docs.sparkSession.sparkContext.broadcast(WindowFilter(lengths, key_filter(windows, "h").value))
    found, words = _free("__found", docs.columns), _free("__words", docs.columns)
    numbered = docs.withColumn(row, F.monotonically_increasing_id())
    marked = T.StructType(numbered.schema.fields + [T.StructField(words, T.LongType()), T.StructField(found, T._parse_datatype_string(WINDOWS))])
    kinds = pa.list_(pa.struct([*((c, pa.int64()) for c in ("at", "n", "s", "e", "h")), ("words", pa.binary())]))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = ts.buffers(batch.column(at))
            counts, rows = [np.zeros(0, np.int64)], []
            for a, b in ts.row_blocks(offsets):
                w = ts.Words(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], ts.ALNUM_WORD)
                counts.append(w.counts)
                mine: list[list[dict]] = [[] for _ in range(b - a)]
                for i, j, n, h in marks.value.hits(w):
                    base = offsets[a + i] - offsets[a]
                    mine[i].append({"at": int(j - w.first[i]), "n": n, "s": int(w.start[j] - base), "e": int(w.end[j + n - 1] - base), "h": h, "words": w.text(j, j + n)})
                rows += mine
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.concatenate(counts)), pa.array(rows, kinds)], names=marked.names)

    kept = saved(numbered.mapInArrow(scan, marked), "marked-documents")
    candidates = kept.select(F.col(row).alias("row"), F.explode(found).alias("x")).select("row", "x.*")
    hit = candidates.join(windows, ["n", "h", "words"]).select("row", F.struct(F.col("at").alias("a"), (F.col("at") + F.col("n")).alias("b"), "s", "e", "item").alias("w"))
    grouped = hit.groupBy("row").agg(F.collect_set("w").alias("w"))
    schema = T.StructType([T.StructField("row", T.LongType()), T.StructField("s", T.StructType(SPANS.fields[1:]))])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spans = [_spans([(x["a"], x["b"], x["s"], x["e"], x["item"]) for x in w]) for w in batch.column(1).to_pylist()]
            kinds = [pa.list_(pa.int64())] * 4 + [pa.list_(pa.string())]
            merged = pa.StructArray.from_arrays([pa.array([s[i] for s in spans], k) for i, k in enumerate(kinds)], names=SPANS.names[1:])
            yield pa.RecordBatch.from_arrays([batch.column(0), merged], names=schema.names)

    merged = grouped.mapInArrow(merge, schema).select(F.col("row").alias(row), F.col("s").alias(found + "_s"))
    both = kept.join(merged, row, "left")
    parts = [F.coalesce(F.col(f"{found}_s.{f.name}"), F.array().cast(f.dataType)).alias(f.name) for f in SPANS.fields[1:]]
    return both.select(*docs.columns, F.struct(F.col(words).alias("n_words"), *parts).alias(name))


def _hit(spans: str) -> Column:
    return F.aggregate(F.zip_with(F.col(f"{spans}.hit_last"), F.col(f"{spans}.hit_first"), lambda b, a: b - a), F.lit(0).cast("long"), lambda s, x: s + x)


def _contaminated(spans: str, share: int) -> Column:
    return (_hit(spans) > 0) & (_hit(spans) * share >= F.col(f"{spans}.n_words"))


def decontaminate(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", window: int = WINDOW, share: int = SHARE, max_bytes: int = MAX_BROADCAST_BYTES) -> DataFrame:
    """One row per document: key, n_words, n_hit, n_items, items_sha256, contaminated, items."""
    found, spans = with_spans(docs.select(key, text), benchmark, text, item_key, item_text, window, max_bytes)
    items = F.col(f"{spans}.items")
    return found.select(key, F.col(f"{spans}.n_words").alias("n_words"), _hit(spans).alias("n_hit"), F.size(items).cast("long").alias("n_items"), F.sha2(F.concat_ws(",", items), 256).alias("items_sha256"), _contaminated(spans, share).alias("contaminated"), items.alias("items"))


def remove_spans(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", window: int = WINDOW, max_bytes: int = MAX_BROADCAST_BYTES) -> DataFrame:
    """key and text without the bytes from the first to the last word of each hit range."""
    schema = docs.select(key, text).schema

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for value, starts, ends in zip(*(batch.column(i).to_pylist() for i in (1, 2, 3)), strict=True):
                if starts:
                    raw, at, kept = value.encode(), 0, []
                    for a, b in zip(starts, ends, strict=True):
                        kept.append(raw[at:a])
                        at = b
                    value = b"".join([*kept, raw[at:]]).decode()
                out.append(value)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, batch.column(1).type)], names=schema.names)

    found, spans = with_spans(docs.select(key, text), benchmark, text, item_key, item_text, window, max_bytes)
    return found.select(key, text, f"{spans}.char_from", f"{spans}.char_to").mapInArrow(cut, schema)


def drop_contaminated_documents(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", window: int = WINDOW, share: int = SHARE, max_bytes: int = MAX_BROADCAST_BYTES) -> DataFrame:
    """docs without the contaminated ones, all columns kept; each row is judged by itself."""
    found, spans = with_spans(docs, benchmark, text, item_key, item_text, window, max_bytes)
    return found.filter(~F.coalesce(_contaminated(spans, share), F.lit(False))).drop(spans)
