"""Pairs and triples of words, counted and joined in packed arrays.

A row of a packed table holds arrays: n values each of some columns of 8 bytes, for one bucket of
hashed keys. What one bucket needs meets in one task, which sorts its arrays; Spark only carries
them. There are as many buckets as the tables need, so a bucket's rows have a bound.

An n-gram is a left part, which is its context, and a right part, which is what it ends with and
what its context fails to: for a pair two words, for a triple two pairs. Parts that occur often
(few by a bound) are broadcast; their n-grams are dealt by their own key, so that no part's n-grams
meet in one task but those of parts that are rare, which have a bound as well.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.broadcast import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textscan as ts
from .keyfilter import passes
from .storage import discard, saved, shuffles_removed

DISCOUNT, LEAST = 0.5, 2
#: Tokens whose n-grams are counted together before they are handed on (fewer than 2**21, so that their numbers fit).
TOGETHER = 1_000_000
#: Rows that one bucket gets.
BUCKET_ROWS = 750_000
#: Values of a packed row, and rows of a batch, at most: large ones stay in memory for long.
ROW_VALUES, BATCH_ROWS = 8192, 32
#: Values of packed rows that are dealt together.
DEALT_VALUES = 250_000
#: Bytes of a packed table's row groups, and rows between two looks at their size.
ROW_GROUP, LOOK = 8 << 20, 8
#: Values of a slice of a long array that tasks add up.
SLICE = 1 << 16
END = np.uint64(0xE5D0C0DE00000001)
START = np.uint64(0xE5D0C0DE00000002)
#: Bits of a word's number in the vocabulary, and of its number among the tokens counted together.
BITS, NEAR = 20, 21
#: Bits of the filter of pairs.
PAIR_BITS = 26
PACKED = "bucket int, kind int, n int, d binary"
#: Kinds of packed rows, in the order in which a bucket's rows come: keys and values of parts,
#: n-grams as numbers of words, n-grams as two keys; and contexts with their failure weights.
FACTS, CODES, ROWS, WEIGHTS = 0, 1, 2, 3


def token_blocks(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Blocks of rows: first, last, token hashes with an end after each row, and each row's first token."""
    data, offsets = ts.buffers(column)
    for a, b in ts.row_blocks(offsets):
        words = ts.Words(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], ts.SPACED_WORD)
        yield a, b, np.insert(words.hashes(), words.first[1:], END), words.first + np.arange(b - a + 1)


def mixed(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    x = a * np.uint64(0x9E3779B97F4A7C15) + b
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(29))


def buckets_of(keys: np.ndarray, count: int) -> np.ndarray:
    """Buckets of well mixed keys (uint64)."""
    return ((keys >> np.uint64(32)) * np.uint64(count) >> np.uint64(32)).astype(np.uint16 if count <= 1 << 16 else np.int32)


def slices(bucket: np.ndarray) -> tuple[np.ndarray, list[tuple[int, int, int]]]:
    """An order of the members by bucket (their own order within it), and each bucket's range in it."""
    order = np.argsort(bucket, kind="stable")
    found = bucket[order]
    cuts = np.concatenate([[0], np.flatnonzero(found[1:] != found[:-1]) + 1, [len(found)]]).tolist()
    return order, [(int(found[i]), i, j) for i, j in zip(cuts, cuts[1:], strict=False) if i < j]


def place(keys: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Where the wanted keys stand among the sorted ones, or -1."""
    if not len(keys):
        return np.full(len(wanted), -1, np.int64)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return np.where(keys[at] == wanted, at, -1)


def bucket_count(df: DataFrame, rows: int) -> int:
    return max(2 * df.sparkSession.sparkContext.defaultParallelism, -(-rows // BUCKET_ROWS))


def _batches(rows: list[tuple[int, int, int, bytes]]) -> Iterator[pa.RecordBatch]:
    for i in range(0, len(rows), BATCH_ROWS):
        bucket, kind, n, d = zip(*rows[i : i + BATCH_ROWS], strict=True)
        yield pa.RecordBatch.from_arrays([pa.array(bucket, pa.int32()), pa.array(kind, pa.int32()), pa.array(n, pa.int32()), pa.array(d, pa.binary())], names=["bucket", "kind", "n", "d"])


def _rows(bucket: int, kind: int, columns: tuple[np.ndarray, ...], first: int = 0, last: int | None = None) -> list[tuple[int, int, int, bytes]]:
    """Packed rows of the columns' values from first to last."""
    last = len(columns[0]) if last is None else last
    cuts = [*range(first, last, ROW_VALUES), last]
    return [(bucket, kind, j - i, b"".join(c[i:j].tobytes() for c in columns)) for i, j in zip(cuts, cuts[1:], strict=False)]


def _dealt(bucket: np.ndarray, kind: int, *columns: np.ndarray) -> list[tuple[int, int, int, bytes]]:
    order, found = slices(bucket)
    columns = tuple(c[order] for c in columns)
    return [row for b, i, j in found for row in _rows(b, kind, columns, i, j)]


def unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, np.ndarray]]:
    """Bucket, kind and columns (uint64, a row each) of packed rows."""
    for batch in batches:
        for i in range(batch.num_rows):
            n = batch.column(2)[i].as_py()
            yield batch.column(0)[i].as_py(), batch.column(1)[i].as_py(), np.frombuffer(batch.column(3)[i].as_buffer(), np.uint64).reshape(-1, n)


def together(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray]]:
    """Kind and columns of packed rows of whatever bucket, many at a time."""
    held: dict[int, list[np.ndarray]] = {}
    sizes: dict[int, int] = {}
    for _, kind, columns in unpacked(batches):
        held.setdefault(kind, []).append(columns.copy())
        sizes[kind] = sizes.get(kind, 0) + columns.shape[1]
        if sizes[kind] >= DEALT_VALUES:
            yield kind, np.concatenate(held.pop(kind), axis=1)
            sizes[kind] = 0
            ts.release()
    for kind, columns in held.items():
        yield kind, np.concatenate(columns, axis=1)


def _buckets_met(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, dict[int, np.ndarray]]]:
    """Each bucket of rows sorted by it, and the columns of its kinds."""
    at, held = None, {}
    for bucket, kind, columns in unpacked(batches):
        if bucket != at:
            if held:
                yield at, {k: np.concatenate(held.pop(k), axis=1) for k in list(held)}
                ts.release()
            at, held = bucket, {}
        held.setdefault(kind, []).append(columns.copy())
    if held:
        yield at, {k: np.concatenate(held.pop(k), axis=1) for k in list(held)}


def _met(parts: DataFrame, buckets: int) -> DataFrame:
    return parts.repartition(buckets, "bucket").sortWithinPartitions("bucket", "kind")


def stored(packed: DataFrame, name: str) -> DataFrame:
    return saved(packed, name, options={"parquet.block.size": ROW_GROUP, "parquet.block.size.row.check.min": LOOK, "parquet.page.size.row.check.min": LOOK})


def rows_of(packed: DataFrame) -> int:
    return packed.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first()["n"]


@dataclass
class Often:
    """Parts that occur often: sorted keys, counts, probabilities; as contexts, their failure weights."""

    keys: np.ndarray
    counts: np.ndarray
    p: np.ndarray
    weights: np.ndarray = field(default_factory=lambda: np.zeros(0))


def _pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
    """Tokens of many rows, their places in their rows (2 at most), and how many tokens come before for context only."""

    def cut(held: list[tuple[np.ndarray, np.ndarray]]) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
        tokens, depth = (np.concatenate(x) for x in zip(*held, strict=True))
        for i in range(0, len(tokens), TOGETHER):
            before = min(i, 2)
            yield tokens[i - before : i + TOGETHER], depth[i - before : i + TOGETHER], before

    held, size = [], 0
    for batch in batches:
        for _, _, tokens, first in token_blocks(batch.column(0)):
            if size and size + len(tokens) > TOGETHER:
                yield from cut(held)
                held, size = [], 0
            depth = np.full(len(tokens), 2, np.int8)
            depth[first[:-1]] = 0
            second = first[:-1] + 1
            depth[second[second < first[1:]]] = 1
            held.append((tokens, depth))
            size += len(tokens)
    if size:
        yield from cut(held)


def _counted(tokens: np.ndarray, depth: np.ndarray, before: int, marked: np.ndarray | None) -> tuple[np.ndarray, list[np.ndarray], np.ndarray]:
    """Hashes of the distinct words and the start; the distinct pairs (with a filter of pairs: triples) as
    places among them, word by word; how often each occurs."""
    order = np.argsort(tokens)
    ordered = tokens[order]
    new = np.concatenate([[True], ordered[1:] != ordered[:-1]])
    hashes = np.append(ordered[new], START)
    last = np.empty(len(tokens), np.int64)
    last[order] = np.cumsum(new) - 1
    left = np.concatenate([last[:1], last[:-1]])
    left[depth == 0] = len(hashes) - 1
    code = left << NEAR | last
    if marked is None:
        code = code[before:]
    else:
        some = passes(marked, mixed(hashes[left], tokens))
        some[1:] &= some[:-1].copy()
        some &= depth > 0
        some[: max(before, 1)] = False
        at = np.flatnonzero(some)
        code = left[at - 1] << 2 * NEAR | code[at]
    code.sort()
    first = np.flatnonzero(np.concatenate([[True], code[1:] != code[:-1]])) if len(code) else np.zeros(0, np.int64)
    c = np.diff(np.append(first, len(code)))
    code, low = code[first], (1 << NEAR) - 1
    return hashes, [code >> s & low for s in ((NEAR, 0) if marked is None else (2 * NEAR, NEAR, 0))], c


def _keys(hashes: np.ndarray, words: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Left and right parts of n-grams."""
    if len(words) == 2:
        return hashes[words[0]], hashes[words[1]]
    a, b, c = (hashes[w] for w in words)
    return mixed(a, b), mixed(b, c)


def _scanned(train: DataFrame, text: str, words: Broadcast, often: Broadcast, marked: Broadcast | None, buckets: int) -> DataFrame:
    """N-grams (left, right, count) of rows that are counted together, dealt by their right part or, if that occurs often, their own key."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for tokens, depth, before in _pieces(batches):
            hashes, at, c = _counted(tokens, depth, before, None if marked is None else marked.value)
            if not len(c):
                continue
            number = place(words.value.keys, hashes)
            a, b = _keys(hashes, at)
            of_right = number[at[1]] if marked is None else place(often.value.keys, b)
            bucket = buckets_of(np.where(of_right >= 0, mixed(a, b), b), buckets)
            numbers = [number[w] for w in at]
            coded = np.logical_and.reduce([x >= 0 for x in numbers])
            code = np.zeros(int(coded.sum()), np.int64)
            for x in numbers:
                code = code << BITS | x[coded]
            rest = ~coded
            yield from _batches(_dealt(bucket[coded], CODES, code, c[coded]))
            yield from _batches(_dealt(bucket[rest], ROWS, a[rest], b[rest], c[rest]))
            ts.release()

    return train.select(text).mapInArrow(scan, PACKED)


def _kept(parts: DataFrame, words: Broadcast, often: Broadcast, size: int, buckets: int, name: str) -> DataFrame:
    """Packed rows of n-grams that occur LEAST times: left, right, count, probability of the right part (given as facts, unless it occurs often)."""

    def reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for bucket, met in _buckets_met(batches):
            found = [met[ROWS]] if ROWS in met else []
            if CODES in met:
                code, c = met[CODES]
                mask = np.uint64((1 << BITS) - 1)
                numbers = [code >> np.uint64(s * BITS) & mask for s in reversed(range(size))]
                found.append(np.stack([*_keys(words.value.keys, [x.astype(np.int64) for x in numbers]), c]))
            if not found:
                continue
            a, b, c = np.concatenate(found, axis=1)
            k = mixed(a, b)
            order = np.argsort(k)
            k = k[order]
            first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
            c = np.add.reduceat(c[order].view(np.int64), first)
            some = c >= LEAST
            at, c = order[first[some]], c[some]
            if not len(at):
                continue
            a, b = a[at], b[at]
            yield from _batches(_rows(bucket, ROWS, (a, b, c, _values(often.value.keys, often.value.p, met.get(FACTS), b))))

    return stored(_met(parts, buckets).mapInArrow(reduce, PACKED), name)


def _values(keys: np.ndarray, values: np.ndarray, facts: np.ndarray | None, wanted: np.ndarray) -> np.ndarray:
    """Values of the wanted parts, from those that occur often or from facts (key, value)."""
    at = place(keys, wanted)
    out = values[at] if len(values) else np.zeros(len(wanted))
    rest = np.flatnonzero(at < 0)
    if len(rest):
        order = np.argsort(facts[0])
        out[rest] = facts[1].view(np.float64)[order][np.searchsorted(facts[0], wanted[rest], sorter=order)]
    return out


def _added(kept: DataFrame, often: Broadcast) -> np.ndarray:
    """Failure weights of the contexts that occur often."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = often.value.keys
        sums = np.zeros((2, len(keys)))
        for _, _, (a, _, c, q) in unpacked(batches):
            at = place(keys, a)
            some = at >= 0
            sums[0] += np.bincount(at[some], c[some].view(np.int64) - DISCOUNT, len(keys))
            sums[1] += np.bincount(at[some], q[some].view(np.float64), len(keys))
        yield from _sliced(sums)

    def weights(bucket: int, sums: np.ndarray) -> np.ndarray:
        seen = often.value.counts[bucket * SLICE : (bucket + 1) * SLICE]
        return np.log10((1 - sums[0] / np.maximum(seen, 1)) / (1 - sums[1]))

    return _joined(kept.mapInArrow(scan, PACKED), 2, np.add, weights, np.zeros(len(often.value.keys)))


def _sliced(found: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Packed rows of slices of the columns of a long array, but those of zeros."""
    for i in range(-(-found.shape[1] // SLICE)):
        part = found[:, i * SLICE : (i + 1) * SLICE]
        if part.any():
            yield from _batches([(i, ROWS, part.shape[1], part.tobytes())])


def _joined(parts: DataFrame, size: int, add: np.ufunc, result, into: np.ndarray) -> np.ndarray:
    """Long arrays of `size` columns, sliced by many tasks, added up; result(slice, columns) goes into the given array."""
    kind = into.dtype

    def reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for bucket, _, columns in unpacked(batches):
            found = total.setdefault(bucket, np.zeros((size, columns.shape[1]), kind))
            add(found, columns.view(kind), out=found)
        for bucket, found in total.items():
            out = result(bucket, found)
            yield from _batches([(bucket, ROWS, len(out), out.tobytes())])

    with shuffles_removed(parts.sparkSession):
        found = parts.repartition(16, "bucket").mapInArrow(reduce, PACKED).toArrow()
    for bucket, _, columns in unpacked(iter(found.to_batches())):
        into[bucket * SLICE : bucket * SLICE + columns.shape[1]] = columns[0].view(kind)
    return into


def marks_of(packed: DataFrame, bits: int, key) -> np.ndarray:
    """A filter of 2**bits bits, as keyfilter.passes reads it, of the keys (uint64) that key(columns) gives of packed rows."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, width = np.zeros(1 << (bits - 6), np.uint64), np.uint64(bits)
        for _, _, columns in unpacked(batches):
            keys = key(columns)
            for p in (keys & np.uint64((1 << bits) - 1), keys >> (np.uint64(64) - width)):
                np.bitwise_or.at(words, (p >> np.uint64(6)).astype(np.int64), np.uint64(1) << (p & np.uint64(63)))
        yield from _sliced(words[None])

    return _joined(packed.mapInArrow(scan, PACKED), 1, np.bitwise_or, lambda _, found: found[0], np.zeros(1 << (bits - 6), np.uint64))


def _weighed(kept: DataFrame, facts: DataFrame, often: Broadcast, buckets: int, name: str) -> DataFrame:
    """Packed rows of all n-grams (own key, count, probability, what the arc gains over failing) and of the
    rare contexts (key, failure weight). Facts: counts of parts that are rare."""

    def arcs(k: np.ndarray, c: np.ndarray, seen: np.ndarray, weight: np.ndarray, q: np.ndarray) -> list[tuple[int, int, int, bytes]]:
        p = (c.view(np.int64) - DISCOUNT) / seen
        return _rows(0, ROWS, (k, c, p, np.log10(p / q) - weight))

    def of_often(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, (a, b, c, q) in together(batches):
            at = place(often.value.keys, a)
            some = at >= 0
            if some.any():
                at = at[some]
                yield from _batches(arcs(mixed(a[some], b[some]), c[some], often.value.counts[at], often.value.weights[at], q[some].view(np.float64)))

    def of_rare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, (a, b, c, q) in together(batches):
            some = place(often.value.keys, a) < 0
            if some.any():
                a, b, c, q = a[some], b[some], c[some], q[some]
                yield from _batches(_dealt(buckets_of(a, buckets), ROWS, a, b, c, q))

    def reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, met in _buckets_met(batches):
            if ROWS not in met:
                continue
            order = np.argsort(met[ROWS][0])
            a, b, c, q = (x[order] for x in met[ROWS])
            q = q.view(np.float64)
            first = np.flatnonzero(np.concatenate([[True], a[1:] != a[:-1]]))
            seen = _values(np.zeros(0, np.uint64), np.zeros(0), met[FACTS], a[first])
            weight = np.log10((1 - np.add.reduceat(c.view(np.int64) - DISCOUNT, first) / seen) / (1 - np.add.reduceat(q, first)))
            sizes = np.diff(np.append(first, len(a)))
            yield from _batches(arcs(mixed(a, b), c, np.repeat(seen, sizes), np.repeat(weight, sizes), q) + _rows(0, WEIGHTS, (a[first], weight)))

    rare = _met(kept.mapInArrow(of_rare, PACKED).unionByName(facts), buckets).mapInArrow(reduce, PACKED)
    return stored(kept.mapInArrow(of_often, PACKED).unionByName(rare), name)


def facts_of(words: DataFrame, below: int, buckets: int, p=None) -> DataFrame:
    """Packed keys and values of words (w, c) that occur fewer than `below` times: p of their counts, or the counts."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            w, c = batch.column(0).to_numpy().view(np.uint64), batch.column(1).to_numpy().astype(np.float64)
            if len(w):
                yield from _batches(_dealt(buckets_of(w, buckets), FACTS, w, p(c) if p else c))

    return words.filter(F.col("c") < below).select("w", "c").mapInArrow(scan, PACKED)


def facts_of_arcs(arcs: DataFrame, below: int, buckets: int, probability: bool) -> DataFrame:
    """The same of n-grams, from what _weighed gives: their probabilities or counts."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, (k, c, p, _) in together(batches):
            some = c.view(np.int64) < below
            if some.any():
                k, c, p = k[some], c[some].view(np.int64).astype(np.float64), p[some]
                yield from _batches(_dealt(buckets_of(k, buckets), FACTS, k, p if probability else c))

    return arcs.filter(F.col("kind") == ROWS).mapInArrow(scan, PACKED)


def frequent(packed: DataFrame, at: int, least: int) -> list[np.ndarray]:
    """The columns of packed n-grams whose counts, column `at`, are at least `least`."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, _, columns in unpacked(batches):
            some = columns[at].view(np.int64) >= least
            if some.any():
                yield pa.RecordBatch.from_arrays([pa.array(x[some].view(np.int64)) for x in columns], names=list("abcd"))

    found = packed.filter(F.col("kind") == ROWS).mapInArrow(scan, "a long, b long, c long, d long").toArrow()
    return [found.column(i).to_numpy().view(np.uint64) for i in range(4)]


@dataclass
class Level:
    """N-grams of one length: those that occur often (left, right, count), all of them packed with the failure
    weights of rare contexts, and the failure weights of contexts that occur often; a filter of them if asked for."""

    often: tuple[np.ndarray, np.ndarray, np.ndarray]
    arcs: DataFrame
    weights: np.ndarray
    marked: np.ndarray | None


def level(train: DataFrame, text: str, words: Often, often: Often, marked: np.ndarray | None, facts, least: int, tokens: int, name: str) -> Level:
    """Pairs, or with a filter of those, triples. `often`: parts that occur often; facts(buckets, probability): the others."""
    size, share = 2 if marked is None else 3, train.sparkSession.sparkContext.broadcast
    numbered, parts = share(words), share(often)
    buckets = bucket_count(train, tokens)
    shared = None if marked is None else share(marked)
    found = _scanned(train, text, numbered, parts, shared, buckets)
    kept = _kept(found.unionByName(facts(buckets, True)), numbered, parts, size, buckets, f"{name}-counts")
    a, b, c, _ = frequent(kept, 2, least)
    weights = _added(kept, parts)
    mark = marks_of(kept, PAIR_BITS, lambda columns: mixed(columns[0], columns[1])) if size == 2 else None
    weighed = share(Often(often.keys, often.counts, often.p, weights))
    buckets = bucket_count(train, rows_of(kept))
    arcs = _weighed(kept, facts(buckets, False), weighed, buckets, f"{name}-arcs")
    discard(kept)
    for used in (numbered, parts, weighed, shared):
        if used is not None:
            used.destroy()
    return Level((a, b, c.view(np.int64)), arcs, weights, mark)
