"""Vectorised scanning of Arrow text columns: words, span hashes and row blocks in numpy.

Everything works on the UTF-8 bytes that Arrow hands over, so a batch is never turned into
Python strings. Hashes are polynomial in 64 bits and only ever propose candidates or name
sets; callers that need certainty compare the bytes.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BYTE_BASE = np.uint64(0x9E3779B97F4A7C55)
WORD_BASE = np.uint64(0xD6E8FEB86659FD93)
BLOCK_BYTES = 1 << 19
#: Bytes (or words) that are hashed at a time; tables of powers are no longer than this and a bit.
SEGMENT = 1 << 20

#: Bytes as they are, but A-Z turned to a-z.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def byte_class(characters: bytes, complement: bool = False) -> np.ndarray:
    """256 booleans: true for the given bytes, or for all others."""
    mask = np.zeros(256, bool)
    mask[list(characters)] = True
    return ~mask if complement else mask


SPACE = bytes([0x20, *range(0x09, 0x0E)])
#: Bytes of words that end at white space.
SPACED_WORD = byte_class(SPACE, complement=True)
#: Bytes of words made of digits, letters and everything beyond ASCII.
ALNUM_WORD = byte_class(bytes(range(0x30, 0x3A)) + bytes(range(0x41, 0x5B)) + bytes(range(0x61, 0x7B)) + bytes(range(0x80, 0x100)))


class Powers:
    """Powers of an odd base modulo 2**64 and of its inverse, grown on demand."""

    def __init__(self, base: np.uint64):
        self.base, self.inverse = int(base), pow(int(base), -1, 1 << 64)
        self.up = self.down = np.ones(0, np.uint64)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = -(-n >> 16) << 16 if n <= SEGMENT + 1 else max(n, 2 * len(self.up))  # blocks differ little: no doubling for them
            for name, base in (("up", self.base), ("down", self.inverse)):
                steps = np.full(size, base, np.uint64)
                steps[0] = 1
                setattr(self, name, np.multiply.accumulate(steps))
        return self.up, self.down


_bytes, _words = Powers(BYTE_BASE), Powers(WORD_BASE)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every input bit."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


def buffers(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a string or binary column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and len(data) else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def row_blocks(offsets: np.ndarray, limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of about `limit` bytes; a longer row is a block of its own."""
    first, rows = 0, len(offsets) - 1
    while first < rows:
        last = int(np.searchsorted(offsets, offsets[first] + limit, side="right")) - 1
        last = min(max(last, first + 1), rows)
        yield first, last
        first = last
    release()


def release() -> None:
    """Gives the memory of freed arrays back to the system, so that a worker doesn't keep its largest block."""
    pa.default_memory_pool().release_unused()
    if _libc is not None:
        _libc.malloc_trim(0)


def _opened_libc() -> ctypes.CDLL | None:
    try:
        libc = ctypes.CDLL(None)
        return libc if hasattr(libc, "malloc_trim") else None
    except OSError:
        return None


_libc = _opened_libc()


class Words:
    """Words of the rows of one block.

    data: the block's bytes, A-Z lowered; start, end: byte places of each word;
    first: for each row the index of its first word, then the number of words.
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray, word_bytes: np.ndarray):
        inside = word_bytes[data]
        n = len(data)
        edge = np.zeros(n + 1, bool)
        edge[offsets] = True
        before = np.empty(n, bool)
        before[:1] = False
        before[1:] = inside[:-1]
        self.start = np.flatnonzero(inside & (~before | edge[:n]))
        after = np.empty(n, bool)
        after[-1:] = False
        after[:-1] = inside[1:]
        self.end = np.flatnonzero(inside & (~after | edge[1:])) + 1
        self.data = LOWER[data]
        self.first = np.searchsorted(self.start, offsets)
        self.counts = np.diff(self.first)

    def hashes(self) -> np.ndarray:
        return hash_spans(self.data, self.start, self.end)

    def text(self, i: int, j: int) -> bytes:
        """Words i to j-1 with one blank between."""
        return b" ".join(self.data[s:e].tobytes() for s, e in zip(self.start[i:j], self.end[i:j], strict=True))


def _sums(data: np.ndarray, start: np.ndarray, end: np.ndarray, powers: Powers) -> np.ndarray:
    up, down = powers.get(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    terms = total[1:]  # in place: these arrays are eight times as large as the text
    terms[:] = data
    terms += np.uint64(1)
    terms *= up[: len(data)]
    np.cumsum(terms, out=terms)
    return (total[end] - total[start]) * down[start]


def _long_sum(data: np.ndarray, powers: Powers) -> int:
    """The same sum for one long span, piece by piece."""
    total, ends = 0, np.zeros(1, np.int64)
    for at in range(0, len(data), SEGMENT):
        piece = data[at : at + SEGMENT]
        total += int(_sums(piece, ends, ends + len(piece), powers)[0]) * pow(powers.base, at, 1 << 64)
    return total & (1 << 64) - 1


def hash_spans(data: np.ndarray, start: np.ndarray, end: np.ndarray, powers: Powers = _bytes) -> np.ndarray:
    """64-bit hashes of data[start:end] for each span; start has to rise.

    A sum starts with the power 0 wherever its span lies, so data can be hashed in overlapping
    segments: a span belongs to the first segment that holds its start in the first half.
    """
    if len(data) <= SEGMENT:
        return mix(_sums(data, start, end, powers))
    out, half = np.empty(len(start), np.uint64), SEGMENT // 2
    edges = np.searchsorted(start, np.arange(0, len(data) + half, half))
    for i, (a, b) in enumerate(zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)):
        if a < b:
            stop = np.minimum(end[a:b] - i * half, SEGMENT)
            out[a:b] = _sums(data[i * half : i * half + SEGMENT], start[a:b] - i * half, np.minimum(stop, len(data) - i * half), powers)
    for k in np.flatnonzero(end - start > half):
        out[k] = _long_sum(data[start[k] : end[k]], powers)
    return mix(out)


def hash_windows(words: np.ndarray, size: int) -> np.ndarray:
    """Hashes of every `size` consecutive word hashes (rows are not told apart)."""
    if len(words) < size:
        return np.zeros(0, np.uint64)
    if len(words) > SEGMENT:
        parts = [hash_windows(words[i : i + SEGMENT], size) for i in range(0, len(words) - size + 1, SEGMENT - size + 1)]
        return np.concatenate(parts)
    up, down = _words.get(len(words) + 1)
    total = np.zeros(len(words) + 1, np.uint64)
    np.cumsum(words * up[: len(words)], out=total[1:])
    return mix((total[size:] - total[:-size]) * down[: len(words) - size + 1] + np.uint64(size))


def window_rows(first: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Of the windows of hash_windows: those inside one row, and that row."""
    counts = np.maximum(np.diff(first) - size + 1, 0)
    rows = np.repeat(np.arange(len(counts)), counts)
    starts = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts) + first[:-1][rows]
    return starts, rows


def ragged(counts: np.ndarray) -> np.ndarray:
    """0..c-1 for each count c, in one array."""
    return np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
