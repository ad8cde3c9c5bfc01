"""Token ids of the public word-level BPE vocabulary for whole columns at a time.

The tokenizer lower-cases, drops white space and never merges across it, so a text's ids are
those of its pieces in turn. Pieces made of plain letters, digits and marks are cut and
merged here in numpy, all different pieces of a block at once; any stretch between blanks
with another character (apostrophes, combining marks, other scripts, special tokens) is
given to the tokenizers library as it stands. Both are remembered by a 64-bit hash.
"""

from __future__ import annotations

import json
import os
from collections.abc import Iterator

import numpy as np

from . import textscan as ts

SPACE, LETTER, DIGIT, OTHER, SLOW = range(5)
LONGEST = 48
REMEMBERED = 1_000_000
NONE = np.iinfo(np.int32).max


def public_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _tables() -> tuple[np.ndarray, np.ndarray]:
    """Class and lower case of each code point below 65536; whatever isn't surely plain is SLOW."""
    kind = np.full(1 << 16, SLOW, np.uint8)
    lower = np.arange(1 << 16, dtype=np.uint32)
    for c in range(0x21, 0x7F):
        kind[c] = LETTER if chr(c).isalpha() else DIGIT if chr(c).isdigit() else OTHER
    kind[[0x20, *range(0x09, 0x0E)]] = SPACE
    kind[ord("'")] = SLOW
    for c in [*range(0xC0, 0x130), *range(0x132, 0x138), *range(0x139, 0x149), *range(0x14A, 0x178), *range(0x410, 0x450)]:
        if chr(c).isalpha() and len(chr(c).lower()) == 1:
            kind[c] = LETTER
    for c in np.flatnonzero(kind == LETTER):
        lower[c] = ord(chr(c).lower())
    return kind, lower


class WordBpe:
    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        with open(path) as f:
            model = json.load(f)["model"]
        vocab = model["vocab"]
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        keys = np.array([vocab[a] << 20 | vocab[b] for a, b in pairs], np.int64)
        self.order = np.argsort(keys, kind="stable")
        self.keys, self.merged = keys[self.order], np.array([vocab[a + b] for a, b in pairs], np.int32)
        self.order = self.order.astype(np.int32)
        visible = [*range(33, 127), *range(161, 173), *range(174, 256)]
        shown = {b: chr(b) for b in visible} | {b: chr(256 + i) for i, b in enumerate(x for x in range(256) if x not in set(visible))}
        self.inner = np.array([vocab[shown[b]] for b in range(256)], np.int32)
        self.final = np.array([vocab[shown[b] + "</w>"] for b in range(256)], np.int32)
        self.kind, self.lower = _tables()
        self.forget()

    def forget(self) -> None:
        self.known = np.zeros(0, np.uint64)
        self.place, self.size, self.flat = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int32)

    def merge(self, words: list[bytes]) -> list[np.ndarray]:
        """Ids of words (lower-cased UTF-8, at most LONGEST bytes), merged side by side."""
        sizes = np.array([len(w) for w in words], np.int64)
        raw = np.frombuffer(b"".join(words), np.uint8)
        word = np.repeat(np.arange(len(words)), sizes)
        symbols = self.inner[raw]
        ends = np.cumsum(sizes) - 1
        symbols[ends] = self.final[raw[ends]]
        done_word, done_symbol = [], []
        while len(symbols):
            key = symbols[:-1].astype(np.int64) << 20 | symbols[1:]
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            rank = np.full(len(symbols), NONE, np.int32)
            rank[:-1] = np.where((self.keys[at] == key) & (word[:-1] == word[1:]), self.order[at], NONE)
            first = np.flatnonzero(np.diff(word, prepend=-1))
            lowest = np.minimum.reduceat(rank, first)
            group = np.repeat(np.arange(len(first)), np.diff(np.append(first, len(word))))
            active = lowest[group] != NONE
            done_word.append(word[~active])
            done_symbol.append(symbols[~active])
            hit = np.flatnonzero(active & (rank == lowest[group]))
            hit = hit[np.diff(group[hit], prepend=-1) != 0]  # the leftmost of each word
            symbols[hit] = self.merged[rank[hit]]
            keep = active
            keep[hit + 1] = False
            symbols, word = symbols[keep], word[keep]
        word, symbols = np.concatenate(done_word), np.concatenate(done_symbol)
        symbols = symbols[np.argsort(word, kind="stable")]
        ends = np.cumsum(np.bincount(word, minlength=len(words))).tolist()
        return [symbols[a:b] for a, b in zip([0, *ends], ends, strict=False)]

    def _learn(self, hashes: np.ndarray, texts: list[str], slow: np.ndarray) -> None:
        ids: list[np.ndarray] = [np.zeros(0, np.int32)] * len(texts)
        raw = [t.encode() for t in texts]
        plain = [i for i in range(len(texts)) if not slow[i] and len(raw[i]) <= LONGEST]
        for i, found in zip(plain, self.merge([raw[i] for i in plain]) if plain else [], strict=True):
            ids[i] = found
        rest = [i for i in range(len(texts)) if slow[i] or len(raw[i]) > LONGEST]
        for i, e in zip(rest, self.tokenizer.encode_batch([texts[i] for i in rest], add_special_tokens=False), strict=True):
            ids[i] = np.array(e.ids, np.int32)
        sizes = np.array([len(x) for x in ids], np.int64)
        place = len(self.flat) + np.cumsum(sizes) - sizes
        known = np.concatenate([self.known, hashes])
        order = np.argsort(known, kind="stable")
        self.known, self.place, self.size = known[order], np.concatenate([self.place, place])[order], np.concatenate([self.size, sizes])[order]
        self.flat = np.concatenate([self.flat, *ids])

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """For blocks of rows (first, last): all ids, and the place of each row's first id (one more for the end)."""
        for a, b in ts.row_blocks(offsets):
            yield a, b, *self._block(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])

    def _block(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        text = data.tobytes().decode()
        points = np.frombuffer(text.encode("utf-32-le"), np.uint32)
        rows = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])[offsets]
        n = len(points)
        if not n:
            return np.zeros(0, np.int32), np.zeros(len(offsets), np.int64)
        small = np.minimum(points, 0xFFFF)
        kind, low = self.kind[small], self.lower[small]
        special = np.flatnonzero((points[:-1] == ord("<")) & (points[1:] == ord("|")))
        kind[special] = SLOW
        edge = np.zeros(n + 1, bool)
        edge[rows] = True
        edge = edge[:n]
        ink = kind != SPACE
        before = np.concatenate([[False], ink[:-1]])
        chunk_start = ink & (~before | edge)
        chunk = np.cumsum(chunk_start) - 1  # of ink
        slow_chunk = np.zeros(int(chunk[-1]) + 2, bool)
        slow_chunk[chunk[kind == SLOW]] = True
        slow = ink & slow_chunk[chunk]
        new = ink & (chunk_start | (~slow & ((kind == DIGIT) | (kind != np.concatenate([[SPACE], kind[:-1]])))))
        start = np.flatnonzero(new)
        stop = np.flatnonzero(ink & np.concatenate([new[1:] | ~ink[1:] | edge[1:], [True]])) + 1
        shown = np.where(slow, points, low)
        hashes = ts.hash_spans(shown, start, stop) ^ (slow[start].astype(np.uint64) * ts.BYTE_BASE)
        distinct, where, back = np.unique(hashes, return_index=True, return_inverse=True)
        if len(self.known) > REMEMBERED:
            self.forget()
        at = np.minimum(np.searchsorted(self.known, distinct), max(len(self.known) - 1, 0))
        fresh = np.flatnonzero(self.known[at] != distinct) if len(self.known) else np.arange(len(distinct))
        if len(fresh):
            i = where[fresh]
            lowered = shown.astype("<u4").tobytes().decode("utf-32-le")
            self._learn(distinct[fresh], [lowered[s:e] for s, e in zip(start[i], stop[i], strict=True)], slow[start[i]])
            at = np.searchsorted(self.known, distinct)
        piece = at[back]
        sizes = self.size[piece]
        ids = self.flat[np.repeat(self.place[piece], sizes) + ts.ragged(sizes)]
        total = np.concatenate([[0], np.cumsum(sizes)])
        return ids, total[np.searchsorted(start, rows)]


_open: dict[str, WordBpe] = {}


def opened(path: str) -> WordBpe:
    """One tokenizer for each process and file."""
    if path not in _open:
        _open[path] = WordBpe(path)
    return _open[path]
