"""Secret scans: rules behind a trigram inverted index.

A rule is a regular expression. From its parse tree follows a Boolean query over lower-case
byte trigrams that every match must satisfy (mandatory literals are joined by AND, branches
by OR). Each block of rows gets an inverted index of the trigrams that the rules ask for;
the postings are intersected and united as the query says, and only the rows that remain
are searched with the expression. A rule without a mandatory trigram scans all rows.

Null text: empty. Spans are code points, end exclusive, ordered by start and then by the
rule's place in the list. Repeated rows are searched one by one; other columns are not read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from re import _constants as c
from re import _parser as parser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from . import textscan as ts


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str
    ignore_case: bool = False
    group: int = 0
    least: int = 0

    def compiled(self) -> re.Pattern:
        return re.compile(self.pattern, re.ASCII | (re.IGNORECASE if self.ignore_case else 0))


# The three base kinds, as the result's contract names them.
BASE = (
    Rule("assign", r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", True, 2, 12),
    Rule("access", r"AKIA[A-Z0-9]+", False, 0, 18),
    Rule("hex", r"[0-9a-f]{16,}", False, 0, 16),
)
#: Well-known public token formats.
EXTRA = (
    Rule("github", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("slack", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("google", r"AIza[A-Za-z0-9_-]{35}"),
    Rule("stripe", r"[rs]k_live_[A-Za-z0-9]{16,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("pem", r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----"),
    Rule("url", r"[a-z][a-z0-9+.-]{1,15}://[^\s:@/]+:[^\s:@/]{3,}@[A-Za-z0-9.-]+", True),
)
RULES = BASE + EXTRA

Query = tuple  # ("all",) | ("tri", t) | ("and", *parts) | ("or", *parts)
ALL: Query = ("all",)


def _both(parts: list[Query]) -> Query:
    parts = [p for p in dict.fromkeys(parts) if p != ALL]
    return ALL if not parts else parts[0] if len(parts) == 1 else ("and", *parts)


def _either(parts: list[Query]) -> Query:
    parts = list(dict.fromkeys(parts))
    return ALL if ALL in parts or not parts else parts[0] if len(parts) == 1 else ("or", *parts)


def _trigrams(literal: str) -> Query:
    raw = literal.lower().encode()
    return _both([("tri", raw[i : i + 3]) for i in range(len(raw) - 2)])


#: Alternatives of mandatory text are spelled out as long as there are no more of them than this.
MAX_SPELLED = 64


def _spell(tree) -> tuple[set[str] | None, Query]:
    """All texts that a sequence can match, if they are few; and the query that its matches satisfy."""
    parts: list[Query] = []
    runs: set[str] = {""}
    whole = True

    def close() -> None:
        nonlocal runs
        parts.append(_either([_trigrams(r) for r in runs]))
        runs = {""}

    def extend(more: set[str]) -> None:
        nonlocal runs, whole
        if len(runs) * len(more) > MAX_SPELLED:
            close()
            whole = False
        runs = {a + b for a in runs for b in more}

    for op, arg in tree:
        if op is c.LITERAL:
            extend({chr(arg)})
            continue
        if op is c.SUBPATTERN:
            texts, query = _spell(arg[-1])
        elif op is c.BRANCH:
            each = [_spell(branch) for branch in arg[1]]
            query = _either([q for _, q in each])
            texts = set().union(*(t for t, _ in each)) if all(t is not None for t, _ in each) else None
        elif op is c.IN and all(k is c.LITERAL for k, _ in arg):
            texts, query = {chr(v) for _, v in arg}, ALL
        elif op in (c.MAX_REPEAT, c.MIN_REPEAT):
            low, high, body = arg
            inner, query = _spell(body)
            query = query if low else ALL
            texts = {""} | inner if (low, high) == (0, 1) and inner is not None and len(inner) <= 8 else None
        else:
            texts, query = None, ALL
        parts.append(query)
        if texts is not None and len(texts) <= MAX_SPELLED:
            extend(texts)
        else:
            close()
            whole = False
    texts = runs if whole else None
    close()
    return texts, _both(parts)


def trigram_query(pattern: str) -> Query:
    """The Boolean trigram query that the text of every match satisfies; ("all",) if there is none."""
    return _spell(parser.parse(pattern))[1]


def _asked(query: Query) -> set[bytes]:
    return {query[1]} if query[0] == "tri" else set().union(*map(_asked, query[1:])) if query != ALL else set()


class TrigramIndex:
    """Inverted index of a block of rows over the trigrams that some queries ask for."""

    def __init__(self, asked: list[bytes]):
        self.asked = {t: i for i, t in enumerate(asked)}
        self.number = np.zeros(1 << 24, np.uint8 if len(asked) < 255 else np.uint16)
        for t, i in self.asked.items():
            self.number[int.from_bytes(t, "big")] = i + 1

    def postings(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """For each trigram asked for, which rows hold it."""
        held = np.zeros((len(self.asked), len(offsets) - 1), bool)
        low = ts.LOWER[data].astype(np.int32)
        code = (low[:-2] << 16) | (low[1:-1] << 8) | low[2:]
        number = self.number[code]
        at = np.flatnonzero(number)
        rows = np.searchsorted(offsets, at, "right") - 1
        inside = at + 3 <= offsets[rows + 1]
        held[number[at[inside]].astype(np.int64) - 1, rows[inside]] = True
        return held

    def rows(self, query: Query, held: np.ndarray) -> np.ndarray:
        if query == ALL:
            return np.ones(held.shape[1], bool)
        if query[0] == "tri":
            return held[self.asked[query[1]]]
        parts = [self.rows(q, held) for q in query[1:]]
        return np.logical_and.reduce(parts) if query[0] == "and" else np.logical_or.reduce(parts)


class Scanner:
    def __init__(self, rules: tuple[Rule, ...] = RULES):
        self.rules = rules
        self.queries = [trigram_query(r.pattern) for r in rules]
        self.index = TrigramIndex(sorted(set().union(*map(_asked, self.queries))))
        self.patterns = [r.compiled() for r in rules]

    def scan(self, texts: pa.Array) -> Iterator[list[list[tuple[int, int]]]]:
        """For each row the spans of each rule."""
        data, offsets = ts.buffers(texts)
        for a, b in ts.row_blocks(offsets):
            part, at = data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
            held = self.index.postings(part, at)
            wanted = [self.index.rows(q, held) for q in self.queries]
            for row in range(b - a):
                text, out = None, []
                for rule, pattern, rows in zip(self.rules, self.patterns, wanted, strict=True):
                    if not rows[row]:
                        out.append([])
                        continue
                    if text is None:
                        text = part[at[row] : at[row + 1]].tobytes().decode()
                    out.append([m.span() for m in pattern.finditer(text) if m.end(rule.group) - m.start(rule.group) >= rule.least])
                yield out


def joined(rules: tuple[Rule, ...], spans: list[list[tuple[int, int]]]) -> str:
    """kind:start:end of all spans by start, then by the rule's place."""
    flat = sorted((s, k, e) for k, each in enumerate(spans) for s, e in each)
    return ",".join(f"{rules[k].kind}:{s}:{e}" for s, k, e in flat)


RESULT = [T.StructField(n, T.LongType()) for n in ("n_assign", "n_access", "n_hex")] + [T.StructField(n, T.StringType()) for n in ("base_sha256", "spans")]


def scan_secrets(docs: DataFrame, key: str = "doc_id", text: str = "text", extra: tuple[Rule, ...] = EXTRA) -> DataFrame:
    """One row per document: key, counts of the base kinds, digest of the base spans, and all spans."""
    rules = BASE + tuple(extra)
    schema = T.StructType([T.StructField(key, docs.schema[key].dataType), *RESULT])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(rules)
        for batch in batches:
            cols: list[list] = [[], [], [], [], []]
            for spans in scanner.scan(batch.column(1)):
                base = joined(BASE, spans[:3])
                for col, v in zip(cols, (*map(len, spans[:3]), hashlib.sha256(base.encode()).hexdigest(), joined(rules, spans)), strict=True):
                    col.append(v)
            arrays = [pa.array(v, pa.int64()) for v in cols[:3]] + [pa.array(v, pa.string()) for v in cols[3:]]
            yield pa.RecordBatch.from_arrays([batch.column(0), *arrays], names=schema.names)

    return docs.select(key, text).mapInArrow(scan, schema)


def redact(docs: DataFrame, key: str = "doc_id", text: str = "text", mask: Callable[[str], str] = lambda kind: f"[{kind}]", extra: tuple[Rule, ...] = EXTRA) -> DataFrame:
    """key and text with every found span replaced by mask(kind); overlapping spans are masked as the first."""
    rules = BASE + tuple(extra)
    schema = docs.select(key, text).schema

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(rules)
        for batch in batches:
            out = []
            for value, spans in zip(batch.column(1).to_pylist(), scanner.scan(batch.column(1)), strict=True):
                if value is None:
                    out.append(None)
                    continue
                at, kept = 0, []
                for s, k, e in sorted((s, k, e) for k, each in enumerate(spans) for s, e in each):
                    if s >= at:
                        kept += [value[at:s], mask(rules[k].kind)]
                    at = max(at, e)
                out.append("".join([*kept, value[at:]]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, batch.column(1).type)], names=schema.names)

    return docs.select(key, text).mapInArrow(scan, schema)
