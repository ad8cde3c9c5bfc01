"""Language-model scoring with a weighted backoff automaton.

Counts of all words of the training rows are gathered. Words whose share of the training
tokens is at least SHARE (of which there can be no more than 1 / SHARE) get a number and
unigram arcs from the root state; the counts of all others stay in a table that documents'
words are joined with. The model's n-grams are all bigrams and trigrams that occur at least
LEAST times, of whatever words. Absolute discounting gives their arcs, and what it leaves goes
to a failure arc to the shorter context, weighted so that each context's probabilities sum to
one. N-grams of numbered words whose share is at least CONTEXT_SHARE are found level by level
(an n-gram is no more frequent than its parts) and become states of a broadcast automaton;
all others stay in tables. One left-to-right traversal of the automaton carries the state of
each document and adds up log-probabilities; a batch's documents step together, long ones in
stretches whose first state the two words before them give. At a word
without a number the failure arcs lead to the root. The same scan emits the words and n-grams
that the automaton lacks, packed into arrays by bucket of their hash; a task looks up one bucket's
arrays in that bucket's terms, and a sum by document adds them to what the traversal gave. Every
document is scored in one of TURNS such scans, whose shuffle files go before the next begins.
N-grams are counted and weighed in packed arrays too (`grams.py`).

With W a context's failure weight (log10; 0 if it has no arcs), the log-probability of c after
a, b is that of c alone, plus W(b), plus W(ab), plus what the arc of bc gains over failing at
b, plus what the arc of abc gains over failing at ab. Each term belongs to one n-gram, so
those that the automaton lacks are added by looking the document's n-grams up in the tables.
There are as many buckets as the tables need, so a bucket's terms have a bound; its packed rows
are read one after another.

The shares only divide the work: scores don't depend on them. The automaton has at most
1 / SHARE + 2 / CONTEXT_SHARE arcs, the tables grow with the input. Words, pairs and triples
are told apart by 64-bit hashes.

Null text: empty, one token (the end). Rows with a null key count as training rows. Repeated
rows train and are scored as rows of their own. Extra columns are not read. Without training
rows every score is 0.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.broadcast import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import grams
from .grams import BITS, DISCOUNT, END, LEAST, START, TOGETHER, mixed, token_blocks
from .keyfilter import passes
from .storage import discard, saved

SHARE, CONTEXT_SHARE = 1e-6, 1e-6
#: Tokens of a row that are walked one after another (at least 2).
STRETCH = 128
FOLDS, HELD_OUT = 5, 1
#: Turns in which the documents are scored, so that only a part of their n-grams is on disk at a time.
TURNS = 2
COLD = -1
#: Bits of the filter of n-grams that are looked up.
RARE_BITS = 27


def word_counts(train: DataFrame, text: str) -> DataFrame:
    """(w, c): how often each word (by hash), or the end, occurs."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [h for _, _, h, _ in token_blocks(batch.column(0))]
            if found:
                w, c = np.unique(np.concatenate(found), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(w.view(np.int64)), pa.array(c)], names=["w", "c"])

    return train.select(text).mapInArrow(scan, "w long, c long").groupBy("w").agg(F.sum("c").alias("c"))


def _collected(df: DataFrame, key: str) -> tuple[np.ndarray, np.ndarray]:
    found = df.toArrow()
    k, c = found.column(key).to_numpy(), found.column("c").to_numpy()
    order = np.argsort(k.view(np.uint64))
    return k[order], c[order]


@dataclass
class Vocabulary:
    """Numbered words: sorted hashes and their counts. The number after the last one stands for a text's start."""

    hashes: np.ndarray
    counts: np.ndarray
    total: int
    distinct: int

    @property
    def start(self) -> int:
        return len(self.hashes)

    def numbers(self, tokens: np.ndarray) -> np.ndarray:
        if not len(self.hashes):
            return np.full(len(tokens), COLD, np.int64)
        at = np.minimum(np.searchsorted(self.hashes, tokens), len(self.hashes) - 1)
        return np.where(self.hashes[at] == tokens, at, COLD)

    def unigram(self, count: np.ndarray) -> np.ndarray:
        return (count + 0.5) / (self.total + 0.5 * (self.distinct + 1))


class Automaton:
    """States: 0 the root, then one for each context. Arcs (state, word) lead to a state with a log10 weight."""

    def __init__(self, vocabulary: Vocabulary, pairs: tuple[np.ndarray, np.ndarray], triples: tuple[np.ndarray, np.ndarray], texts: int):
        v, mask = vocabulary, (1 << BITS) - 1
        p1 = v.unigram(v.counts.astype(np.float64))
        left, right = pairs[0] >> BITS, pairs[0] & mask
        ones = np.unique(left)  # words (or the start) that are contexts
        twos = np.unique(triples[0] >> BITS)  # pairs that are contexts
        one_state = np.zeros(v.start + 1, np.int64)
        one_state[ones] = 1 + np.arange(len(ones))
        seen = np.append(v.counts, texts).astype(np.float64)
        p2 = (pairs[1] - DISCOUNT) / seen[left]
        self.fail, self.weight = np.zeros(1 + len(ones) + len(twos), np.int64), np.zeros(1 + len(ones) + len(twos))
        spent, below = np.bincount(one_state[left], p2, len(self.fail)), np.bincount(one_state[left], p1[right], len(self.fail))
        level = slice(1, 1 + len(ones))
        self.weight[level] = np.log10((1 - spent[level]) / (1 - below[level]))
        two_state = 1 + len(ones) + np.arange(len(twos))

        def state_of(pair: np.ndarray) -> np.ndarray:
            """The longest context that a pair leaves: itself, its last word, or the root."""
            at = np.minimum(np.searchsorted(twos, pair), max(len(twos) - 1, 0))
            held = twos[at] == pair if len(twos) else np.zeros(len(pair), bool)
            return np.where(held, two_state[at] if len(twos) else 0, one_state[pair & mask])

        context, last = triples[0] >> BITS, triples[0] & mask
        owner = 1 + len(ones) + np.searchsorted(twos, context)
        count = dict(zip(pairs[0].tolist(), pairs[1].tolist(), strict=True))
        p3 = (triples[1] - DISCOUNT) / np.array([count[c] for c in context.tolist()], np.float64)
        lower = (context & mask) << BITS | last
        p2_of = dict(zip(pairs[0].tolist(), p2.tolist(), strict=True))
        shorter = np.array([p2_of[k] for k in lower.tolist()], np.float64)  # held: both pairs of a triple are known
        spent, below = np.bincount(owner, p3, len(self.fail)), np.bincount(owner, shorter, len(self.fail))
        level = slice(1 + len(ones), None)
        self.weight[level] = np.log10((1 - spent[level]) / (1 - below[level]))
        self.fail[level] = one_state[twos & mask]
        keys = np.concatenate([one_state[left] << BITS | right, owner << BITS | last])
        order = np.argsort(keys)
        self.keys = keys[order]
        self.to = np.concatenate([state_of(pairs[0]), state_of(lower)])[order]
        self.log = np.log10(np.concatenate([p2, p3]))[order]
        self.root_log, self.root_to = np.log10(p1), one_state[:-1]
        self.begin = int(one_state[v.start])
        self.ones, self.twos, self.pairs, self.triples = ones, twos, pairs[0], triples[0]

    def step(self, state: np.ndarray, word: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Next states and added log-probabilities; a cold word adds only the failure arcs' weights."""
        score, to = np.zeros(len(state)), np.zeros(len(state), np.int64)
        open_ = np.flatnonzero(state > 0)
        at_root = np.flatnonzero((state == 0) & (word >= 0))
        score[at_root], to[at_root] = self.root_log[word[at_root]], self.root_to[word[at_root]]
        state = state.copy()
        while len(open_):
            key = state[open_] << BITS | np.maximum(word[open_], 0)
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            found = (self.keys[at] == key) & (word[open_] >= 0)
            hit = open_[found]
            score[hit] += self.log[at[found]]
            to[hit] = self.to[at[found]]
            miss = open_[~found]
            score[miss] += self.weight[state[miss]]
            state[miss] = self.fail[state[miss]]
            done = miss[(state[miss] == 0) & (word[miss] >= 0)]
            score[done] += self.root_log[word[done]]
            to[done] = self.root_to[word[done]]
            open_ = miss[state[miss] > 0]
        return to, score

    def traverse(self, words: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Log-probabilities of the rows' numbered words. Long rows are cut into stretches, which all walk from
        left to right together: the two words before a stretch lead to the state it begins with."""
        sizes = np.diff(first)
        stretches = -(-sizes // STRETCH)
        row = np.repeat(np.arange(len(sizes)), stretches)
        nth = np.arange(len(row)) - np.repeat(np.cumsum(stretches) - stretches, stretches)
        place = first[:-1][row] + nth * STRETCH
        left = np.minimum(first[1:][row] - place, STRETCH)
        order = np.argsort(-left, kind="stable")
        row, nth, place, left = row[order], nth[order], place[order], left[order]
        total, state = np.zeros(len(row)), np.where(nth == 0, self.begin, 0)
        later = np.flatnonzero(nth > 0)
        for back in (2, 1):
            state[later], _ = self.step(state[later], words[place[later] - back])
        live, t = len(row), 0
        while True:
            live = int(np.searchsorted(-left[:live], -t, "left"))
            if not live:
                break
            state[:live], gained = self.step(state[:live], words[place[:live] + t])
            total[:live] += gained
            t += 1
        return np.bincount(row, total, len(sizes))


def _pairs_of(tokens: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Left words, right words and keys of the pairs of each row: as many as tokens, the first with the start."""
    left = np.concatenate([tokens[:1], tokens[:-1]])
    left[first[:-1]] = START
    return left, tokens, mixed(left, tokens)


def _triples_of(pairs: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Places of the second pairs of the rows' triples."""
    inner = np.ones(len(pairs), bool)
    inner[first[:-1]] = False
    return np.flatnonzero(inner)


@dataclass
class Learned:
    """The numbered words, the automaton, and the n-grams of which it has the frequent ones."""

    vocabulary: Vocabulary
    automaton: Automaton
    words: grams.Often
    pairs: grams.Level
    triples: grams.Level


def _thresholds(n: int) -> tuple[int, int]:
    """How often numbered words, and frequent n-grams, occur at least."""
    return max(1, int(np.ceil(SHARE * n))), max(LEAST, int(np.ceil(CONTEXT_SHARE * n)))


def learn(train: DataFrame, text: str, counts: DataFrame) -> Learned:
    sums = counts.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.count("*").alias("v"), F.coalesce(F.sum(F.when(F.col("w") == int(END.view(np.int64)), F.col("c"))), F.lit(0)).alias("texts")).first()
    n = sums["n"]
    numbered, least = _thresholds(n)
    hashes, c = _collected(counts.filter(F.col("c") >= numbered), "w")
    vocabulary = Vocabulary(hashes.view(np.uint64), c, n, sums["v"])
    keys, seen = np.append(vocabulary.hashes, START), np.append(c, sums["texts"]).astype(np.float64)
    order = np.argsort(keys)
    words = grams.Often(keys[order], seen[order], vocabulary.unigram(seen)[order])
    pairs = grams.level(train, text, words, words, None, lambda buckets, p: grams.facts_of(counts, numbered, buckets, vocabulary.unigram if p else None), least, n, "pair")
    k, c, p, _ = grams.frequent(pairs.arcs, 1, least)
    order = np.argsort(k)
    often = grams.Often(k[order], c[order].view(np.int64).astype(np.float64), p[order].view(np.float64))
    triples = grams.level(train, text, words, often, pairs.marked, lambda buckets, p: grams.facts_of_arcs(pairs.arcs, least, buckets, p), least, n, "triple")
    return Learned(vocabulary, _automaton(vocabulary, pairs.often, triples.often, sums["texts"]), words, pairs, triples)


@dataclass
class Rest:
    """What the automaton lacks: terms of the start and the numbered words, of frequent n-grams (sorted keys), and a filter of the others."""

    start: float
    words: np.ndarray
    keys: np.ndarray
    terms: np.ndarray
    others: np.ndarray


def _at(keys: np.ndarray, terms: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Terms of the wanted keys (0 if there is none); keys are sorted."""
    if not len(keys):
        return np.zeros(len(wanted))
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return np.where(keys[at] == wanted, terms[at], 0.0)


def complete(learned: Learned) -> Rest:
    """Gives the automaton's failure arcs the whole model's weights; returns what it lacks (but the filter)."""
    vocabulary, automaton, words = learned.vocabulary, learned.automaton, learned.words
    _, least = _thresholds(vocabulary.total)

    def gains(level: grams.Level) -> tuple[np.ndarray, np.ndarray]:
        k, _, _, gain = grams.frequent(level.arcs, 1, least)
        order = np.argsort(k)
        return k[order], gain[order].view(np.float64)

    of_word = _at(words.keys, learned.pairs.weights, np.append(vocabulary.hashes, START))
    (k2, gain2), (k3, gain3) = gains(learned.pairs), gains(learned.triples)
    w2 = learned.triples.weights
    hashes, mask = np.append(vocabulary.hashes, START), (1 << BITS) - 1
    keyed = lambda pair: mixed(hashes[pair >> BITS], hashes[pair & mask])
    ones, twos = automaton.ones, keyed(automaton.twos)
    automaton.weight[1 : 1 + len(ones)] = of_word[ones]
    automaton.weight[1 + len(ones) :] = _at(k2, w2, twos)
    of_word[ones] = 0
    first, last = automaton.triples >> BITS, (automaton.triples >> BITS & mask) << BITS | automaton.triples & mask
    lacks2 = np.where(np.isin(k2, keyed(automaton.pairs)), 0, gain2) + np.where(np.isin(k2, twos), 0, w2)
    lacks3 = np.where(np.isin(k3, mixed(keyed(first), keyed(last))), 0, gain3)
    keys, terms = np.concatenate([k2, k3]), np.concatenate([lacks2, lacks3])
    order = np.argsort(keys)
    order = order[terms[order] != 0]
    return Rest(float(of_word[-1]), of_word[:-1], keys[order], terms[order], np.zeros(0, np.uint64))


def rare_terms(learned: Learned, counts: DataFrame, buckets: int) -> DataFrame:
    """Packed terms of the words without a number and of the n-grams that are looked up; a key may have several."""
    vocabulary = learned.vocabulary
    numbered, least = _thresholds(vocabulary.total)
    total, distinct = float(vocabulary.total), float(vocabulary.distinct)

    def packed(k: np.ndarray, term: np.ndarray, base: np.ndarray | None = None) -> pa.RecordBatch:
        order, found = grams.slices(grams.buckets_of(k, buckets))
        k, term, base = k[order], term[order], None if base is None else base[order]
        return pa.RecordBatch.from_arrays(_packed([(b, TERMS, k[i:j].tobytes(), term[i:j].tobytes(), b"" if base is None else base[i:j].tobytes()) for b, i, j in found]), names=NAMES)

    def of_arcs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for kind, columns in grams.together(batches):
            k, term = columns[0], columns[-1].view(np.float64)
            if kind == grams.ROWS:
                some = columns[1].view(np.int64) < least
                k, term = k[some], term[some]
            if len(k):
                yield packed(k, term)

    def of_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                base = np.log10((batch.column(1).to_numpy() + 0.5) / (total + 0.5 * (distinct + 1)))
                yield packed(batch.column(0).to_numpy().view(np.uint64), base, base)

    cold = counts.filter(F.col("c") < numbered).select("w", "c")
    found = [cold.mapInArrow(of_words, PACKED), *(x.arcs.mapInArrow(of_arcs, PACKED) for x in (learned.pairs, learned.triples))]
    return grams.stored(found[0].unionByName(found[1]).unionByName(found[2]), "rare-terms")


def _marked(terms: DataFrame) -> np.ndarray:
    """A filter of the keys of packed terms of n-grams (which have no bases)."""
    rows = terms.filter(F.length("z") == 0).select("bucket", "kind", (F.length("x") / 8).cast("int").alias("n"), F.col("x").alias("d"))
    return grams.marks_of(rows, RARE_BITS, lambda columns: columns[0])


def build(train: DataFrame, text: str, counts: DataFrame) -> tuple[Vocabulary, Automaton]:
    """The numbered words, and the automaton of the n-grams of numbered words that are frequent enough."""
    learned = learn(train, text, counts)
    return learned.vocabulary, learned.automaton


def _automaton(vocabulary: Vocabulary, pairs: tuple[np.ndarray, ...], triples: tuple[np.ndarray, ...], texts: int) -> Automaton:
    """The automaton of the frequent pairs and triples (left, right, count) that consist of numbered words."""

    def packed(a: np.ndarray, b: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = a << BITS | b
        order = np.argsort(key)
        return key[order], c[order]

    a, b, c2 = pairs
    k = mixed(a, b)
    left = np.where(a == START, vocabulary.start, vocabulary.numbers(a))
    right = vocabulary.numbers(b)
    held = (left >= 0) & (right >= 0)
    k, left, right, c2 = k[held], left[held], right[held], c2[held]
    by_key = np.argsort(k)

    def pair_of(key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places of pairs (any, where there is none), and whether they are held."""
        if not len(k):
            return np.zeros(len(key), np.int64), np.zeros(len(key), bool)
        at = by_key[np.minimum(np.searchsorted(k, key, sorter=by_key), len(k) - 1)]
        return at, k[at] == key

    a, b, c3 = triples
    (i, first), (j, second) = pair_of(a), pair_of(b)
    both = first & second
    i, j, c3 = i[both], j[both], c3[both]
    return Automaton(vocabulary, packed(left, right, c2), packed(left[i] << BITS | right[i], right[j], c3), texts)


def score_documents(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, held_out, n_tokens, n_known, train_tokens, base_score, score of every document."""
    held = lambda k: F.coalesce(F.crc32(F.col(k).cast("string").cast("binary")) % FOLDS == HELD_OUT, F.lit(False))
    train = docs.filter(~held(key))
    counts = saved(word_counts(train, text), "word-counts")
    learned = learn(train, text, counts)
    vocabulary, automaton = learned.vocabulary, learned.automaton
    lacking = complete(learned)
    n, v = float(vocabulary.total), float(vocabulary.distinct)
    unseen = float(np.log10(0.5 / (n + 0.5 * (v + 1))))
    rare = vocabulary.distinct + sum(grams.rows_of(x.arcs) for x in (learned.pairs, learned.triples))
    buckets = max(2 * docs.sparkSession.sparkContext.defaultParallelism, -(-rare // BUCKET_KEYS))
    terms = rare_terms(learned, counts, buckets)
    discard(learned.pairs.arcs, learned.triples.arcs, counts)
    lacking.others = _marked(terms)
    model = docs.sparkSession.sparkContext.broadcast((vocabulary, automaton, lacking))
    found = []
    for turn in range(TURNS):
        parts = parts_of_scores(docs, key, text, model, turn, buckets)
        rows = summed_terms(parts.unionByName(terms, allowMissingColumns=True), key, buckets, unseen)
        found.append(saved(rows.groupBy("row").agg(F.max(key).alias(key), *(F.sum(c).alias(c) for c in ("n_tokens", "n_known", "base_score", "score"))).drop("row"), "scores"))
    discard(terms)
    summed = reduce(DataFrame.unionByName, found)
    return summed.select(key, held(key).alias("held_out"), "n_tokens", "n_known", F.lit(int(n)).cast("long").alias("train_tokens"), "base_score", "score")


#: Kinds of packed rows: terms of keys, n-grams of documents, words of documents.
TERMS, GRAMS, WORDS = 0, 1, 2
PACKED = "bucket int, kind int, x binary, y binary, z binary"
NAMES = ["bucket", "kind", "x", "y", "z"]
#: Keys of terms that one bucket holds (24 bytes each).
BUCKET_KEYS = 1_000_000


def _packed(rows: list[tuple[int, int, bytes, bytes, bytes]]) -> list[pa.Array]:
    bucket, kind, *data = zip(*rows, strict=True)
    return [pa.array(bucket, pa.int32()), pa.array(kind, pa.int32()), *(pa.array(d, pa.binary()) for d in data)]


def summed_terms(parts: DataFrame, key: str, buckets: int, unseen: float) -> DataFrame:
    """Partial sums by row: a document's own row as it is, and for each packed row of its n-grams or
    words what their terms add. A bucket's terms come first, then its packed rows one after another."""
    own = [key, "n_tokens", "n_known", "base_score", "score"]
    schema = T.StructType([parts.schema["row"], *(parts.schema[c] for c in own)])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at_bucket, held, table = -1, [], None
        for batch in batches:
            kinds = batch.column("kind")
            plain = batch.filter(kinds.is_null())
            if plain.num_rows:
                yield plain.select(schema.names)
            packed = batch.filter(kinds.is_valid()).select(NAMES)
            found = []
            for i in range(packed.num_rows):
                bucket, kind = packed.column(0)[i].as_py(), packed.column(1)[i].as_py()
                x, y, z = (packed.column(c)[i].as_buffer() for c in (2, 3, 4))
                if bucket != at_bucket:
                    at_bucket, held, table = bucket, [], None
                if kind == TERMS:
                    k = np.frombuffer(x, np.uint64).copy()
                    held.append([k, np.frombuffer(y).copy(), np.frombuffer(z).copy() if z.size else np.zeros(len(k))])
                    continue
                if table is None:
                    table = [np.concatenate(c) for c in zip(*held, strict=True)] if held else [np.zeros(0, np.uint64), np.zeros(0), np.zeros(0)]
                    order = np.argsort(table[0])
                    k, term, base = (c[order] for c in table)
                    starts = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]])) if len(k) else np.zeros(0, np.int64)
                    table, held = [k[starts], *(np.add.reduceat(c, starts) if len(k) else c for c in (term, base))], []
                found.append(_summed(*table, kind, np.frombuffer(x, np.int64), np.frombuffer(y, np.int32), np.frombuffer(z, np.uint64), unseen))
            if found:
                row, known, base, score = (np.concatenate(c) for c in zip(*found, strict=True))
                out = [pa.array(row), pa.nulls(len(row), plain.schema.field(key).type), pa.array(np.zeros(len(row), np.int64)), pa.array(known), pa.array(base), pa.array(score)]
                yield pa.RecordBatch.from_arrays(out, names=schema.names)

    # a document's own row lies anywhere, packed rows with their bucket
    return parts.repartition(buckets, F.coalesce(F.col("bucket"), F.col("row"))).sortWithinPartitions("bucket", "kind").mapInArrow(scan, schema)


def _summed(keys: np.ndarray, terms: np.ndarray, bases: np.ndarray, kind: int, row: np.ndarray, sizes: np.ndarray, wanted: np.ndarray, unseen: float) -> tuple[np.ndarray, ...]:
    """Rows, and their sums of known words, base and score, over the wanted keys of each row."""
    first = np.cumsum(sizes) - sizes
    at = np.minimum(np.searchsorted(keys, wanted), max(len(keys) - 1, 0))
    hit = keys[at] == wanted if len(keys) else np.zeros(len(wanted), bool)
    term = np.zeros(len(wanted))
    term[hit] = terms[at[hit]]
    if kind == GRAMS:
        none = np.zeros(len(row))
        return row, none.astype(np.int64), none, np.add.reduceat(term, first)
    base = np.full(len(wanted), unseen)
    base[hit], term[~hit] = bases[at[hit]], unseen
    return row, np.add.reduceat(hit.astype(np.int64), first), np.add.reduceat(base, first), np.add.reduceat(term, first)


def parts_of_scores(docs: DataFrame, key: str, text: str, model: Broadcast, turn: int, buckets: int) -> DataFrame:
    """From one scan: a row of each document of a turn, with what the automaton gives it, and packed rows of the
    words without a number and of the n-grams that may be among the others: rows, sizes, keys."""
    own = T.StructType([T.StructField("row", T.LongType()), T.StructField(key, docs.schema[key].dataType), *(T.StructField(c, T.LongType()) for c in ("n_tokens", "n_known")), *(T.StructField(c, T.DoubleType()) for c in ("base_score", "score"))])
    packed = T.StructType([T.StructField("bucket", T.IntegerType()), T.StructField("kind", T.IntegerType()), *(T.StructField(c, T.BinaryType()) for c in "xyz")])
    schema = T.StructType([*own, *packed])
    arrow = [pa.int32(), pa.int32(), *[pa.binary()] * 3]

    def bundled(held: list[tuple[int, np.ndarray, np.ndarray]], key_type: pa.DataType) -> pa.RecordBatch:
        found = []
        for kind in (GRAMS, WORDS):
            mine = [(r, k) for x, r, k in held if x == kind]
            if not mine:
                continue
            row, k = (np.concatenate(c) for c in zip(*mine, strict=True))
            by_row = np.argsort(row, kind="stable")
            row, k = row[by_row], k[by_row]
            order, ranges = grams.slices(grams.buckets_of(k, buckets))
            row, k = row[order], k[order]
            for bucket, i, j in ranges:
                of = row[i:j]
                first = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]]))
                found.append((bucket, kind, of[first].tobytes(), np.diff(np.append(first, len(of))).astype(np.int32).tobytes(), k[i:j].tobytes()))
        nothing = [pa.nulls(len(found), t) for t in (pa.int64(), key_type, pa.int64(), pa.int64(), pa.float64(), pa.float64())]
        return pa.RecordBatch.from_arrays([*nothing, *_packed(found)], names=schema.names)

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, automaton, lacking = model.value
        held, size, key_type = [], 0, None
        for batch in batches:
            at_row, key_type = batch.column(0).to_numpy(), batch.column(1).type
            for x, y, tokens, first in token_blocks(batch.column(2)):
                row = at_row[x:y]
                words = vocabulary.numbers(tokens)
                known = words >= 0
                owner = np.repeat(np.arange(y - x), np.diff(first))
                _, _, k2 = _pairs_of(tokens, first)
                at3 = _triples_of(k2, first)
                k3 = mixed(k2[at3 - 1], k2[at3])
                gained = _at(lacking.keys, lacking.terms, k2) + np.where(known, np.append(lacking.words, 0.0)[words], 0.0)
                gained[at3] += _at(lacking.keys, lacking.terms, k3)
                unigram = np.where(known, automaton.root_log[np.maximum(words, 0)] if len(automaton.root_log) else 0.0, 0.0)
                walk = automaton.traverse(words, first) + np.add.reduceat(gained, first[:-1]) + lacking.start
                counted = (np.diff(first), np.add.reduceat(known.astype(np.int64), first[:-1]), np.add.reduceat(unigram, first[:-1]), walk)
                nothing = [pa.nulls(len(row), t) for t in arrow]
                yield pa.RecordBatch.from_arrays([pa.array(row), batch.column(1).slice(x, y - x), *map(pa.array, counted), *nothing], names=schema.names)
                in2, in3 = np.flatnonzero(passes(lacking.others, k2)), np.flatnonzero(passes(lacking.others, k3))
                cold = np.flatnonzero(~known)
                held += [(GRAMS, row[owner[in2]], k2[in2]), (GRAMS, row[owner[at3[in3]]], k3[in3]), (WORDS, row[owner[cold]], tokens[cold])]
                size += len(in2) + len(in3) + len(cold)
                if size > TOGETHER:
                    yield bundled(held, key_type)
                    held, size = [], 0
        if size:
            yield bundled(held, key_type)

    # by key: a row has the same turn however often its table is read
    mine = docs.filter(F.pmod(F.xxhash64(F.col(key).cast("string")), F.lit(TURNS)) == turn)
    return mine.select(F.monotonically_increasing_id().alias("row"), F.col(key), F.col(text)).mapInArrow(scan, schema)
