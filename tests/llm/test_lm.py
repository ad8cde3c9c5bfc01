import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from gridknn.llm import lm

LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def words(text):
    return re.findall("[^\x20\x09-\x0d]+", (text or "").translate(LOW)) + [None]


def held(k):
    return k is not None and zlib.crc32(str(k).encode()) % 5 == 1


def base(rows):
    c = Counter(w for k, t in rows if not held(k) for w in words(t))
    n, v = sum(c.values()), len(c)
    return c, {i: (held(k), len(words(t)), sum(c[w] > 0 for w in words(t)), n, sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in words(t))) for i, (k, t) in enumerate(rows)}


def corpus(n=120):
    rng = random.Random(8)
    texts = [None, "", " \n", "Only ONCE-held words", "tie tie tie"]
    while len(texts) < n:
        texts.append(" ".join(rng.choice(["the cat sat on the mat", "a dog ran", f"rare{rng.randint(0, 200)}", "Über é"]) for _ in range(rng.randint(0, 30))))
    return list(enumerate(texts))


def collect(spark, rows):
    frame = spark.createDataFrame([(k, t, 1, "x") for k, t in rows], "doc_id long, text string, row int, w string")
    return lm.score_documents(frame).collect()


@pytest.mark.parametrize("share,context", [(1e-6, 1e-5), (0.01, 0.01), (0.3, 0.3), (2.0, 2.0)])
def test_base_counts(spark, monkeypatch, share, context):
    monkeypatch.setattr(lm, "SHARE", share)
    monkeypatch.setattr(lm, "CONTEXT_SHARE", context)
    rows = corpus()
    _, want = base(rows)
    out = collect(spark, rows)
    assert len(out) == len(rows)
    for r in out:
        h, n, known, total, score = want[r.doc_id]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (h, n, known, total)
        assert r.base_score == pytest.approx(score, abs=1e-8)
    if share < 0.1:
        assert sum(r.score for r in out if r.held_out) > sum(r.base_score for r in out if r.held_out)


def test_each_state_sums_to_one(spark, monkeypatch):
    monkeypatch.setattr(lm, "CONTEXT_SHARE", 0.005)
    rows = corpus()
    frame = spark.createDataFrame([r for r in rows if not held(r[0])], "doc_id long, text string")
    vocabulary, automaton = lm.build(frame, "text", lm.word_counts(frame, "text"))
    unseen = 0.5 / (vocabulary.total + 0.5 * (vocabulary.distinct + 1))
    everything = np.arange(len(vocabulary.hashes))
    assert len(automaton.fail) > 10 and (automaton.fail > 0).any()
    for state in range(len(automaton.fail)):
        _, score = automaton.step(np.full(len(everything), state), everything)
        _, cold = automaton.step(np.array([state]), np.array([lm.COLD]))
        assert (10**score).sum() + unseen * 10 ** cold[0] == pytest.approx(1, abs=1e-9)


@pytest.mark.parametrize("stretch", [2, 5, 128])
def test_traversal_equals_word_by_word(spark, monkeypatch, stretch):
    monkeypatch.setattr(lm, "CONTEXT_SHARE", 0.005)
    monkeypatch.setattr(lm, "STRETCH", stretch)
    rows = corpus(40)
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    vocabulary, automaton = lm.build(frame, "text", lm.word_counts(frame, "text"))
    rng = np.random.default_rng(1)
    sizes = rng.integers(1, 30, 50)
    w = rng.integers(-1, len(vocabulary.hashes), sizes.sum())
    first = np.concatenate([[0], np.cumsum(sizes)])
    for i, got in enumerate(automaton.traverse(w, first)):
        state, total = np.array([automaton.begin]), 0.0
        for x in w[first[i] : first[i + 1]]:
            state, s = automaton.step(state, np.array([x]))
            total += s[0]
        assert got == pytest.approx(total)


@pytest.mark.parametrize("share,context", [(1e-6, 1e-5), (0.002, 0.01), (2.0, 2.0)])
def test_every_repeated_ngram_counts(spark, monkeypatch, share, context):
    """Scores are those of the model of all n-grams that occur twice, however few of them the automaton holds."""
    monkeypatch.setattr(lm, "SHARE", share)
    monkeypatch.setattr(lm, "CONTEXT_SHARE", context)
    rows = corpus()
    c1, c2, c3 = Counter(), Counter(), Counter()
    for k, t in rows:
        if not held(k):
            w = ["<s>", *words(t)]
            c1.update(w)
            c2.update(zip(w, w[1:], strict=False))
            c3.update(zip(w, w[1:], w[2:], strict=False))
    n, v = sum(c1.values()) - c1["<s>"], len(c1) - 1
    c2, c3 = ({g: c for g, c in x.items() if c >= 2} for x in (c2, c3))
    p1 = lambda c: (c1[c] + 0.5) / (n + 0.5 * (v + 1))

    def p2(b, c):
        if (b, c) in c2:
            return (c2[b, c] - 0.5) / c1[b]
        arcs = [g[1] for g in c2 if g[0] == b]
        return p1(c) * (1 - sum(p2(b, x) for x in arcs)) / (1 - sum(map(p1, arcs)))

    def p3(a, b, c):
        if (a, b, c) in c3:
            return (c3[a, b, c] - 0.5) / c2[a, b]
        arcs = [g[2] for g in c3 if g[:2] == (a, b)]
        return p2(b, c) * (1 - sum(p3(a, b, x) for x in arcs)) / (1 - sum(p2(b, x) for x in arcs))

    for r in collect(spark, rows):
        w = ["<s>", *words(dict(rows)[r.doc_id])]
        want = math.log10(p2(*w[:2])) + sum(math.log10(p3(*g)) for g in zip(w, w[1:], w[2:], strict=False))
        assert r.score == pytest.approx(want, abs=1e-7), w


def test_odd_tables(spark):
    assert collect(spark, []) == []
    only_held = [(k, "a b") for k in range(200) if held(k)][:3]
    assert [(r.n_known, r.train_tokens, r.base_score, r.score) for r in collect(spark, only_held)] == [(0, 0, 0.0, 0.0)] * 3
    twice = collect(spark, [(0, "a b"), (0, "a b"), (None, "a")])
    assert len(twice) == 3 and {r.train_tokens for r in twice} == {8}
