import random
import tracemalloc
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from gridknn.llm import components as cc
from gridknn.llm import jaccard as jc

BLANK = " \t\n\x0b\x0c\r"
LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def shingles(text):
    words, word = [], ""
    for ch in (text or "").translate(LOW) + " ":
        if ch in BLANK:
            words += [word] if word else []
            word = ""
        else:
            word += ch
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def brute(rows):
    sets = [shingles(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both and 100 * both >= 75 * len(sets[i] | sets[j]):
                root[find(i)] = find(j)
    least = {}
    for i, (k, _) in enumerate(rows):
        if k is not None:
            least[find(i)] = min(least.get(find(i), k), k)
    return sorted(((k, len(sets[i]), least.get(find(i))) for i, (k, _) in enumerate(rows)), key=str)


def corpus(seed, n=150):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(400)]
    passage = rng.choices(vocabulary, k=60)
    texts = [None, "", "  \t", "one", "One", "one two three", "one two three", "a b c d e", "é ü ö ä ß", "a b c d e f"]
    while len(texts) < n:
        words = rng.choices(vocabulary, k=rng.randint(3, 90))
        if rng.random() < 0.4:
            words += passage
        for _ in range(rng.choice([1, 1, 2, 6])):
            copy = list(words)
            for _ in range(rng.randint(0, 4)):
                copy[rng.randrange(len(copy))] = rng.choice(vocabulary)
            texts.append(rng.choice([" ", "\n", "  "]).join(copy[: rng.randint(max(1, len(copy) - 9), len(copy))]))
    return list(enumerate(texts))


def got(spark, rows):
    frame = spark.createDataFrame([(k, t, 1, 2) for k, t in rows], "doc_id long, text string, n int, cid int")
    return sorted(((r.doc_id, r.n_shingles, r.component_id) for r in jc.jaccard_components(frame).collect()), key=str)


@pytest.mark.parametrize("seed", [1, 2])
def test_matches_brute_force(spark, seed):
    rows = corpus(seed)
    rows += [(rows[20][0], rows[20][1]), (None, rows[30][1]), (None, None)]
    assert got(spark, rows) == brute(rows)


def test_links_survive_without_hints(spark, monkeypatch):
    """No groups and no frequent tokens: the matrix alone finds every link."""
    monkeypatch.setattr(jc, "HOPEFUL", 2.0)
    monkeypatch.setattr(jc, "HEAVY_LEAST", 10**9)
    rows = corpus(3)
    assert got(spark, rows) == brute(rows)


def test_empty_table(spark):
    assert got(spark, []) == []


def test_representatives(spark):
    rows = corpus(4, 80)
    frame = spark.createDataFrame([(k, t, "s") for k, t in rows], "doc_id long, text string, source string")
    kept = jc.keep_representatives(frame)
    assert kept.columns == frame.columns
    assert sorted(r.doc_id for r in kept.collect()) == sorted(k for k, _, c in brute(rows) if k == c)


def test_components_of_a_path_and_a_star(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 30)] + [(500, 501)]
    random.Random(5).shuffle(edges)
    out = {r.node: r.label for r in cc.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert {out[i] for i in range(41)} == {0} and {out[100 + i] for i in range(30)} == {100} and out[501] == 500


class Steps:
    """Stands for a table: keeps the functions that go over its batches."""

    def __init__(self):
        self.found = []

    def __getattr__(self, name):
        def step(*args):
            if name == "mapInArrow":
                self.found.append(args[0])
            return self

        return step


def test_token_totals_hold_few_copies(monkeypatch):
    """Workers count tokens in place, and no batch holds more than a slice's part."""
    monkeypatch.setattr(jc, "TOGETHER", 400_000)
    monkeypatch.setattr(jc, "SLICE_TOKENS", 10**7)
    rng = np.random.default_rng(6)
    pool = rng.integers(0, 1 << 64, 600_000, dtype=np.uint64)
    sets = [np.sort(rng.choice(pool, 50_000, replace=False)) for _ in range(40)]
    sets.append(np.sort(rng.choice(pool, 450_000, replace=False)))

    def blocks(column):
        for i in range(len(column)):
            at = column[i].as_py()
            yield 0, 1, sets[at], np.array([0, len(sets[at])]), np.array([at + 1])

    monkeypatch.setattr(jc, "_set_blocks", blocks)
    steps = Steps()
    jc.token_totals(steps, "text", 0)
    scan, merge = steps.found

    def measured(run, batches):
        tracemalloc.start()
        out, most = [], 0
        for batch in run(batches):
            out.append(batch)
            most = max(most, tracemalloc.get_traced_memory()[1])
        tracemalloc.stop()
        return out, most

    sliced, most = measured(scan, [pa.RecordBatch.from_arrays([pa.array([i])], names=["text"]) for i in range(len(sets))])
    assert most < 5 * 8 * 450_000
    assert all(b.num_rows == 1 for b in sliced)
    lots = sorted(sliced, key=lambda b: b.column(0)[0].as_py())
    totals, _ = measured(merge, lots)
    assert max(b.num_rows for b in totals) <= 2 * jc.SUMMED
    values, counts = np.unique(np.concatenate(sets), return_counts=True)
    got_counts = Counter({t & (1 << 64) - 1: n for b in totals for t, n in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)})
    assert got_counts == Counter(dict(zip(values[counts > 1].tolist(), counts[counts > 1].tolist(), strict=True)))


def test_loose_cluster_does_not_leave_the_matrix_pair_by_pair(spark, monkeypatch):
    """Sets that are just alike enough link many times over; a few links each make them a group."""
    rng = random.Random(7)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for k in range(240):
        words = list(base)
        for i in rng.sample(range(20, 100), 2):
            words[i] = f"x{k}-{i}"
        rows.append((k, " ".join(words)))
    met, real = [], jc.qualifying

    def counted(*args):
        out = jc.saved(real(*args), "counted")
        met.append(out.count())
        return out

    monkeypatch.setattr(jc, "qualifying", counted)
    assert got(spark, rows) == brute(rows)
    assert sum(met) < 10 * len(rows)
