import random
import zlib

import numpy as np
from gridknn.llm import packing as pk
from gridknn.llm.wordbpe import opened, public_path


def by_document(lengths, capacity):
    """Best-fit decreasing with a plain scan; the number of bins."""
    bins = []
    for n in sorted(lengths, reverse=True):
        fits = [(r, i) for i, r in enumerate(bins) if r >= n]
        if fits:
            bins[min(fits)[1]] -= n
        else:
            bins.append(capacity - n)
    return len(bins)


def test_plan_equals_best_fit_by_document():
    rng = random.Random(1)
    for _ in range(60):
        capacity = rng.choice([1, 7, 32, 100])
        lengths = [rng.randint(1, capacity) for _ in range(rng.randint(1, 150))]
        if rng.random() < 0.5:
            lengths += [rng.randint(1, capacity)] * rng.randint(1, 80)
        hist = {n: lengths.count(n) for n in set(lengths)}
        plan = pk.best_fit_plan(hist, capacity)
        bins = {}
        for length, _, n, per, first, offset in plan.tolist():
            for j in range(n):
                bins.setdefault(first + j // per, []).append((offset + j % per * length, length))
        assert len(bins) == by_document(lengths, capacity)
        assert sum(len(b) for b in bins.values()) == len(lengths)
        for b in bins.values():
            at = 0
            for offset, n in sorted(b):
                assert offset == at
                at += n
            assert at <= capacity


def test_tree_finds_the_tightest():
    rng, tree, held = random.Random(2), pk.RemainingTree(50), []
    for _ in range(400):
        if held and rng.random() < 0.4:
            tree.add(x := held.pop(rng.randrange(len(held))), -1)
        else:
            held.append(x := rng.randint(0, 50))
            tree.add(x)
        need = rng.randint(0, 50)
        assert tree.tightest(need) == min((h for h in held if h >= need), default=None)


ODD = ["", None, "don't stop's ÀÉ'll 12345 a1b2 <|endoftext|> x<|y>", "ΣΑΣ ﬁ 日本語 😀 \x1cx", "aaaa " * 9000, "x" * 300, "Hello,World!!... ’s", "twice", "twice"]


def test_pieces_and_places(spark):
    docs = spark.createDataFrame([(i, t, "x", 1) for i, t in enumerate(ODD)] + [(8, "twice", "x", 1)], "doc_id long, text string, length string, piece int")
    rows = pk.pack_documents(docs).collect()
    reference = opened(public_path()).tokenizer
    want = {}
    for i, t in enumerate(ODD):
        ids = [*reference.encode(t or "", add_special_tokens=False).ids, 1]
        for p in range(0, len(ids), 4096):
            part = ids[p : p + 4096]
            want[(i, p // 4096)] = (p, len(part), zlib.crc32(np.array(part, "<u4").tobytes()))
    assert {(r.doc_id, r.piece): (r.start, r.length, r.ids_crc32) for r in rows} == want
    assert len(rows) == len(want) + 1
    used = {}
    for r in rows:
        used.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for spans in used.values():
        spans.sort()
        assert spans[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(spans, spans[1:], strict=False))
        assert sum(n for _, n in spans) <= 4096
    assert len(used) == by_document([r.length for r in rows], 4096)


def test_sequences_hold_the_ids(spark):
    docs = spark.createDataFrame([(i, "some words here " * i) for i in range(40)], "doc_id long, text string")
    got = pk.sequences(docs, capacity=64).collect()
    assert all(len(r.ids) == sum(p.length for p in r.pieces) <= 64 for r in got)
    assert sum(r.ids.count(1) for r in got) == 40


def test_empty_table(spark):
    assert pk.pack_documents(spark.createDataFrame([], "doc_id long, text string")).collect() == []
