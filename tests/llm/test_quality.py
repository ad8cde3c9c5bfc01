import random
import zlib

import numpy as np
import pyarrow as pa
from gridknn.llm import quality as q
from gridknn.llm import textscan as ts


def corpus(n=240):
    rng = random.Random(4)
    word = lambda: "".join(rng.choices("abcdefgh", k=rng.randint(2, 7)))
    rows = []
    for i in range(n):
        good = rng.random() < 0.6
        rows.append((i, " ".join(word() if good else word().upper() + "!!" for _ in range(rng.randint(5, 300))), int(good)))
    return rows


def test_held_out_accuracy_and_odd_rows(spark):
    rows = corpus()
    docs = spark.createDataFrame([(i, t, "s") for i, t, _ in rows] + [(1000, None, "s"), (1001, "", "s"), (3, rows[3][1], "s"), (None, "x", "s")], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(i, y) for i, _, y in rows if i % 5], "doc_id long, quality int")
    out = q.score_quality(docs, labels).collect()
    assert len(out) == len(rows) + 4
    got = {r.doc_id: r for r in out}
    truth = {i: y for i, _, y in rows}
    held = [i for i in truth if zlib.crc32(str(i).encode()) % 4 == 2]
    assert all(got[i].held_out == (i in held) for i in truth)
    assert sum(got[i].predicted == truth[i] for i in held) > 0.95 * len(held)
    assert got[1000].score == got[1001].score and all(0 <= r.score <= 1 for r in out)
    kept = q.keep_quality(docs, docs, labels)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {r.doc_id for r in out if r.predicted}


def test_held_out_labels_change_nothing(spark):
    rows = corpus(80)
    docs = spark.createDataFrame([(i, t) for i, t, _ in rows], "doc_id long, text string")
    held = lambda i: zlib.crc32(str(i).encode()) % 4 == 2
    a = spark.createDataFrame([(i, y) for i, _, y in rows], "doc_id long, quality int")
    b = spark.createDataFrame([(i, 1 - y if held(i) else y) for i, _, y in rows], "doc_id long, quality int")
    assert q.score_quality(docs, a).collect() == q.score_quality(docs, b).collect()


def test_score_sees_every_byte_and_not_its_neighbours():
    rng = np.random.default_rng(1)
    net = q.Network(rng.normal(size=(q.WIDTH, 256, q.FILTERS)).astype(np.float32), np.zeros(q.FILTERS, np.float32), rng.normal(size=2 * q.FILTERS + 1).astype(np.float32))
    texts = ["", "a", "x" * 127, "x" * 128, "x" * 129, "y" * 5000, "z" * 300_000 + "end"]
    together = net.score(*ts.buffers(pa.array(texts)))
    assert np.allclose(together, [net.score(*ts.buffers(pa.array([t])))[0] for t in texts])


def test_no_labels_and_empty_tables(spark):
    docs = spark.createDataFrame([(1, "a"), (2, "b")], "doc_id long, text string")
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert {r.score for r in q.score_quality(docs, none).collect()} == {0.5}
    assert q.score_quality(docs.limit(0), none).collect() == []
