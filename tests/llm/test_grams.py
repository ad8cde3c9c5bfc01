from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from gridknn.llm import grams, lm

TEXTS = [None, "a b a b a b c", "", "x", " ".join(f"w{i % 7}" for i in range(60)), "a b", *(f"p{i} a b q{i % 3}" for i in range(20))]


def hashed(texts):
    """Each word's hash, by the module's own scan."""
    found = {}
    for _, _, tokens, first in grams.token_blocks(pa.array(texts)):
        for i, text in enumerate(texts):
            found.update(zip((text or "").split(), tokens[first[i] : first[i + 1]].tolist(), strict=False))
    return found


@pytest.mark.parametrize("together", [3, 7, 50, 1000])
@pytest.mark.parametrize("size", [2, 3])
def test_counted_pieces_equal_brute_force(monkeypatch, together, size):
    """Also of rows longer than what is counted together."""
    monkeypatch.setattr(grams, "TOGETHER", together)
    name = hashed(TEXTS)
    want = Counter()
    for text in TEXTS:
        w = [int(grams.START), *(name[x] for x in (text or "").split()), int(grams.END)]
        want.update(zip(*(w[i:] for i in range(size)), strict=False))
    got = Counter()
    batches = [pa.RecordBatch.from_arrays([pa.array(TEXTS[i : i + 9])], names=["text"]) for i in range(0, len(TEXTS), 9)]
    everything = np.full(1 << 4, (1 << 64) - 1, np.uint64)
    for tokens, depth, before in grams._pieces(iter(batches)):
        assert len(tokens) <= together + 2
        hashes, at, c = grams._counted(tokens, depth, before, None if size == 2 else everything)
        for *words, n in zip(*(hashes[x].tolist() for x in at), c.tolist(), strict=True):
            got[tuple(words)] += n
    assert got == want


def test_packed_rows_keep_every_value(monkeypatch):
    monkeypatch.setattr(grams, "ROW_VALUES", 3)
    monkeypatch.setattr(grams, "BATCH_ROWS", 2)
    monkeypatch.setattr(grams, "DEALT_VALUES", 5)
    k = grams.mixed(np.arange(40, dtype=np.uint64), np.arange(40, dtype=np.uint64))
    bucket = grams.buckets_of(k, 4)
    rows = list(grams._batches(grams._dealt(bucket, grams.ROWS, k, np.arange(40))))
    assert all(r.num_rows <= 2 for r in rows)
    for b, met in grams._buckets_met(iter(rows)):
        assert sorted(met[grams.ROWS][1].tolist()) == np.flatnonzero(bucket == b).tolist()
    seen = [columns for _, columns in grams.together(iter(rows))]
    assert sorted(np.concatenate(seen, axis=1)[1].tolist()) == list(range(40)) and len(seen) > 1


def shuffled_records(spark):
    """Records that all stages so far wrote to shuffles."""
    stages = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
    return sum(stages.apply(i).shuffleWriteRecords() for i in range(stages.size()))


def test_ngrams_are_not_shuffled_one_by_one(spark):
    """Packed arrays are: a row for each n-gram, sorted and joined again and again, was most of the time."""
    rng = np.random.default_rng(3)
    rows = [(i, " ".join(f"w{x}" for x in rng.zipf(1.3, 300) % 3000)) for i in range(100)]
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(2)
    before = shuffled_records(spark)
    assert len(lm.score_documents(frame).collect()) == 100
    tokens, words = 100 * 301, len({w for _, t in rows for w in t.split()})
    assert shuffled_records(spark) - before < tokens / 2 + 2 * words
