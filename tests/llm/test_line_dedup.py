import hashlib
import random

from gridknn.llm import line_dedup as ld

BLANK = " \t\n\x0b\x0c\r"
LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def brute(rows):
    key = lambda line: line.strip(BLANK).translate(LOW)
    holders, largest = {}, {}
    for i, t in rows:
        for k in {key(x) for x in (t or "").split("\n")}:
            holders[k] = holders.get(k, 0) + 1
            if i is not None:
                largest[k] = max(largest.get(k, i), i)
    out = []
    for i, t in rows:
        lines = (t or "").split("\n")
        gone = lambda k: len(k) >= 20 and holders[k] >= 3 and i is not None and i < largest[k]
        kept = [x for x in lines if not gone(key(x))]
        out.append((i, len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out, key=str)


def table(seed=1, n=120):
    rng = random.Random(seed)
    pool = ["  The same Line of twenty characters ", "the SAME line of twenty characters", "ÄÖÜäöü" * 4, "short", "", "\t\t", "x" * 19, "y" * 20, "é" * 19, "wholly common line, everywhere in the table"] + [f"line number {j} with enough characters" for j in range(60)]
    return [(i, rng.choice([None, "", "\n\n", "\n".join(rng.choices(pool, k=rng.randint(1, 12)))]) if rng.random() < 0.2 else "\n".join(rng.choices(pool, k=rng.randint(1, 12)))) for i in range(n)]


def got(spark, rows, **options):
    frame = spark.createDataFrame([(i, t, 0, "z") for i, t in rows], "doc_id long, text string, h1 int, batch string")
    return sorted(((r.doc_id, r.n_lines, r.n_dropped, r.kept_sha256) for r in ld.line_dedup_report(frame, **options).collect()), key=str)


def test_matches_brute_force(spark):
    rows = table() + [(5, "y" * 20), (5, "y" * 20), (None, "y" * 20), (None, None)]
    assert got(spark, rows) == brute(rows)


def test_heavy_keys_and_compaction(spark, monkeypatch):
    monkeypatch.setattr(ld, "HEAVY_LEAST", 10)
    rows = table(2)
    assert got(spark, rows, batches=5, fanout=2) == brute(rows)


def test_empty_table(spark):
    assert got(spark, []) == []


def test_rewritten_documents(spark):
    rows = table(3, 60)
    frame = spark.createDataFrame([(i, t, len(t or ""), "z") for i, t in rows], "doc_id long, text string, n_chars long, gone string")
    out = {r.doc_id: r for r in ld.dedup_lines(frame).collect()}
    assert [c for c in ld.dedup_lines(frame).columns] == frame.columns
    want = {i: h for i, _, _, h in brute(rows)}
    texts = dict(rows)
    for i, r in out.items():
        assert hashlib.sha256((r.text or "").encode()).hexdigest() == want[i] and r.gone == "z"
        assert r.n_chars == len(r.text or "") and (r.text is None) == (texts[i] is None)


def test_unseen_lines_of_a_new_batch(spark):
    store = ld.LineRuns(spark, fanout=2)
    holders = {}
    for b in range(4):
        rows = [(100 * b + i, t) for i, t in table(10 + b, 20)]
        keys = ld.line_keys(spark.createDataFrame(rows, "doc_id long, text string"))
        mine = [(r.h1, r.h2, r.doc_id) for r in keys.collect()]
        assert {(r.h1, r.h2) for r in store.unseen(keys).collect()} == {x[:2] for x in mine} - holders.keys()
        store.add(keys)
        for *k, i in mine:
            holders.setdefault(tuple(k), []).append(i)
    assert [len(x) for x in store.levels] == [0, 0, 1] or sum(len(x) for x in store.levels) < 4
    assert sum(r.count() for r in store.runs()) == len(holders)
    for copies in (1, 3):
        found = {(r.h1, r.h2): (r.holders, r.largest) for r in store.at_least(copies).collect()}
        assert found == {k: (len(v), max(v)) for k, v in holders.items() if len(v) >= copies}
    store.close()
    assert not [t.name for t in spark.catalog.listTables() if t.name.startswith("line_")]
