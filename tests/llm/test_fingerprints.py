import hashlib

from gridknn.llm import fingerprints as fp


def rows(spark, data, schema="doc_id long, text string", **kw):
    return fp.fingerprint_report(spark.createDataFrame(data, schema), **kw).collect()


def brute(data):
    order = sorted(((k, t or "") for k, t in data), key=lambda x: -x[0])
    out = {}
    for (k, t), (_, after) in zip(order, order[1:] + order[:1], strict=True):
        half = len(t) // 2
        edited = t[: len(t) - half] + after[:half]
        same = lambda a, b: float(fp.canonical(a) == fp.canonical(b))
        out[k] = (len(t), hashlib.sha256(edited.encode()).hexdigest(), same(t, edited), same(t, after))
    return out


def test_matches_brute_force(spark):
    data = [(i, ["Ünï  Text\n%d" % (i % 5), "", None, "a" * i, "ﬁne Straße"][i % 5]) for i in range(83)]
    got = rows(spark, data)
    want = brute(data)
    assert len(got) == len(data)
    for r in got:
        assert (r.n_chars, r.edited_sha256, r.near_edited, r.near_next) == want[r.doc_id]
    texts = dict(data)
    by_print = {}
    for r in got:
        by_print.setdefault(r.fingerprint, set()).add(fp.canonical(texts[r.doc_id]))
    assert all(len(v) == 1 for v in by_print.values())
    assert len(by_print) == len({fp.canonical(t) for _, t in data})


def test_colliding_digests_are_told_apart_by_bytes(spark):
    data = [(i, f"text {i % 7}") for i in range(40)]
    got = rows(spark, data, digest=lambda b: b"\x01" * 16)
    assert len({r.fingerprint for r in got}) == 7
    assert {r.near_next for r in got} == {0.0}


def test_odd_rows(spark):
    assert rows(spark, []) == []
    one = rows(spark, [(3, "alone")])
    assert one[0].edited_sha256 == hashlib.sha256(b"aloal").hexdigest() and one[0].near_next == 1.0
    twice = rows(spark, [(3, "same"), (3, "same"), (None, "null key")])
    assert len(twice) == 3 and sum(r.near_next for r in twice) == 1
    extra = spark.createDataFrame([(1, "a", "x", 2), (2, None, "y", 3)], "doc_id long, text string, digest string, r int")
    assert {r.doc_id: r.n_chars for r in fp.fingerprint_report(extra).collect()} == {1: 1, 2: 0}


def test_groups(spark):
    g = fp.exact_groups(spark.createDataFrame([(1, "A b"), (2, " a  B"), (3, "c")], "doc_id long, text string"))
    assert {r.doc_id: (r.copies, r["first"]) for r in g.collect()} == {1: (2, 1), 2: (2, 1), 3: (1, 3)}
