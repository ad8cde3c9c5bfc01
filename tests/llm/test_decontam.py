"""Decontamination against all windows compared as tuples of words, on both sides of the size check."""

import hashlib

import pytest

from gridknn.llm import decontam
from gridknn.llm.queries import QUERIES

SF = "/root/testdata/sf0.001"


def words_of(t: str | None) -> list[str]:
    out, word = [], ""
    for ch in (t or "") + " ":
        if ch >= "\x80" or ch.isalnum():
            word += ch.lower() if "A" <= ch <= "Z" else ch
        elif word:
            out.append(word)
            word = ""
    return out


def windows_of(items: list) -> dict[tuple, set[str]]:
    found: dict[tuple, set[str]] = {}
    for item, text in items:
        w = words_of(text)
        n = min(13, len(w))
        for i in range(len(w) - n + 1 if n else 0):
            found.setdefault(tuple(w[i : i + n]), set()).add(str(item))
    return found


def wanted(text: str | None, windows: dict[tuple, set[str]], lengths: set[int]) -> tuple:
    w, hit, items = words_of(text), set(), set()
    for n in lengths:
        for i in range(len(w) - n + 1):
            found = windows.get(tuple(w[i : i + n]))
            if found:
                hit.update(range(i, i + n))
                items |= found
    digest = hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()
    return len(w), len(hit), len(items), digest, bool(hit) and 20 * len(hit) >= len(w)


def shown(r) -> tuple:
    return r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated


@pytest.fixture(scope="module")
def expected(spark):
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    windows = windows_of(items)
    lengths = {len(k) for k in windows}
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()
    return {r.doc_id: wanted(r.text, windows, lengths) for r in docs}


def test_query_over_the_whole_table(spark, expected):
    (query,) = (q for n, q in QUERIES.items() if n.startswith("op3_"))
    assert {r.doc_id: shown(r) for r in query(spark, SF).collect()} == expected
    assert any(e[1] for e in expected.values()) and not all(e[4] for e in expected.values())


def test_join_beyond_the_size_check_over_the_whole_table(spark, expected):
    docs, bench = (spark.read.parquet(f"{SF}/{n}.parquet") for n in ("documents", "benchmark"))
    assert {r.doc_id: shown(r) for r in decontam.decontaminate(docs, bench, max_bytes=1).collect()} == expected


@pytest.mark.parametrize("limit", [1, 1 << 27])
def test_odd_rows_on_both_sides_of_the_check(spark, limit):
    passage = [f"p{i}" for i in range(40)]
    items = [("b", " ".join(passage)), ("a", " ".join(passage[:20])), ("10", "Tiny Item"), ("9", "tiny--item"), ("e", ""), ("n", None), ("q", "…")]
    bench = spark.createDataFrame(items, "item_id string, text string")
    long = "filler " * 50_000 + " ".join(passage[3:16]).upper() + " tail" * 1_000
    texts = [None, "", " .,- ", " ".join(passage), " ".join(passage[:12]), long, "a tiny item", "tinyitem", "… x", " ".join(passage[5:18] + passage[6:19])]
    rows = [(i, t, "x", 1) for i, t in enumerate(texts)] + [(3, texts[3], "x", 1), (None, texts[3], "x", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, h string, n int")
    windows = windows_of(items)
    got = decontam.decontaminate(docs, bench, max_bytes=limit).collect()
    assert len(got) == len(rows)
    for r in got:
        assert shown(r) == wanted(texts[3 if r.doc_id is None else r.doc_id], windows, {len(k) for k in windows}), r.doc_id
    assert decontam.decontaminate(docs.limit(0), bench, max_bytes=limit).collect() == []
    kept = decontam.drop_contaminated_documents(docs, bench, max_bytes=limit)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect()) == [0, 1, 2, 4, 5, 7]
