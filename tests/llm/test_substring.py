import hashlib
import random
import re

from gridknn.llm import substring as sd

BLANK = " \t\n\x0b\x0c\r"
LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def units(text):
    """Stripped units with their places in code points, by place."""
    found = set()
    for pattern, least in ((r"[^\n]*", 20), (None, 50)):
        cuts = [m.span() for m in re.finditer(pattern, text)] if pattern else []
        if not pattern:
            at = 0
            for m in re.finditer(r"\n|(?<=[.!?])[ \t\x0b\x0c\r]", text):
                cuts.append((at, m.start()))
                at = m.end()
            cuts.append((at, len(text)))
        for s, e in cuts:
            part = text[s:e]
            key = part.strip(BLANK)
            if len(key) >= least:
                a = s + len(part) - len(part.lstrip(BLANK))
                found.add((a, a + len(key), key.translate(LOW)))
    return sorted(found)


def runs(t, gone, sentence, least):
    """The mask of repeated units, as runs of `least` words with short text between."""
    ends = [i for i in range(len(t) + 1) if (i < len(t) and gone[i]) != (i > 0 and gone[i - 1])]
    spans = []
    for a, b in zip(ends[::2], ends[1::2], strict=True):
        if spans and len(t[spans[-1][1] : a].strip(BLANK)) < sentence:
            spans[-1][1] = b
        else:
            spans.append([a, b])
    out = [False] * len(t)
    for a, b in spans:
        if len([w for w in re.split(f"[{BLANK}]+", t[a:b]) if w]) >= least:
            out[a:b] = [True] * (b - a)
    return out


def brute(rows, least=0):
    first = {}
    rank = lambda k: sd.LAST if k is None else k
    for k, t in rows:
        for _, _, u in units(t or ""):
            first[u] = min(first.get(u, sd.LAST), rank(k))
    out = []
    for k, t in rows:
        t, seen, gone = t or "", set(), [False] * len(t or "")
        for a, b, u in units(t):
            if first[u] < rank(k) or u in seen:
                gone[a:b] = [True] * (b - a)
            seen.add(u)
        if least:
            gone = runs(t, gone, 50, least)
        kept = "".join(c for c, g in zip(t, gone, strict=True) if not g)
        out.append((k, len(units(t)), sum(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out, key=str)


def corpus(seed=1, n=90):
    rng = random.Random(seed)
    sentence = [f"Sentence {i} has quite a few words in it so that it counts é." for i in range(30)] + ["Short one.", "WHAT?", "x" * 49 + ".", "y" * 50]
    texts = [None, "", "\n", "a line of exactly 20!", "  a line of exactly 20! \n a line of exactly 20!"]
    while len(texts) < n:
        texts.append("\n".join(" ".join(rng.choices(sentence, k=rng.randint(1, 3))) for _ in range(rng.randint(1, 4))))
    return list(enumerate(texts))


def test_matches_brute_force(spark):
    rows = corpus() + [(7, corpus()[7][1]), (None, corpus()[8][1])]
    frame = spark.createDataFrame([(k, t, "x", 1) for k, t in rows], "doc_id long, text string, rank string, gone int")
    out = sd.substring_dedup(frame, line=20, sentence=50, run=0, with_text=True).collect()
    assert sorted(((r.doc_id, r.n_units, r.n_removed_chars, r.kept_sha256) for r in out), key=str) == brute(rows)
    texts = dict(rows)
    for r in out:
        if r.doc_id is not None:
            t = texts[r.doc_id] or ""
            assert "".join(t[slice(*map(int, s.split(":")))] for s in r.kept.split(",") if s) == r.kept_text


def test_heavy_units(spark, monkeypatch):
    monkeypatch.setattr(sd, "HEAVY_LEAST", 5)
    rows = corpus(2)
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(((r.doc_id, r.n_units, r.n_removed_chars, r.kept_sha256) for r in sd.substring_dedup(frame, line=20, sentence=50, run=0).collect()), key=str) == brute(rows)


def test_runs_of_repeated_units(spark):
    rows = corpus(3) + [(200, "\n".join(f"A passage of sentence {i} that others hold as well." for i in range(9))), (201, "Its own words first. " + "\n".join(f"A passage of sentence {i} that others hold as well." for i in range(9)) + " And more.")]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    for least in (14, 30):
        got = sd.substring_dedup(frame, line=20, sentence=50, run=least)
        assert sorted(((r.doc_id, r.n_units, r.n_removed_chars, r.kept_sha256) for r in got.collect()), key=str) == brute(rows, least)
    alone = [(1, "One common sentence of some words. Then others."), (2, "Quite different here. One common sentence of some words.")]
    assert {r.n_removed_chars for r in sd.substring_dedup(spark.createDataFrame(alone, "doc_id long, text string")).collect()} == {0}


def test_empty_table(spark):
    assert sd.substring_dedup(spark.createDataFrame([], "doc_id long, text string")).collect() == []
