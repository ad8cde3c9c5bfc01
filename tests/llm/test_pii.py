import hashlib
import random
import re

from gridknn.llm import pii

KINDS = ("email", "ip", "card", "phone")
PATTERNS = [r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]"]


def luhn(d):
    total = 0
    for i, x in enumerate(reversed(d)):
        x = int(x) * (1 + i % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def brute(text):
    spans = []
    for k, p in enumerate(PATTERNS):
        for m in re.finditer(p, text or "", re.ASCII):
            s, d = m.group(), re.sub("[^0-9]", "", m.group())
            if k == 1 and any(int(x) > 255 for x in s.split(".")):
                continue
            if (k == 2 and not (12 <= len(d) <= 19 and luhn(d))) or (k == 3 and not 9 <= len(d) <= 15):
                continue
            spans.append((m.start(), k, m.end()))
    return sorted(spans)


def check(spark, texts):
    docs = spark.createDataFrame([(i, t, "x", 1) for i, t in enumerate(texts)], "doc_id long, text string, k string, row int")
    rows = pii.find_personal_data(docs).collect()
    assert len(rows) == len(texts)
    for r in rows:
        want = brute(texts[r.doc_id])
        shown = ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in want)
        assert r.base_sha256 == hashlib.sha256(shown.encode()).hexdigest(), (texts[r.doc_id], r.spans, shown)
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == i for _, k, _ in want) for i in range(4)]
    return {r.doc_id: r.spans for r in rows}


def test_base_spans_match_brute_force(spark):
    rng = random.Random(3)
    bits = ["a.b@c.de", "_x@y.z", "@", ".", "1.2.3.4", "255.256.1.1", "0001.2.3.004", "4111 1111 1111 1111", "4111-1111-1111-1112", "79927398713", "+1 (555) 010-9999", "+49.30.1234567 ", "+1", "(", " ", "-", "é😀", "\n", "7", "00", "٣"]
    texts = [None, "", "x@y", "a@b.c_d@e.f", "1.2.3.4.5.6.7.8", "+1 ((((", "1" * 30_000, "1 " * 8_000, "a." * 20_000 + "@", "x@" + "a." * 20_000 + "b"]
    texts += ["".join(rng.choices(bits, k=rng.randint(1, 25))) for _ in range(300)]
    check(spark, texts)


def test_contexts_discover_unseen_identifiers(spark):
    seeds = [f"filler words the mailbox: user{i}@host.example then more" for i in range(12)]
    unseen = ["we saw mailbox: cust-778812x again", "the order-4411xyz is no person", "mailbox: only once"]
    spans = check(spark, seeds + unseen)
    assert "context" in spans[12] and "context" not in spans[13] and "context" not in spans[14]
    at = unseen[0].index("cust")
    assert spans[12] == f"context:{at}:{at + len('cust-778812x')}"


def test_a_refused_cue_stays_refused(spark):
    """`blend:` shares five addresses with the trusted `mailbox:`, but stands before 60 other tokens."""
    trusted = [f"some mailbox: user{i}@host.example and more" for i in range(12)]
    shared = [f"some blend: user{i}@host.example and more" for i in range(5)]
    clean = [f"some blend: lot-{4000 + i}x and more" for i in range(60)]
    spans = check(spark, [*trusted, *shared, *clean, "in mailbox: cust-778812x again"])
    assert not [i for i in range(17, 77) if "context" in spans[i]]
    assert "context" in spans[77]


def test_candidates_in_any_surroundings(spark):
    texts = ["account AB-123456.", "account\n(AB-123456), so", "account  \"AB-123456\"!", "account " + "a1" * 40, "ID AB1234 CD5678", "AB-123456 first", "tel +1 (555) 010-9999 now"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.k: sorted((r.s, r.v, r.w) for r in r.candidates) for r in pii.exact_spans(docs).collect()}
    at = [(8, "AB-123456", "account"), (9, "AB-123456", "account"), (10, "AB-123456", "account")]
    assert [got[i] for i in range(3)] == [[x] for x in at]
    assert got[3] == [(8, "a1" * 40, "account")]
    assert got[4] == [(3, "AB1234", "id"), (10, "CD5678", "ab1234")] and got[5] == []
    assert got[6] == [(4, "+1 (555) 010-9999", "tel")]


def test_empty_table_and_masking(spark):
    assert pii.find_personal_data(spark.createDataFrame([], "doc_id long, text string")).collect() == []
    docs = spark.createDataFrame([(1, "mail a@b.cd or 1.2.3.4!"), (2, None), (3, "none")], "doc_id long, text string")
    assert {r.doc_id: r.text for r in pii.mask_personal_data(docs, mask="#").collect()} == {1: "mail # or #!", 2: None, 3: "none"}
