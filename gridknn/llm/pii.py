r"""Personal data: four exact kinds, and identifiers found by bootstrapped contexts.

DataFrame functions only. The exact kinds (email, ip, card, phone) are leftmost
non-overlapping matches, those that fail their test dropped. They seed a bipartite graph
between lexical patterns (the word before an identifier-like token) and instances (the
token). A pattern must be specific: at least SPECIFIC of its word's occurrences in the whole
corpus stand before such a token. In each round a pattern's confidence is the mean belief in
its instances, and an instance's belief is one minus the product of its patterns' doubts;
patterns of at least CONFIDENT with SUPPORT seed instances pass belief on. Tokens believed
in at the end become spans of kind `context`, unless they overlap an exact span.

Null text: empty. Repeated rows are searched one by one. Spans are code points, end
exclusive, ordered by start, then by kind. Extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import saved

KINDS = ("email", "ip", "card", "phone", "context")
SPECIFIC, CONFIDENT, SUPPORT, ROUNDS = 0.5, 0.8, 5, 3

# The kinds' expressions. Possessive and anchored where that changes no match,
# so that long runs of one class cost a single pass and no stack.
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
CARD = r"[0-9](?:[\x20-]?+[0-9])++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
OCTET = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
#: A token of at least 6 characters with a digit, after opening and before closing punctuation.
OPENING = r"[\x22'(\[{<]*+"
CANDIDATE = rf"(?<!\S){OPENING}(?=\S*[0-9])[A-Za-z0-9][A-Za-z0-9@._+/-]{{5,}}(?<=[A-Za-z0-9])(?=[.,;:!?\x22')\]}}>]*+(?!\S))"
#: The word before the one that the text's end is in.
BEFORE = r"(?<!\S)(\S++)\s++\S*+\z"


def _digits(match: Column) -> Column:
    return F.regexp_replace(match, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    n = F.length(digits)

    def add(total: Column, i: Column) -> Column:
        x = F.substring(digits, i, F.lit(1)).cast("int")
        twice = 2 * x - F.when(x > 4, 9).otherwise(0)
        return total + F.when((n - i) % 2 == 1, twice).otherwise(x)

    return F.aggregate(F.sequence(F.lit(1), n), F.lit(0), add) % 10 == 0


def _card(m: Column) -> Column:
    d = _digits(m)
    return F.length(d).between(12, 19) & _luhn(d)


def _ip(m: Column) -> Column:
    return m.rlike(rf"^{OCTET}(?:\.{OCTET}){{3}}$")


def _phone(m: Column) -> Column:
    return F.length(_digits(m)).between(9, 15)


def _always(m: Column) -> Column:
    return F.lit(True)


#: Kind, expression, what a text must hold to be searched at all, and the test of a match.
EXACT = (
    ("email", EMAIL, lambda t: F.contains(t, F.lit("@")), _always),
    ("ip", IP, lambda t: t.rlike(r"[0-9]\.[0-9]+\.[0-9]+\.[0-9]"), _ip),
    ("card", CARD, lambda t: t.rlike(r"[0-9](?:[\x20-]?[0-9]){11}"), _card),
    ("phone", PHONE, lambda t: F.contains(t, F.lit("+")), _phone),
)


def _located(df: DataFrame, text: str, name: str, pattern: str, likely, valid) -> DataFrame:
    """df with the array `name` of (s, e, v, w): places and texts of valid matches, and the words before them.

    The gaps between matches (split) and the matches themselves alternate, so their running
    lengths are the places. A word before is empty at the text's start.
    """
    t = F.col(text)
    found = df.withColumn("__m", F.when(likely(t), F.regexp_extract_all(t, F.lit(pattern), F.lit(0))))
    found = found.withColumn("__g", F.when(F.exists("__m", valid), F.split(t, pattern, -1)))
    kind = "struct<s:int,e:int,v:string,w:string>"

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["__g"])
        end = start + F.length(x["__m"])
        led = F.concat(acc["tail"], x["__g"])
        span = F.array(F.struct(start.alias("s"), end.alias("e"), x["__m"].alias("v"), F.lower(F.regexp_extract(led, BEFORE, 1)).alias("w")).cast(kind))
        tail = F.regexp_extract(F.concat(led, x["__m"]), r"(?<!\S)\S++\z", 0)
        return F.struct(end.alias("at"), tail.alias("tail"), F.when(valid(x["__m"]), F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans"))

    none = F.array().cast(f"array<{kind}>")
    zipped = F.arrays_zip(F.slice("__g", F.lit(1), F.size("__m")).alias("__g"), F.col("__m").alias("__m"))
    spans = F.aggregate(zipped, F.struct(F.lit(0).alias("at"), F.lit("").alias("tail"), none.alias("spans")), step, lambda acc: acc["spans"])
    return found.withColumn(name, F.coalesce(F.when(F.col("__g").isNotNull(), spans), none)).drop("__m", "__g")


def exact_spans(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """A row number, the key, arrays of spans of each exact kind, and candidates (s, e, v, w: the word before)."""
    df = docs.select(F.monotonically_increasing_id().alias("row"), F.col(key).alias("k"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    for name, pattern, likely, valid in EXACT:
        df = _located(df, "t", name, pattern, likely, valid)
    df = _located(df, "t", "c", CANDIDATE, lambda t: t.rlike("[0-9]"), _always)
    token = lambda c: F.regexp_replace(c["v"], "^" + OPENING, "")
    c = F.transform(F.filter("c", lambda c: c["w"] != ""), lambda c: F.struct((c["e"] - F.length(token(c))).alias("s"), c["e"].alias("e"), token(c).alias("v"), c["w"].alias("w")))
    # an exact identifier is a candidate as a whole, not each of its parts
    exact = F.concat(*[F.col(n) for n, *_ in EXACT])
    parts = F.filter(c, lambda c: ~F.exists(exact, lambda b: (b["s"] <= c["s"]) & (b["e"] >= c["e"])))
    c = F.concat(parts, F.filter(exact, lambda b: b["w"] != ""))
    return df.select("row", "k", *[n for n, *_ in EXACT], c.alias("candidates"))


def context_spans(found: DataFrame, docs: DataFrame, text: str = "text", specific: float = SPECIFIC, confident: float = CONFIDENT, support: int = SUPPORT, rounds: int = ROUNDS) -> DataFrame:
    """(row, s, e) of the candidates that the bootstrapped patterns discover; found: stored rows of exact_spans."""
    seeds = F.concat(*[F.col(n) for n, *_ in EXACT])
    covers = lambda c: F.exists(F.col("seeds"), lambda b: (b["s"] <= c["s"]) & (b["e"] >= c["e"]))
    touches = lambda c: F.exists(F.col("seeds"), lambda b: (b["s"] < c["e"]) & (b["e"] > c["s"]))
    marked = found.filter(F.size("candidates") > 0).withColumn("seeds", seeds)
    marked = marked.select("row", F.explode(F.transform("candidates", lambda c: F.struct(c["s"].alias("s"), c["e"].alias("e"), F.lower(c["v"]).alias("instance"), c["w"].alias("pattern"), covers(c).alias("seed"), touches(c).alias("taken")))).alias("c")).select("row", "c.*")
    rows = saved(marked, "pii-candidates")
    often = saved(rows.groupBy("pattern").agg(F.count("*").alias("before"), F.count_if("seed").alias("seeded")).filter(F.col("seeded") >= support), "pii-patterns")
    # how often the patterns' words occur at all; Spark broadcasts `often` only if its file is small
    words = docs.select(F.explode(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"\s+")).alias("pattern"))
    uses = words.join(often.select("pattern"), "pattern", "left_semi").groupBy("pattern").agg(F.count("*").alias("uses"))
    cues = saved(often.join(uses, "pattern").filter(F.col("before") >= specific * F.col("uses")).select("pattern"), "pii-cues")
    edges = saved(rows.join(cues, "pattern", "left_semi").groupBy("pattern", "instance").agg(F.max("seed").alias("seed")), "pii-edges")
    belief = edges.groupBy("instance").agg(F.max(F.col("seed").cast("double")).alias("belief"))
    for i in range(rounds):
        weighed = edges.join(belief, "instance").groupBy("pattern").agg(F.avg("belief").alias("confidence"), F.count_if("seed").alias("seeded"))
        trusted = weighed.filter((F.col("confidence") >= confident) & (F.col("seeded") >= support))
        doubt = F.exp(F.sum(F.log1p(-F.least(F.coalesce("confidence", F.lit(0.0)), F.lit(0.999)))))
        # every instance stays, also those that nothing speaks for: a confidence is the mean over all of them
        derived = edges.join(trusted.select("pattern", "confidence"), "pattern", "left").groupBy("instance").agg(F.max(F.col("seed").cast("double")).alias("own"), (1 - doubt).alias("passed"))
        belief = saved(derived.select("instance", "passed", F.greatest("own", "passed").alias("belief")), f"pii-belief-{i}")
    sure = belief.filter(F.col("passed") >= confident).select("instance")
    return rows.filter(~F.col("taken")).join(cues, "pattern", "left_semi").join(sure, "instance", "left_semi").select("row", "s", "e")


def find_personal_data(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document: key, counts of the exact kinds, digest of their spans, and all spans."""
    found = saved(exact_spans(docs, key, text), "pii-exact")
    more = context_spans(found, docs, text).groupBy("row").agg(F.collect_set(F.struct("s", F.lit(4).alias("k"), "e")).alias("extra"))
    numbered = lambda i: lambda x: F.struct(x["s"].alias("s"), F.lit(i).alias("k"), x["e"].alias("e"))
    spans = [F.transform(n, numbered(i)) for i, (n, *_) in enumerate(EXACT)]
    names = F.array(*[F.lit(k) for k in KINDS])
    shown = lambda a: F.array_join(F.transform(F.array_sort(a), lambda x: F.concat_ws(":", F.element_at(names, x["k"] + 1), x["s"].cast("string"), x["e"].cast("string"))), ",")
    all_rows = found.select("row", F.col("k").alias(key), *[F.size(n).cast("long").alias(f"n_{n}") for n, *_ in EXACT], F.concat(*spans).alias("base")).join(more, "row", "left")
    every = F.when(F.col("extra").isNull(), F.col("base")).otherwise(F.concat("base", F.coalesce("extra", F.array().cast("array<struct<s:int,k:int,e:int>>"))))
    return all_rows.select(key, *[f"n_{n}" for n, *_ in EXACT], F.sha2(shown(F.col("base")), 256).alias("base_sha256"), shown(every).alias("spans"))


def mask_personal_data(docs: DataFrame, key: str = "doc_id", text: str = "text", mask: str = "[private]") -> DataFrame:
    """key and text with the found spans replaced, from the last to the first; key has to be unique."""
    found = find_personal_data(docs, key, text).select(F.col(key).alias("__k"), "spans").filter("spans <> ''")
    part = lambda x, i: F.element_at(F.split(x, ":"), i).cast("int")
    ordered = F.reverse(F.split("spans", ","))
    start = F.struct(F.col(text).alias("t"), F.lit(2**31 - 1).alias("at"))
    cut = lambda acc, x: F.when(
        part(x, 3) <= acc["at"],
        F.struct(F.concat(F.substring(acc["t"], F.lit(1), part(x, 2)), F.lit(mask), F.substring(acc["t"], part(x, 3) + 1, F.length(acc["t"]))).alias("t"), part(x, 2).alias("at")),
    ).otherwise(acc)
    joined = docs.select(key, text).join(found, F.col(key) == F.col("__k"), "left")
    return joined.select(key, F.when(F.col("spans").isNull(), F.col(text)).otherwise(F.aggregate(ordered, start, cut, lambda acc: acc["t"])).alias(text))
