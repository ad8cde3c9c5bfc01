"""Canonical exact digests of whole documents.

Texts are folded (Unicode NFKC, case, white space), hashed with 128-bit xxhash, and grouped
by that hash; inside a bucket of equal hashes the folded bytes are compared, so that texts
which merely collide get fingerprints of their own. Only documents whose hash repeats are
brought together for the comparison, one copy of each folded text from each batch, chosen
by a filter of fixed size.

Null text: empty. Repeated rows: equal fingerprints. Rows of equal or null doc_id: ordered by
their text, null last. Other columns are not read.
"""

from __future__ import annotations

import hashlib
import unicodedata
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .keyfilter import key_filter, passes

LOWEST = -(1 << 63)
_codec = pa.Codec("zstd", 1)


def canonical(text: str | None) -> str:
    """NFKC, full case folding, NFKC again, runs of white space as one blank, none at the ends."""
    if not text:
        return ""
    if text.isascii():
        return " ".join(text.lower().split())
    folded = unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", text).casefold())
    return " ".join(folded.split())


def digest(folded: bytes) -> bytes:
    return xxhash.xxh3_128_digest(folded)


def pack_text(text: str | None) -> bytes:
    raw = (text or "").encode()
    return len(raw).to_bytes(4, "little") + _codec.compress(raw, asbytes=True)


def unpack_text(packed: bytes) -> str:
    return _codec.decompress(packed[4:], int.from_bytes(packed[:4], "little"), asbytes=True).decode()


def _head(d: bytes) -> int:
    return int.from_bytes(d[:8], "little", signed=True)


def colliding(docs: DataFrame, text: str = "text", digest: Callable[[bytes], bytes] = digest) -> DataFrame:
    """(digest, sha, variant) of folded texts that share their digest with another folded text.

    variant numbers the different texts of one digest from 0 in byte order. Empty unless the
    hash collides.
    """

    def heads(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = [_head(digest(canonical(t).encode())) for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(values, pa.int64())], names=["h"])

    repeated = docs.select(text).mapInArrow(heads, "h long").groupBy("h").count().filter("count > 1")
    wanted = key_filter(repeated, "h")

    def bodies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            folded = [canonical(t).encode() for t in batch.column(0).to_pylist()]
            digests = [digest(f) for f in folded]
            may = passes(wanted.value, np.array([_head(d) for d in digests], np.int64))
            rows = list({(d, f) for d, f, m in zip(digests, folded, may, strict=True) if m})
            packed = [pack_text(f.decode()) for _, f in rows]
            yield pa.RecordBatch.from_arrays([pa.array([d for d, _ in rows], pa.binary()), pa.array(packed, pa.binary())], names=["digest", "body"])

    same = docs.select(text).mapInArrow(bodies, "digest binary, body binary").groupBy("digest", "body").agg(F.lit(1).alias("one"))
    many = same.groupBy("digest").agg(F.count("*").alias("n")).filter("n > 1").select("digest")

    def shas(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            folded = [unpack_text(b).encode() for b in batch.column(1).to_pylist()]
            out = [batch.column(0), pa.array(folded, pa.binary()), pa.array([hashlib.sha256(f).digest() for f in folded], pa.binary())]
            yield pa.RecordBatch.from_arrays(out, names=["digest", "folded", "sha"])

    apart = same.join(many, "digest", "left_semi").select("digest", "body").mapInArrow(shas, "digest binary, folded binary, sha binary")
    number = F.row_number().over(Window.partitionBy("digest").orderBy("folded")) - 1
    return apart.select("digest", "sha", number.cast("long").alias("variant"))


def exact_groups(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, fingerprint, and the number and smallest key of the documents that share it."""
    prints = fingerprint_report(docs, key, text).select(key, "fingerprint")
    groups = prints.groupBy("fingerprint").agg(F.count("*").alias("copies"), F.min(key).alias("first"))
    return prints.join(groups, "fingerprint")


REPORT = [
    T.StructField("n_chars", T.LongType()),
    T.StructField("edited_sha256", T.StringType()),
    *(T.StructField(n, T.BinaryType()) for n in ("digest", "sha", "e_digest", "e_sha", "n_digest", "n_sha")),
]


def fingerprint_report(docs: DataFrame, key: str = "doc_id", text: str = "text", digest: Callable[[bytes], bytes] = digest) -> DataFrame:
    """Fingerprints of all documents and of their edited texts.

    A document's neighbour is the next in descending order of an integer key. The table is
    cut into key ranges, one for each shuffle partition; texts travel once, compressed, to
    their range, and the first document of each range also to the range before it.
    """
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    order = F.coalesce(F.col(key), F.lit(LOWEST))
    points = [i / parts for i in range(1, parts)]
    cuts = docs.agg(F.percentile_approx(order, points, 100 * parts).alias("c")).first()["c"] if points else []
    cuts = np.unique(np.array(cuts or [], np.int64))

    def ranges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy()
            at = np.searchsorted(cuts, ids)
            yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(ids)], names=["r", "top"])

    tops = docs.select(order.alias("o")).mapInArrow(ranges, "r int, top long").groupBy("r").agg(F.max("top").alias("top")).collect()
    tops = sorted((r["r"], r["top"]) for r in tops)
    above = {top: tops[i + 1][0] for i, (_, top) in enumerate(tops[:-1])}
    last, highest = (tops[0][0], tops[-1][1]) if tops else (0, LOWEST)
    heads = spark.sparkContext.broadcast((cuts, above))
    schema = T.StructType([T.StructField("r", T.IntegerType()), T.StructField("guest", T.BooleanType()), T.StructField("o", T.LongType()), T.StructField(key, docs.schema[key].dataType), T.StructField("body", T.BinaryType())])

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cuts, above = heads.value
        for batch in batches:
            ids = batch.column(0).to_numpy()
            bodies = pa.array([pack_text(t) for t in batch.column(2).to_pylist()], pa.binary())
            at = np.searchsorted(cuts, ids).astype(np.int32)
            rows, to = [np.arange(len(ids))], [at]
            for i in np.flatnonzero(np.isin(ids, [*above, highest])):
                for target in ([above[ids[i]]] if ids[i] in above else []) + ([last] if ids[i] == highest else []):
                    rows.append(np.array([i]))
                    to.append(np.array([target], np.int32))
            take = pa.array(np.concatenate(rows))
            guest = pa.array(np.arange(len(take)) >= len(ids))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(to)), guest, batch.column(0).take(take), batch.column(1).take(take), bodies.take(take)], names=schema.names)

    dealt = docs.select(order.alias("o"), F.col(key).alias("k"), text).mapInArrow(deal, schema)
    dealt = dealt.repartitionById(parts, F.col("r")).sortWithinPartitions(F.col("r").desc(), "guest", F.col("o").desc(), "body")
    out_schema = T.StructType([T.StructField(key, docs.schema[key].dataType), *REPORT])

    def marks(text: str) -> tuple[bytes, bytes]:
        folded = canonical(text).encode()
        return digest(folded), hashlib.sha256(folded).digest()

    def row(now: tuple, after: tuple) -> tuple:
        key_value, text, own = now
        half = len(text) // 2
        edited = text[: len(text) - half] + after[1][:half]
        return key_value, len(text), hashlib.sha256(edited.encode()).hexdigest(), *own, *marks(edited), *after[2]

    def report(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, at = None, None  # the document that waits for its neighbour, and its range
        for batch in batches:
            out = []
            for r, guest, key_value, body in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(3).to_pylist(), batch.column(4).to_pylist(), strict=True):
                if guest and (held is None or at != r):
                    continue  # a second guest of equal key
                text = unpack_text(body)
                now = (key_value, text, marks(text))
                if held is not None:
                    out.append(row(held, now))
                held, at = (None if guest else now), r
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], f.type) for i, f in enumerate(arrow)], names=out_schema.names)

    arrow = to_arrow_schema(out_schema)
    rows = dealt.mapInArrow(report, out_schema)
    variants = colliding(docs, text, digest)
    plain, edited = F.hex("digest"), F.hex("e_digest")
    if not variants.isEmpty():
        numbered = rows.join(variants, ["digest", "sha"], "left").join(variants.select(F.col("digest").alias("e_digest"), F.col("sha").alias("e_sha"), F.col("variant").alias("e_variant")), ["e_digest", "e_sha"], "left")
        name = lambda h, v: F.concat(h, F.when(F.col(v) > 0, F.concat(F.lit("-"), F.col(v).cast("string"))).otherwise(""))
        rows, plain, edited = numbered, name(plain, "variant"), name(edited, "e_variant")
    same = lambda p: ((F.col("digest") == F.col(p + "_digest")) & (F.col("sha") == F.col(p + "_sha"))).cast("double")
    return rows.select(key, "n_chars", "edited_sha256", F.lower(plain).alias("fingerprint"), F.lower(edited).alias("edited_fingerprint"), same("e").alias("near_edited"), same("n").alias("near_next"))
