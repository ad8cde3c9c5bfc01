"""Quality classifier: a byte-level convolutional network in numpy.

Filters of WIDTH bytes slide over every byte of a document. A learned table holds what each
byte adds to each filter at each tap, so that a convolution is a sum of gathered rows. The
rectified responses are max-pooled over overlapping chunks that cover the whole document;
the maximum and the mean of the chunks' pools give one probability by a logistic layer.

It is fitted on the driver by Adam from at most SAMPLE labelled documents of the training
rows, chosen by a hash of their key (a bound, so the fit costs the same at any size; of a
document beyond FIT_BYTES code points eight evenly spread pieces are used). Scoring reads
whole texts and nothing else.

Null text: empty; empty texts get the score of padding. Rows are scored one by one, so
repeated rows get equal scores; other columns are not read. Without any label, or with
one class only, the fit returns the smoothed share of label 1 for all texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.broadcast import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textscan as ts

WIDTH, FILTERS, HALF = 6, 16, 128
SAMPLE, FIT_BYTES, EPOCHS, BATCH, RATE = 2000, 32_768, 8, 32, 0.01
THRESHOLD = 0.7
FOLDS, HELD_OUT = 4, 2
BLOCK = 1 << 18


def _padded(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows with WIDTH zero bytes behind each, so that every byte starts a full filter window."""
    sizes = np.diff(offsets)
    at = np.concatenate([[0], np.cumsum(sizes + WIDTH)])
    out = np.zeros(at[-1] + WIDTH, np.uint8)
    out[np.arange(len(data)) + np.repeat(np.arange(len(sizes)) * WIDTH, sizes)] = data
    return out, at


@dataclass
class Network:
    taps: np.ndarray  # WIDTH x 256 x FILTERS
    bias: np.ndarray  # FILTERS
    out: np.ndarray  # 2 * FILTERS + 1: maxima, means, constant

    def pairs(self) -> list[np.ndarray]:
        """Tables over two neighbouring bytes: half as many gathers."""
        t = self.taps.astype(np.float32)
        tables = [(t[k][:, None, :] + t[k + 1][None, :, :]).reshape(1 << 16, FILTERS) for k in range(0, WIDTH, 2)]
        tables[0] = tables[0] + self.bias.astype(np.float32)
        return tables

    def pool(self, pairs: list[np.ndarray], data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Responses, maxima over half chunks, and each half chunk's first byte; at: row starts in padded data."""
        code = (data[:-1].astype(np.int64) << 8) | data[1:]
        n = int(at[-1])
        response = pairs[0][code[:n]]
        for k in range(1, len(pairs)):
            response += pairs[k][code[2 * k : n + 2 * k]]
        sizes = np.diff(at) - WIDTH
        ends = at[:-1] + np.maximum(sizes, 1)  # windows that begin later would see the next row
        beyond = at[1:] - ends
        response[np.repeat(ends, beyond) + ts.ragged(beyond)] = -np.inf
        halves = np.maximum(1, -(-sizes // HALF))
        starts = np.repeat(at[:-1], halves) + ts.ragged(halves) * HALF
        return response, np.maximum.reduceat(response, starts, axis=0), starts

    @staticmethod
    def chunks(halves: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of each chunk (two half chunks, the next one starting one half later) the first half and the row."""
        n = np.maximum(1, halves - 1)
        rows = np.repeat(np.arange(len(halves)), n)
        return (np.cumsum(halves) - halves)[rows] + ts.ragged(n), rows

    def features(self, pairs: list[np.ndarray], data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        padded, at = _padded(data, offsets)
        _, top, _ = self.pool(pairs, np.concatenate([padded, np.zeros(WIDTH, np.uint8)]), at)
        halves = np.maximum(1, -(-np.diff(offsets) // HALF))
        first, rows = self.chunks(halves)
        pooled = np.maximum(np.maximum(top[first], top[np.minimum(first + (halves[rows] > 1), len(top) - 1)]), 0)
        cuts = np.flatnonzero(np.diff(rows, prepend=-1))
        counts = np.diff(np.append(cuts, len(rows)))[:, None]
        return np.hstack([np.maximum.reduceat(pooled, cuts, axis=0), np.add.reduceat(pooled, cuts, axis=0) / counts, np.ones((len(halves), 1), np.float32)])

    def score(self, data: np.ndarray, offsets: np.ndarray, pairs: list[np.ndarray] | None = None) -> np.ndarray:
        pairs = pairs or self.pairs()
        out = [np.zeros(0)]
        for a, b in ts.row_blocks(offsets, BLOCK):
            out.append(_sigmoid(self.features(pairs, data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) @ self.out))
        return np.concatenate(out).astype(np.float64)


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def fit(texts: list[bytes], labels: np.ndarray, epochs: int = EPOCHS, seed: int = 7) -> Network:
    """Adam on the logistic loss; gradients flow back only to the bytes that won a pool."""
    rng = np.random.default_rng(seed)
    net = Network(rng.normal(0, 0.25, (WIDTH, 256, FILTERS)).astype(np.float32), np.zeros(FILTERS, np.float32), np.concatenate([rng.normal(0, 0.1, 2 * FILTERS), [0.0]]).astype(np.float32))
    share = (labels.sum() + 1) / (len(labels) + 2)
    net.out[-1] = np.log(share / (1 - share))
    if len(set(labels.tolist())) < 2:
        net.out[:-1] = 0
        return net
    params = [net.taps, net.bias, net.out]
    m, v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    step = 0
    for _ in range(epochs):
        order = rng.permutation(len(texts))
        for i in range(0, len(order), BATCH):
            pick = order[i : i + BATCH]
            offsets = np.concatenate([[0], np.cumsum([len(texts[j]) for j in pick])])
            grads = _gradients(net, np.frombuffer(b"".join(texts[j] for j in pick), np.uint8), offsets, labels[pick])
            step += 1
            for p, g, a, b in zip(params, grads, m, v, strict=True):
                a += 0.1 * (g - a)
                b += 0.01 * (g * g - b)
                p -= RATE * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.99**step)) + 1e-6)
    return net


def _gradients(net: Network, data: np.ndarray, offsets: np.ndarray, labels: np.ndarray) -> list[np.ndarray]:
    padded, at = _padded(data, offsets)
    padded = np.concatenate([padded, np.zeros(WIDTH, np.uint8)])
    response, top, starts = net.pool(net.pairs(), padded, at)
    halves = np.maximum(1, -(-np.diff(offsets) // HALF))
    first, rows = net.chunks(halves)
    second = np.minimum(first + (halves[rows] > 1), len(top) - 1)
    won = np.where(top[first] >= top[second], first[:, None], second[:, None])  # half chunk of each chunk's maximum
    pooled = np.maximum(np.take_along_axis(top, won, 0), 0)
    cuts = np.flatnonzero(np.diff(rows, prepend=-1))
    counts = np.diff(np.append(cuts, len(rows)))[:, None]
    high = np.maximum.reduceat(pooled, cuts, axis=0)
    x = np.hstack([high, np.add.reduceat(pooled, cuts, axis=0) / counts, np.ones((len(halves), 1), np.float32)])
    d = ((_sigmoid(x @ net.out) - labels) / len(labels)).astype(np.float32)
    d_out = x.T @ d
    d_pool = (d[:, None] * net.out[FILTERS : 2 * FILTERS] / counts)[rows]
    best = pooled >= high[rows]
    d_pool = (d_pool + best * (d[:, None] * net.out[:FILTERS])[rows] / np.maximum(1, np.add.reduceat(best, cuts, axis=0))[rows]) * (pooled > 0)
    # the byte of each half chunk where each filter is largest
    half_of = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, len(response))))
    taps, bias = np.zeros_like(net.taps), np.zeros_like(net.bias)
    for f in range(FILTERS):
        flow = np.bincount(won[:, f], weights=d_pool[:, f], minlength=len(starts))
        at_top = np.flatnonzero(response[:, f] == top[half_of, f])
        place = np.zeros(len(starts), np.int64)
        place[half_of[at_top]] = at_top
        bias[f] = flow.sum()
        for k in range(WIDTH):
            taps[k, :, f] = np.bincount(padded[place + k], weights=flow, minlength=256)
    return [taps, bias, d_out]


def sample(docs: DataFrame, labels: DataFrame, key: str, text: str, label: str, limit: int = SAMPLE) -> tuple[list[bytes], np.ndarray]:
    """At most limit training texts and labels; rows of the held-out fold are left out before anything else."""
    learnt = labels.select(F.col(key).alias("k"), F.col(label).cast("int").alias("y")).filter(F.col("y").isin(0, 1))
    learnt = learnt.filter(F.crc32(F.col("k").cast("string").cast("binary")) % FOLDS != HELD_OUT)
    agreed = learnt.groupBy("k").agg(F.min("y").alias("y"), F.max("y").alias("z")).filter("y = z")
    picked = agreed.orderBy(F.xxhash64("k"), "k").limit(limit).select("k", "y")
    piece = FIT_BYTES // 8
    spread = F.concat(*[F.expr(f"substring(t, 1 + cast((length(t) - {piece}) * {i} / 7 as int), {piece})") for i in range(8)])
    texts = docs.select(F.col(key).alias("k"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    rows = texts.join(F.broadcast(picked), "k").select("k", "y", F.when(F.length("t") > FIT_BYTES, spread).otherwise(F.col("t")).alias("t"))
    found = sorted(rows.collect(), key=lambda r: (r["k"], r["t"]))[: 2 * limit]
    return [r["t"].encode() for r in found], np.array([r["y"] for r in found], np.float32)


def trained(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "quality") -> Broadcast:
    return docs.sparkSession.sparkContext.broadcast(fit(*sample(docs, labels, key, text, label)))


def _scores(network: Broadcast, column: pa.Array) -> np.ndarray:
    net = network.value
    if not hasattr(net, "_pairs"):
        net._pairs = net.pairs()
    return net.score(*ts.buffers(column), net._pairs)


def score_quality(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "quality") -> DataFrame:
    """key, held_out, score and predicted for every document."""
    network = trained(docs, labels, key, text, label)
    schema = T.StructType([T.StructField(key, docs.schema[key].dataType), T.StructField("score", T.DoubleType())])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(_scores(network, batch.column(1)))], names=schema.names)

    held = F.coalesce(F.crc32(F.col(key).cast("string").cast("binary")) % FOLDS == HELD_OUT, F.lit(False))
    return docs.select(key, text).mapInArrow(scan, schema).select(key, held.alias("held_out"), "score", F.when(F.col("score") >= THRESHOLD, 1).otherwise(0).alias("predicted"))


def keep_quality(docs: DataFrame, train_docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "quality") -> DataFrame:
    """docs that are not rejected, all columns kept."""
    network = trained(train_docs, labels, key, text, label)
    column = docs.columns.index(text)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(_scores(network, batch.column(column)) >= THRESHOLD))

    return docs.mapInArrow(keep, docs.schema)
