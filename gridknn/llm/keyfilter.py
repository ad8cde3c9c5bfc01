"""A filter of fixed size over 64-bit keys, built in Spark and tested in numpy.

It may let other keys pass (then a later join drops their rows) but never loses one. Its
size is a parameter and doesn't grow with the data: beyond its capacity it lets more pass.
"""

from __future__ import annotations

import numpy as np
from pyspark.broadcast import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import shuffles_removed

BITS = 26


def key_filter(df: DataFrame, column: str, bits: int = BITS) -> Broadcast:
    """Broadcast of 2**bits bits (8 MB at 26) that hold two marks for each key; keys must be well mixed longs."""
    mask = (1 << bits) - 1
    key = F.col(column)
    places = df.select(F.explode(F.array(key.bitwiseAND(F.lit(mask)), F.shiftrightunsigned(key, 64 - bits))).alias("p"))
    word = F.shiftright("p", 6).alias("w")
    with shuffles_removed(df.sparkSession):
        marks = places.groupBy(word).agg(F.bit_or(F.expr("shiftleft(1L, cast(p & 63 as int))")).alias("m")).toArrow()
    words = np.zeros(1 << (bits - 6), np.uint64)
    words[marks.column("w").to_numpy()] = marks.column("m").to_numpy().view(np.uint64)
    return df.sparkSession.sparkContext.broadcast(words)


def passes(words: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Which keys (int64 or uint64) may be in the filter."""
    keys = keys.view(np.uint64)
    bits = np.uint64(len(words).bit_length() + 5)
    out = np.ones(len(keys), bool)
    for p in (keys & np.uint64((1 << int(bits)) - 1), keys >> (np.uint64(64) - bits)):
        out &= (words[(p >> np.uint64(6)).astype(np.int64)] >> (p & np.uint64(63))) & np.uint64(1) == 1
    return out
