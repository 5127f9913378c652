"""Membership bitmaps: a broadcast of 8 MB, or more where the caller says how many keys to expect, 64 MB at most.

A miss is certain, a hit only likely; whatever passes is checked exactly afterwards. When the set
outgrows the bitmap more passes it, and the result stays the same.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BITS, MOST_BITS = 26, 29  # 2^26 bits: 8 MB; 2^29: 64 MB


def bits_for(expected: int) -> int:
    """About 16 bits a key, within the two bounds."""
    return min(MOST_BITS, max(BITS, (16 * max(1, expected) - 1).bit_length()))


def build(keys: DataFrame, key: Column, expected: int = 0) -> np.ndarray:
    """The bitmap of a column of well-mixed longs, OR-ed up by an aggregate; the driver gets a row per 64 bits at most."""
    bits = bits_for(expected)
    spot = F.shiftrightunsigned(key, 64 - bits)
    words = keys.select(F.shiftright(spot, 6).cast("int").alias("w"), F.expr("1L").alias("one"), F.pmod(spot, F.lit(64)).cast("int").alias("b"))
    rows = words.groupBy("w").agg(F.bit_or(F.expr("shiftleft(one, b)")).alias("bits")).toPandas()
    out = np.zeros(1 << (bits - 6), np.int64)
    out[rows["w"].to_numpy(np.int64)] = rows["bits"].to_numpy(np.int64)
    return out.view(np.uint64)


def has(bitmap: np.ndarray, key: np.ndarray) -> np.ndarray:
    bits = 6 + (len(bitmap) - 1).bit_length()
    spot = key.astype(np.uint64, copy=False) >> np.uint64(64 - bits)
    return (bitmap[(spot >> np.uint64(6)).astype(np.int64)] >> (spot & np.uint64(63))) & np.uint64(1) != 0
