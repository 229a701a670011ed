"""A bit set of hashed keys that is built by an aggregate and has a proven bound of size.

It only saves shuffling rows that have no partner: what passes wrongly is dealt with exactly later, so the results don't
depend on its size. Beyond MOST_BITS it lets more rows pass, nothing else changes.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordwork.llm.common import tidy

LEAST_BITS, MOST_BITS = 1 << 20, 1 << 29
BITS_PER_KEY = 16


def build(keys: DataFrame, n: int):
    """Broadcast array of 64-bit words for the one long column of keys; n: about how many keys there are."""
    bits = 1 << min(max(int(n * BITS_PER_KEY).bit_length(), LEAST_BITS.bit_length() - 1), MOST_BITS.bit_length() - 1)
    at = F.col(keys.columns[0]).bitwiseAND(F.lit(bits - 1))
    words = keys.select(F.shiftright(at, 6).alias("word"), F.call_function("shiftleft", F.lit(1).cast("long"), at.bitwiseAND(F.lit(63)).cast("int")).alias("bit"))
    with tidy(keys.sparkSession):
        rows = words.groupBy("word").agg(F.bit_or("bit").alias("bits")).toArrow()  # at most bits / 64 rows
    out = np.zeros(bits // 64, np.uint64)
    out[rows["word"].to_numpy()] = rows["bits"].to_numpy().view(np.uint64)
    return keys.sparkSession.sparkContext.broadcast(out)


def test(words: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """For each uint64 key, whether its bit is set."""
    at = keys & np.uint64(len(words) * 64 - 1)
    return (words[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63))) & np.uint64(1) == 1
