"""Fixed-size bitmaps of keys: they prune a scan before its rows are shuffled.

A bitmap has 2**bits bits whatever the data hold, so what is broadcast is bounded. Where it fills up
it prunes less and nothing else changes: what passes wrongly finds no partner later."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LOG_BITS = 23


def slot(keys: np.ndarray, bits: int = LOG_BITS) -> np.ndarray:
    h = keys.astype(np.int64)
    return (h ^ (h >> bits)) & ((1 << bits) - 1)


def id_bitmap(keys: DataFrame, column: str, bits: int = LOG_BITS) -> np.ndarray:
    """Bits of every key in ``column``; one aggregation, at most 2**(bits-6) rows to the driver."""
    h = F.col(column).bitwiseXOR(F.shiftright(F.col(column), bits)).bitwiseAND(F.lit((1 << bits) - 1).cast("long"))
    words = (
        keys.where(F.col(column).isNotNull())
        .select(h.alias("h"))
        .groupBy(F.expr("shiftright(h, 6)").alias("w"))
        .agg(F.bit_or(F.expr("shiftleft(1L, cast(h & 63 as int))")).alias("b"))
        .toArrow()
    )
    out = np.zeros(1 << (bits - 6), np.uint64)
    out[words["w"].to_numpy()] = words["b"].to_numpy().view(np.uint64)
    return out


def maybe_in(bitmap: np.ndarray, keys: np.ndarray) -> np.ndarray:
    h = slot(keys, len(bitmap).bit_length() + 5)
    return (bitmap[h >> 6] >> (h & 63).astype(np.uint64)) & np.uint64(1) == 1
