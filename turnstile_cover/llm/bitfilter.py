"""A set of 64-bit hashes as a bitmap of bounded size, with false positives but no false negatives."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

BUCKET = 32_768  # bits in one row of Spark's bitmap aggregate
MAX_BITS = 27
STEP = 13  # shift between the places of a hash


class BitFilter:
    """places: bits that every hash sets; all of them must be set for a hit."""

    def __init__(self, bits: int, data: np.ndarray, places: int = 1):
        self.bits, self.data, self.places = bits, data, places

    def __contains__(self, hashes: np.ndarray) -> np.ndarray:  # pragma: no cover
        raise TypeError("use holds()")

    def holds(self, hashes: np.ndarray) -> np.ndarray:
        h, out = hashes.view(np.int64), np.ones(len(hashes), bool)
        for p in range(self.places):
            at = ((h >> (STEP * p)) ^ (h << (STEP * p))) & ((1 << self.bits) - 1) if p else h & ((1 << self.bits) - 1)
            out &= (self.data[at >> 3] >> (at & 7).astype(np.uint8) & 1).astype(bool)
        return out


def build(hashes: DataFrame, column: str, each: int = 8, max_bits: int = MAX_BITS, places: int = 1) -> BitFilter:
    """About so many bits each, 2**max_bits bits (16 MB) at most: beyond that more false positives, which later joins drop.

    places: bits set by each hash; with ten bits a hash four places let a fiftieth of the others pass. Past max_bits fewer are set.
    """
    n = hashes.count()
    bits = min(max_bits, max(15, (each * max(n, 1)).bit_length()))
    places = max(1, min(places, round(0.7 * (1 << bits) / max(n, 1))))
    h = F.col(column)
    spots = [(h if not p else F.shiftright(h, STEP * p).bitwiseXOR(F.shiftleft(h, STEP * p))).bitwiseAND((1 << bits) - 1) + 1 for p in range(places)]
    rows = hashes.select((spots[0] if places == 1 else F.explode(F.array(*spots))).alias("p")).groupBy(F.bitmap_bucket_number("p").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("m")).collect()
    data = np.zeros((1 << bits) // 8, np.uint8)
    for b, m in rows:
        at = (b - 1) * BUCKET // 8
        data[at : at + BUCKET // 8] = np.frombuffer(bytes(m), np.uint8)
    return BitFilter(bits, data, places)


def text_key(text: str = "text") -> Column:
    """Tells apart different texts under one id."""
    return F.xxhash64(F.coalesce(F.col(text), F.lit("")))
