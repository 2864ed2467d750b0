"""A Bloom filter over hashed keys, of bounded size, that saves shuffling rows which match nothing."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_MOST_BITS = 29  # 64 MB: beyond about 50 million keys it only gets less selective
_LEAST_BITS = 16


@dataclass(frozen=True)
class KeyFilter:
    mask: int
    words: np.ndarray

    def has(self, hashes: np.ndarray) -> np.ndarray:
        """For 64-bit hashes: False only where the key is surely absent."""
        h = np.asarray(hashes).astype(np.int64).view(np.uint64)
        out = np.ones(len(h), dtype=bool)
        for shift in (0, 30):
            p = (h >> np.uint64(shift)) & np.uint64(self.mask)
            out &= ((self.words[(p >> np.uint64(6)).astype(np.int64)].view(np.uint64) >> (p & np.uint64(63))) & np.uint64(1)).astype(bool)
        return out


def key_filter(keys: DataFrame, hash_col: str) -> KeyFilter:
    """A filter of the 64-bit hashes in a column; eight bits a key up to 64 MB."""
    count = keys.count()
    mask = (1 << int(min(_MOST_BITS, max(_LEAST_BITS, np.ceil(np.log2(8 * max(count, 1))))))) - 1
    h = F.col(hash_col)
    bit = F.explode(F.array(h.bitwiseAND(F.lit(mask)), F.shiftrightunsigned(h, 30).bitwiseAND(F.lit(mask))))
    words = keys.select(bit.alias("p")).groupBy(F.shiftright("p", 6).alias("w")).agg(F.expr("bit_or(shiftleft(1L, cast(p & 63 as int)))").alias("bits")).toArrow()
    table = np.zeros((mask + 1) >> 6, dtype=np.int64)
    table[words.column("w").to_numpy()] = words.column("bits").to_numpy()
    return KeyFilter(mask, table)
