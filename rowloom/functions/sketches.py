"""Reading what Spark's sketch aggregates write."""

from __future__ import annotations

import struct

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

# Fixed value: the prime of the sketch's row hashes.
_PRIME = (1 << 31) - 1


class CountMin:
    """A serialised count-min sketch: version, total, depth, width, a multiplier and `width` counters for each row."""

    def __init__(self, data: bytes):
        version, self.total, depth, self.width = struct.unpack_from(">iqii", data)
        if version != 1:
            raise ValueError(f"count-min version {version}")
        at = 20
        self.factors = [int(x) for x in np.frombuffer(data, ">i8", depth, at)]
        self.table = np.frombuffer(data, ">i8", depth * self.width, at + 8 * depth).reshape(depth, self.width)

    def estimate(self, item: int) -> int:
        """Never less than the item's count."""
        return min(int(row[self._place(f, item)]) for f, row in zip(self.factors, self.table, strict=True))

    def _place(self, factor: int, item: int) -> int:
        x = (factor * item) & ((1 << 64) - 1)
        x = x - (1 << 64) if x >> 63 else x
        x = x + (x >> 32)
        return (x & _PRIME) % self.width


def count_min_estimate(sketch: str, item: str) -> Column:
    """The estimated count of each integer item; rows of one batch mostly share the sketch, which is read once."""

    @F.pandas_udf("long")
    def run(data: pd.Series, items: pd.Series) -> pd.Series:
        known: dict[bytes, CountMin] = {}
        out = []
        for d, x in zip(data, items, strict=True):
            d = bytes(d)
            if d not in known:
                known = {d: CountMin(d)}
            out.append(known[d].estimate(int(x)))
        return pd.Series(out, dtype="int64")

    return run(F.col(sketch), F.col(item))
