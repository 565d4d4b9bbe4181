"""Seeded tables with Zipfian, uniform and correlated columns.

Exact mode uses integers only (hashed ids, integer weights), so that any engine gives the same rows."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# A Mersenne prime, multipliers of the integer hash, and the scale of Zipf weights.
PRIME, M1, M2, S1, S2, SCALE = 2_147_483_647, 48_271, 69_621, 7_919, 104_729, 1_000_000_000


def hash_column(key: Column, salt: int) -> Column:
    """A hash of a non-negative integer below 2**62, from integer products and remainders."""
    x = ((key + 1) * M1 + salt * S1) % PRIME
    y = (x * x + salt * S2 + 1) % PRIME
    z = (y * M2 + x) % PRIME
    w = (z * z + y) % PRIME
    return z * 2_147_483_648 + w


def hash_sql(key: str, salt: int) -> str:
    """The same hash as SQL text."""
    x = f"((({key} + 1) * {M1} + {salt * S1}) % {PRIME})"
    y = f"(({x} * {x} + {salt * S2 + 1}) % {PRIME})"
    z = f"(({y} * {M2} + {x}) % {PRIME})"
    w = f"(({z} * {z} + {y}) % {PRIME})"
    return f"({z} * 2147483648 + {w})"


def hash_values(key: np.ndarray, salt: int) -> np.ndarray:
    """The same hash of 64-bit integers; remainders have the sign of the dividend, as in SQL."""
    x = np.fmod((key + 1) * M1 + salt * S1, PRIME)
    y = np.fmod(x * x + salt * S2 + 1, PRIME)
    z = np.fmod(y * M2 + x, PRIME)
    return z * 2_147_483_648 + np.fmod(z * z + y, PRIME)


def mixed_values(key: np.ndarray, salt: int, share: int, octaves: int) -> np.ndarray:
    """0 in `share` hundredths of the keys, else a random octave of `octaves` and a value in it."""
    h, g = hash_values(key, salt), hash_values(key, salt + 1)
    size = np.left_shift(np.int64(1), np.fmod(h >> 20, octaves))
    return np.where(np.fmod(h, 100) < share, 0, size + np.fmod(g, size))


@lru_cache(maxsize=4)
def zipf_steps(n: int) -> np.ndarray:
    """Running sums of the weights SCALE div i, i = 1 .. n."""
    return np.cumsum(SCALE // np.arange(1, n + 1, dtype="int64"))


def zipf_value(h: Column, n: int) -> Column:
    """1 .. n with probability in proportion to 1 / value, from a hash."""
    total = int(zipf_steps(n)[-1])

    @F.pandas_udf("int")
    def lookup(at: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(zipf_steps(n), at.to_numpy("int64"), "right").astype("int32") + 1)

    return lookup(h % total)


def zipf_table(spark: SparkSession, n: int, c: int = 4, seed: int = 42, mode: str = "exact") -> DataFrame:
    """id and c independent Zipfian columns c1.. on n possible values."""
    ids = spark.range(n)
    if mode == "exact":
        return ids.select("id", *[zipf_value(hash_column(F.col("id"), seed + j), n).alias(f"c{j + 1}") for j in range(c)])
    if mode != "rand":
        raise ValueError("mode is exact or rand")
    steps = zipf_steps(n)
    total = float(steps[-1])

    @F.pandas_udf("int")
    def inverse(u: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(zipf_steps(n), (u.to_numpy() * total).astype("int64"), "right").astype("int32") + 1)

    return ids.select("id", *[inverse(F.rand(seed + j)).alias(f"c{j + 1}") for j in range(c)])


def uniform_table(spark: SparkSession, n: int, c: int = 4, seed: int = 42, mode: str = "exact") -> DataFrame:
    """id and c independent uniform columns on n possible values."""
    ids = spark.range(n)
    if mode == "exact":
        return ids.select("id", *[(hash_column(F.col("id"), seed + j) % n).cast("int").alias(f"c{j + 1}") for j in range(c)])
    return ids.select("id", *[F.floor(F.rand(seed + j) * n).cast("int").alias(f"c{j + 1}") for j in range(c)])


def skewed_lineitem(lineitem: DataFrame, c: int = 4, support: int = 4096, seed: int = 7) -> DataFrame:
    """Zipfian columns keyed by (l_orderkey, l_linenumber), so that rows that share a key are duplicates."""
    key = F.col("l_orderkey") * 8 + F.col("l_linenumber")
    return lineitem.select(
        "l_orderkey", "l_linenumber", *[zipf_value(hash_column(key, seed + j), support).alias(f"c{j + 1}") for j in range(c)]
    )


def correlated_table(spark: SparkSession, n: int, c: int = 6, rho: float = 0.75, support: int = 4096, seed: int = 11) -> DataFrame:
    """Columns that copy the first with probability `rho` (in 1/1000) and are Zipfian otherwise; rows with equal ids mod 4 of 5 repeat."""
    ids = spark.range(n).withColumn("k", F.col("id") - F.col("id") % 5 % 2)
    first = ids.withColumn("c1", zipf_value(hash_column(F.col("k"), seed), support))
    cut = int(rho * 1000)
    cols = [
        F.when(hash_column(F.col("k"), seed + 100 + j) % 1000 < cut, F.col("c1")).otherwise(zipf_value(hash_column(F.col("k"), seed + j), support)).alias(f"c{j + 1}")
        for j in range(1, c)
    ]
    return first.select("id", "c1", *cols)


def grid_table(spark: SparkSession, cards: list[int]) -> DataFrame:
    """All tuples of {1..N1} x .. x {1..Nc}, columns c1.., one range and integer arithmetic."""
    total = int(np.prod(cards))
    cols, base = [], total
    for j, n in enumerate(cards):
        base //= n
        cols.append((F.floor(F.col("id") / base) % n + 1).cast("int").alias(f"c{j + 1}"))
    return spark.range(total).select(*cols)
