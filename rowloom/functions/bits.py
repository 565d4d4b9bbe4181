"""Integer bit arithmetic as column expressions, and the SQL functions registered from it."""

from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def bits_of(x: int) -> int:
    """ceil(log2 x): bits of a code with x values; 0 for one value or none."""
    return max(0, int(x) - 1).bit_length()


def bits(x: Column | str) -> Column:
    """ceil(log2 x) by integers only; 0 for one value or none."""
    x = F.col(x) if isinstance(x, str) else x
    return F.when(x <= 1, F.lit(0)).otherwise(F.length(F.bin(x.cast("long") - 1)))


def binary_length(x: Column | str) -> Column:
    """Digits of x >= 1 in binary; 0 for 0."""
    x = F.col(x) if isinstance(x, str) else x
    return F.when(x <= 0, F.lit(0)).otherwise(F.length(F.bin(x.cast("long"))))


def elias_delta_bits(x: Column) -> Column:
    """Bits of Elias' delta code of x >= 1."""
    n = binary_length(x)
    return n - 1 + 2 * binary_length(n) - 1


def vbyte_bits(x: Column) -> Column:
    """Bits of the variable-byte code of x >= 1: seven to a byte."""
    return F.ceil(binary_length(x) / F.lit(7)).cast("int") * 8


def golomb_bits(x: Column, m: int) -> Column:
    """Bits of the Golomb code of x >= 1 with parameter m (truncated binary remainders)."""
    b = bits_of(m)
    cut = (1 << b) - m
    q, r = F.floor((x - 1) / m), (x - 1) % m
    return (q + 1 + F.when(r < cut, F.lit(max(0, b - 1))).otherwise(F.lit(b))).cast("long")


def golomb_parameter(mean: float) -> int:
    """The parameter for geometric lengths of this mean."""
    p = 1.0 / max(mean, 1.0)
    if p >= 1.0:
        return 1
    return max(1, math.ceil(-1.0 / math.log2(1.0 - p)))


#: Names, parameters and bodies of the SQL functions.
SQL_FUNCTIONS = {
    "code_bits": ("x BIGINT", "INT", "CASE WHEN x <= 1 THEN 0 ELSE length(bin(x - 1)) END"),
    "hamming2": ("a1 BIGINT, a2 BIGINT, b1 BIGINT, b2 BIGINT", "INT", "int(NOT a1 <=> b1) + int(NOT a2 <=> b2)"),
    "interleave_item": ("code BIGINT, col BIGINT, cols BIGINT", "BIGINT", "code * cols + col"),
    "elias_delta_bits": ("x BIGINT", "INT", "length(bin(x)) - 1 + 2 * length(bin(length(bin(x)))) - 1"),
}


def register_sql(spark: SparkSession) -> None:
    """Temporary SQL functions; Catalyst inlines their bodies."""
    for name, (params, kind, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({params}) RETURNS {kind} RETURN {body}")
