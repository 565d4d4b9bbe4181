"""Sort keys of row orders, as scalar sort columns over code (or raw integer) columns.

Every order that the paper compares by a comparator is a plain sort by such columns, so Spark's
range exchange and its spilling sort do the work. Computed keys are columns before the sort: an
expression inside a sort would be evaluated at every comparison."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from rowloom.functions.bits import bits_of


@dataclass
class Keys:
    """Ascending computed keys, helper columns that they are taken from, or ready sort columns."""

    computed: list[Column] = field(default_factory=list)
    helpers: dict[str, Column] = field(default_factory=dict)
    ready: list[Column] = field(default_factory=list)


def lexicographic(codes: list[Column]) -> Keys:
    return Keys(ready=[c.asc_nulls_first() for c in codes])


def alternating(codes: list[Column]) -> Keys:
    """First column ascending, second descending, and so on."""
    return Keys(ready=[c.asc_nulls_first() if i % 2 == 0 else c.desc_nulls_last() for i, c in enumerate(codes)])


def reflected_gray(codes: list[Column]) -> Keys:
    """Snake order: a digit's direction turns with the parity of the digits before it (0-based codes)."""
    keys, before = [], F.lit(0).cast("long")
    for c in codes:
        keys.append(F.when(before % 2 == 0, c).otherwise(-c))
        before = before + c
    return Keys(keys)


def interleave(codes: list[Column]) -> Keys:
    """Whole column values interleaved: the row's (code, column) pairs in rising order, compared with
    alternating direction. Pairs are packed in one integer each; positions 2, 4, ... are negated."""
    c = len(codes)
    packed = F.sort_array(F.array(*[x.cast("long") * c + i for i, x in enumerate(codes)]))
    return Keys([F.get("__pairs", F.lit(i)) * (1 if i % 2 == 0 else -1) for i in range(c)], {"__pairs": packed})


def frequent_component(codes: list[Column], freqs: list[Column], triple: str = "freq_col_value", descending: bool = False) -> Keys:
    """The row's (frequency, column, value) triples, largest first, compared in turn. Values stand as
    codes, which rise with the value where frequencies are equal. Column and value share an integer."""
    c, rows = len(codes), []
    for i, (x, f) in enumerate(zip(codes, freqs, strict=True)):
        v = x.cast("long")
        rest = F.lit(i).cast("long") * (1 << 48) + v if triple == "freq_col_value" else v * c + i
        rows.append(F.struct(f.cast("long").alias("f"), rest.alias("r")))
    sign = -1 if descending else 1
    keys = [F.get("__triples", F.lit(i))[n] * sign for i in range(c) for n in ("f", "r")]
    return Keys(keys, {"__triples": F.sort_array(F.array(*rows), asc=False)})


def _interleaved_bits(codes: list[Column], width: int) -> list[Column]:
    """Bits from the most significant on, a bit of each column in turn."""
    return [F.shiftright(c.cast("long"), b).bitwiseAND(F.lit(1)) for b in range(width - 1, -1, -1) for c in codes]


_WORD = 60


def zorder_gray(codes: list[Column], cards: list[int]) -> Keys:
    """Rank of the interleaved bits in the binary reflected Gray code; 60 bits to a sort column.

    A Gray code is undone by exclusive-or with its own right shifts by 1, 2, 4, ...; a word after
    an odd number of ones in the words before it is complemented."""
    width = max(1, *(bits_of(n) for n in cards))
    bits = _interleaved_bits(codes, width)
    keys, ones = [], F.lit(0)
    for at in range(0, len(bits), _WORD):
        part = bits[at : at + _WORD]
        word = F.lit(0).cast("long")
        for i, bit in enumerate(part):
            word = word + F.shiftleft(bit, len(part) - 1 - i)
        full = F.lit((1 << len(part)) - 1).cast("long")
        rank = F.aggregate(F.array(*[F.lit(1 << k) for k in range(6)]), word, lambda x, k: x.bitwiseXOR(F.call_function("shiftright", x, k)))
        keys.append(F.when(ones % 2 == 1, full - rank).otherwise(rank))
        ones = ones + F.bit_count(word)
    return Keys(keys)


def hilbert_2d(x: Column, y: Column, width: int) -> Keys:
    """Distance along the plane Hilbert curve over a square of 2**width steps; no Python.

    The state of the walk down the levels is what is left of both coordinates and the distance."""
    start = F.struct(x.cast("long").alias("x"), y.cast("long").alias("y"), F.lit(0).cast("long").alias("d"))
    sides = F.array(*[F.lit(1 << b).cast("long") for b in range(width - 1, -1, -1)])

    def level(p: Column, s: Column) -> Column:
        right, up = p["x"].bitwiseAND(s) > 0, p["y"].bitwiseAND(s) > 0
        low = s - 1
        lx, ly = p["x"].bitwiseAND(low), p["y"].bitwiseAND(low)
        quarter = F.when(right, F.when(up, 2).otherwise(3)).otherwise(F.when(up, 1).otherwise(0))
        return F.struct(
            F.when(up, lx).when(right, low - ly).otherwise(ly).alias("x"),
            F.when(up, ly).when(right, low - lx).otherwise(lx).alias("y"),
            (p["d"] + s * s * quarter).alias("d"),
        )

    return Keys([F.aggregate(sides, start, level)["d"]])


def hilbert_index(codes: np.ndarray, width: int) -> np.ndarray:
    """Bits of the Hilbert rank of integer points, most significant first: n rows of width * c bits.

    Works on the axes in place, a bit plane at a time, from the most significant one."""
    x = codes.astype("int64").copy()
    n, c = x.shape
    for b in range(width - 1, 0, -1):
        low = (1 << b) - 1
        for i in range(c):
            up = (x[:, i] >> b) & 1 == 1
            turn = (x[:, 0] ^ x[:, i]) & low
            x[:, 0] = np.where(up, x[:, 0] ^ low, x[:, 0] ^ turn)
            if i:
                x[:, i] = np.where(up, x[:, i], x[:, i] ^ turn)
    for i in range(1, c):
        x[:, i] ^= x[:, i - 1]
    flip = np.zeros(n, "int64")
    for b in range(width - 1, 0, -1):
        flip ^= np.where((x[:, c - 1] >> b) & 1 == 1, (1 << b) - 1, 0)
    x ^= flip[:, None]
    planes = [(x[:, i] >> b) & 1 for b in range(width - 1, -1, -1) for i in range(c)]
    return np.stack(planes, axis=1).astype("uint8")


def hilbert(codes: list[Column], cards: list[int]) -> Keys:
    """Hilbert order of any number of columns; two columns stay in code-generated expressions."""
    width = max(1, *(bits_of(n) for n in cards))
    if len(codes) == 2 and width <= 30:
        return hilbert_2d(codes[0], codes[1], width)

    @F.pandas_udf("binary")
    def rank(parts: Iterator[tuple[pd.Series, ...]]) -> Iterator[pd.Series]:
        for columns in parts:
            x = np.stack([c.to_numpy("int64") for c in columns], axis=1)
            packed = np.packbits(hilbert_index(x, width), axis=1)
            yield pd.Series([r.tobytes() for r in packed])

    return Keys([rank(*[c.cast("long") for c in codes])])


def discriminating(codes: list[Column]) -> Keys:
    """Equal rows together, in hash order."""
    return Keys([F.xxhash64(*codes)], ready=lexicographic(codes).ready)


def shuffled(number: Column, seed: int = 0) -> Keys:
    """A hash of a row's number, so that equal rows part."""
    return Keys([F.xxhash64(number, F.lit(seed))])


#: Orders that need code columns only.
ORDERS: dict[str, Callable[[list[Column]], Keys]] = {
    "lexicographic": lexicographic,
    "alternating": alternating,
    "reflected_gray": reflected_gray,
    "interleave": interleave,
    "discriminating": discriminating,
}
