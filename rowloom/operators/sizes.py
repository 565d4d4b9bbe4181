"""Exact sizes, in bits, of column codecs over a reordered table. All take code columns.

Output rows are (method, codec, col, bits). n and the distinct counts N are a few numbers from the
table and its dictionary. Block codes are costed where the rows are: only the codes of blocks that
two tasks or batches share leave them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.functions.bits import (
    binary_length,
    bits_of,
    elias_delta_bits,
    golomb_bits,
    golomb_parameter,
    vbyte_bits,
)
from rowloom.operators.position import neighbours
from rowloom.operators.runs import few_rows, rle_encode, run_count, stretches

BLOCK = 128
#: Codecs whose bits are a sum over blocks of positions.
BLOCK_CODECS = ("indirect", "sparse", "prefix")
CODECS = ("dictionary", "indirect", "sparse", "prefix", "rle", "rle_pair", "rle_nested", "delta", "entropy")


def _counts(df: DataFrame, cols: list[str], cards: list[int] | None) -> tuple[int, list[int]]:
    aggs = [F.count("*")]
    if cards is None:
        aggs += [F.count_distinct(F.col(f"`{c}`")) + F.max(F.col(f"`{c}`").isNull().cast("int")) for c in cols]
    row = df.agg(*aggs).first()
    return row[0], cards if cards is not None else [x or 0 for x in row[1:]]


def long_codes(df: DataFrame, cols: list[str]) -> DataFrame:
    """(i, pos, code): the code columns under each other."""
    items = F.array(*[F.struct(F.lit(i).alias("i"), F.col(f"`{c}`").cast("long").alias("code")) for i, c in enumerate(cols)])
    return df.select("pos", F.explode(items).alias("x")).select("x.i", "pos", "x.code")


def _named(rows: DataFrame, method: str, codec: str, cols: list[str]) -> DataFrame:
    """Rows with `i` and `bits` in the output form; columns without a row take 0 bits."""
    names = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(c).alias("col")) for i, c in enumerate(cols)]))
    every = rows.sparkSession.range(1).select(names.alias("c")).select("c.i", "c.col")
    return F.broadcast(every).join(rows, "i", "left").select(
        F.lit(method).alias("method"), F.lit(codec).alias("codec"), "col", F.coalesce("bits", F.lit(0)).cast("long").alias("bits")
    )


def _per_column(cols: list[str], values: list[int]):  # noqa: ANN202
    """A column that is values[i] where the row's `i` is i."""
    return F.element_at(F.array(*[F.lit(int(v)).cast("long") for v in values]), F.col("i") + 1)


def size(
    df: DataFrame, codec: str, cols: list[str], method: str = "given", cards: list[int] | None = None, p: int = BLOCK,
    counter: str = "fixed", min_run: int = 0, facts: dict[str, list[int]] | None = None,
) -> DataFrame:
    """Bits of every column under `codec`; `cards` are the distinct counts (counted if not given).

    `facts` are a `survey` of the same rows, columns and distinct counts: what it summed is not summed again."""
    n, cards = (facts["rows"][0], cards) if facts and cards is not None else _counts(df, cols, cards)
    width = _per_column(cols, [bits_of(x) for x in cards])
    if codec == "dictionary":
        rows = few_rows(df.sparkSession, [n * bits_of(x) for x in cards], "bits")
    elif codec in BLOCK_CODECS and facts:
        rows = few_rows(df.sparkSession, facts[codec], "bits")
    elif codec in BLOCK_CODECS:
        rows = _block_bits(df, codec, cols, [bits_of(x) for x in cards], p)
    elif codec in ("rle", "rle_pair", "rle_nested"):
        counted = run_count(df, cols, nested=codec == "rle_nested", facts=facts)
        index = F.array_position(F.array(*[F.lit(c) for c in cols]), F.col("col")).cast("int") - 1
        each = width + bits_of(n) * (1 if codec == "rle_pair" else 2)
        rows = counted.withColumn("i", index).select("i", (F.col("runs") * each).alias("bits"))
    elif codec == "delta":
        both = neighbours(df.select("pos", *[F.col(f"`{c}`") for c in cols]), cols)
        costs = [F.sum(_delta_bits(c)).alias(f"d{i}") for i, c in enumerate(cols)]
        one = both.agg(*costs)
        rows = one.select(F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.col(f"d{i}").alias("bits")) for i in range(len(cols))])).alias("x")).select("x.i", "x.bits")
    elif codec == "entropy":
        per_code = long_codes(df, cols).groupBy("i", "code").agg(F.count("*").alias("k"))
        rows = per_code.groupBy("i").agg(F.ceil(F.sum(-F.col("k") * F.log2(F.col("k") / F.lit(float(max(n, 1)))))).alias("bits"))
    else:
        raise ValueError(f"codec is one of {CODECS}")
    return _named(rows, method, codec, cols)


def block_costs(blocks: np.ndarray, codec: str, width: int, p: int) -> np.ndarray:
    """Bits of each row of `blocks`, a coding block of codes of `width` bits; `p` is the nominal block size."""
    m, n = blocks.shape
    if codec == "prefix":
        differs = blocks != blocks[:, :1]
        first = np.where(differs.any(axis=1), differs.argmax(axis=1), n)
        return bits_of(p) + width + (n - first) * width
    rank = np.sort(blocks, axis=1)
    new = np.ones((m, n), bool)
    new[:, 1:] = rank[:, 1:] != rank[:, :-1]
    own = new.sum(axis=1)
    if codec == "indirect":
        return own * width + n * np.array([bits_of(k) for k in range(n + 1)])[own]
    starts = np.flatnonzero(new.ravel())
    lengths = np.diff(np.append(starts, m * n))
    top = np.maximum.reduceat(lengths, np.concatenate([[0], np.cumsum(own)[:-1]]))
    return (n - top + 1) * width + n


def _block_bits(df: DataFrame, codec: str, cols: list[str], widths: list[int], p: int) -> DataFrame:
    """(i, bits): the costs of whole blocks of `p` positions, summed where they are, and of those put together from pieces."""

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            pos = batch.column(0).to_numpy().astype("int64")
            rows: list[tuple] = []
            totals = [0] * len(cols)
            codes = [c.to_numpy(zero_copy_only=False).astype("int64") for c in batch.columns[1:]]
            for lo, hi in zip(*stretches(pos), strict=True):
                a = min(hi, lo + -int(pos[lo]) % p)
                b = a + (hi - a) // p * p
                for i, c in enumerate(codes):
                    if b > a:
                        totals[i] += int(block_costs(c[a:b].reshape(-1, p), codec, widths[i], p).sum())
                    rows += [(i, int(pos[x] // p), None, int(pos[x]), c[x:y]) for x, y in ((lo, a), (b, hi)) if y > x]
            rows += [(i, -1, t, 0, []) for i, t in enumerate(totals) if t]
            if rows:
                kinds = (pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()))
                columns = [pa.array(x, k) for x, k in zip(zip(*rows, strict=True), kinds, strict=True)]
                yield pa.RecordBatch.from_arrays(columns, names=["i", "cblock", "bits", "first", "codes"])

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            i, bits = batch.column(0).to_pylist(), []
            for k, b, parts in zip(i, batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                if b is None:
                    codes = np.array([[x for part in parts for x in part["codes"]]], "int64")
                    b = int(block_costs(codes, codec, widths[k], p)[0])
                bits.append(b)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(bits, pa.int64())], names=["i", "bits"])

    codes = df.select("pos", *[F.col(f"`{c}`").cast("long").alias(f"c{j}") for j, c in enumerate(cols)])
    found = codes.mapInArrow(pieces, "i int, cblock long, bits long, first long, codes array<long>")
    # a block has p codes at most, whatever the number of its pieces
    joined = found.groupBy("i", "cblock").agg(F.sum("bits").alias("bits"), F.sort_array(F.collect_list(F.when(F.col("bits").isNull(), F.struct("first", "codes")))).alias("parts"))
    return joined.select("i", "bits", "parts").mapInArrow(whole, "i int, bits long").groupBy("i").agg(F.sum("bits").alias("bits"))


def _delta_bits(c: str):  # noqa: ANN202
    """A first code as it is, then a sign bit and the absolute difference where it is not 0."""
    now, before = F.col(f"`{c}`").cast("long"), F.col(f"`prev_{c}`").cast("long")
    gap = F.abs(now - before)
    return F.when(~F.col("has_neighbour"), binary_length(now)).otherwise(binary_length(gap) + (gap > 0).cast("int")).cast("long")


def size_rle_counters(df: DataFrame, col: str, counter: str, card: int, method: str = "given", min_run: int = 0) -> DataFrame:
    """Bits of one column as (value, length) runs, with a coded length; runs under `min_run` rows stand verbatim.

    Counters: fixed, vbyte, elias_delta, golomb. With `min_run`, every entry has a bit that tells
    a run from a verbatim value."""
    runs = rle_encode(df, col)
    row = runs.agg(F.sum("len").alias("n"), F.avg("len").alias("mean")).first()
    n, length = row["n"] or 0, F.col("len")
    width = bits_of(card)
    coded = {
        "fixed": lambda: F.lit(bits_of(n)),
        "vbyte": lambda: vbyte_bits(length),
        "elias_delta": lambda: elias_delta_bits(length),
        "golomb": lambda: golomb_bits(length, golomb_parameter(row["mean"] or 1.0)),
    }[counter]()
    entry = coded + width + (1 if min_run else 0)
    cost = F.when(length < min_run, length * (width + 1)).otherwise(entry) if min_run else entry
    got = runs.agg(F.sum(cost.cast("long")).alias("bits"))
    return got.select(
        F.lit(method).alias("method"), F.lit(f"rle_{counter}" + (f"_min{min_run}" if min_run else "")).alias("codec"),
        F.lit(col).alias("col"), F.coalesce("bits", F.lit(0)).cast("long").alias("bits"),
    )


def compression_ratio(base: DataFrame, other: DataFrame) -> DataFrame:
    """(codec, method, ratio): total bits of `base` over those of `other`; above 1, `other` is smaller."""
    a = base.groupBy("codec").agg(F.sum("bits").alias("base_bits"))
    b = other.groupBy("codec", "method").agg(F.sum("bits").alias("bits"))
    return b.join(a, "codec").select("codec", "method", F.round(F.col("base_bits") / F.col("bits"), 6).alias("ratio"))
