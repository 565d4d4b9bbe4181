"""Shards of near-equal bytes by sampled splitters: size-weighted key samples, quantile
boundaries, range partition, and subdivision of overfull ranges."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from rowloom.llm.shared import utf8, written

#: Ranges for each shard, sampled keys for each range, and hash cells that a range can be cut into.
RANGES, SAMPLES, CELLS = 32, 16, 64
#: Times the mean bytes of a range over which it is subdivided.
OVERFULL = 2.0


def weighted_sample(rows: DataFrame, key: str, size: str, tie: Column, count: int, n: int) -> np.ndarray:
    """Sorted keys of `count` of the n rows drawn without replacement with chances that follow `size`.

    Exponential clocks: the rows whose hash-derived exponential time over size is least. A bound on
    the clock, from a histogram of sizes, lets little more than `count` rows reach the sort, however
    many tasks there are."""
    unit = (F.pmod(tie, F.lit(1 << 52)).cast("double") + 0.5) / F.lit(float(1 << 52))
    clock = -F.log(unit) / F.col(size).cast("double")
    timed = rows.select(F.col(key).alias("key"), F.col(size).alias("size"), clock.alias("clock"))
    if n > 4 * count:
        octaves = timed.groupBy(F.floor(F.log2("size")).alias("octave")).agg(F.count("*").alias("n")).collect()
        timed = timed.where(F.col("clock") <= F.lit(clock_bound([(r["octave"], r["n"]) for r in octaves], 1.2 * count + 10 * count**0.5)))
    got = timed.orderBy("clock", "key").limit(count).toPandas()
    return np.sort(got["key"].to_numpy("int64"))


def clock_bound(octaves: list[tuple[int, int]], count: float) -> float:
    """A clock under which at least `count` rows are expected, of `n` rows of sizes from 2 ** octave each."""
    low, high = 0.0, 1.0
    expected = lambda t: sum(n * -np.expm1(-t * 2.0**o) for o, n in octaves)
    while expected(high) < count and high < 1e300:
        high *= 2
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if expected(mid) < count else (low, mid)
    return high


def splitters(sample: np.ndarray, ranges: int) -> np.ndarray:
    """Up to ranges - 1 distinct quantile boundaries of a sorted sample."""
    if not len(sample):
        return np.empty(0, "int64")
    return np.unique(sample[(np.arange(1, ranges) * len(sample)) // ranges])


def shard_documents(
    docs: DataFrame, shards: int = 8, id_col: str = "doc_id", text_col: str = "text", ranges: int | None = None
) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row.

    size is the UTF-8 length plus 1 (null: 1). Sampled splitters cut the ids in ranges of near-equal
    bytes, overfull ones are subdivided by hash cells, and a range whose bytes lie in one shard's equal
    part of all bytes goes there whole. The few that lie across two parts are cut at the row (by id,
    then content) whose first byte is in the next part, so a shard is less than one row's size from
    its equal part. Slots count from 0 in that order. Null ids sort first; repeated rows are rows of
    their own, dealt over cells; an empty table gives no rows; extra columns are ignored. `ranges`
    should follow the row count, so that a range is one task's sort. To the driver go
    ranges * SAMPLES keys, ranges * CELLS sums, and one row for each shard."""
    ranges = shards * RANGES if ranges is None else ranges
    text = utf8(text_col)
    # the narrow columns once: texts are read once, and rows that are alike get numbers of their own
    rows = written(
        docs.select(
            F.col(id_col).cast("long").alias("doc_id"),
            (F.octet_length(text) + F.lit(1)).cast("long").alias("size"),
            F.crc32(text).alias("text_crc32"),
            F.monotonically_increasing_id().alias("row"),
        ).withColumn("sort_key", F.coalesce("doc_id", F.lit(-(1 << 63)))),
        "sizes",
    )
    tie = F.xxhash64("doc_id", "text_crc32", "size", "row")
    cuts = splitters(weighted_sample(rows, "sort_key", "size", tie, ranges * SAMPLES, rows.count()), ranges)

    @F.pandas_udf("int")
    def range_of(key: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(cuts, key.to_numpy("int64"), "right").astype("int32"))

    placed = rows.withColumn("range", range_of("sort_key")).withColumn("cell", F.pmod(tie, F.lit(CELLS)).cast("int"))
    cells = placed.groupBy("range", "cell").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")).toPandas()
    spark = docs.sparkSession
    blocks = spark.createDataFrame(
        pd.DataFrame(whole_shards(subdivide(cells, ranges), cells, shards), columns=["range", "cell", "block", "base_bytes", "base_rows", "whole"]),
        "range int, cell int, block int, base_bytes long, base_rows long, whole int",
    )
    total = int(cells["bytes"].sum()) if len(cells) else 0
    order = W.partitionBy("block").orderBy("sort_key", "text_crc32", "size", "row")
    before = F.coalesce(F.sum("size").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    part = F.expr(f"cast((at * {shards}) div {max(1, total)} as int)")
    numbered = (
        placed.join(F.broadcast(blocks), ["range", "cell"])
        .withColumn("at", F.col("base_bytes") + before)
        .withColumn("row", F.col("base_rows") + F.row_number().over(order) - 1)
        .withColumn("shard", F.when(F.col("whole") >= 0, F.col("whole")).otherwise(F.least(part, F.lit(shards - 1))))
        .select("doc_id", "size", "text_crc32", "shard", "row")
    )
    numbered = written(numbered, "numbered")
    first = numbered.groupBy("shard").agg(F.min("row").alias("first_row"))
    return numbered.join(F.broadcast(first), "shard").select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard",
        (F.col("row") - F.col("first_row")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"),
    )


def whole_shards(placed: list[tuple[int, int, int, int, int]], cells: pd.DataFrame, shards: int) -> list[tuple[int, int, int, int, int, int]]:
    """`subdivide`'s rows with the shard that takes the whole block, or -1 where it lies across two shards' parts."""
    size = dict(zip(zip(cells["range"], cells["cell"], strict=True), cells["bytes"], strict=True))
    ends: dict[int, int] = {}
    for part, cell, block, base, _ in placed:
        ends[block] = ends.get(block, base) + int(size[(part, cell)])
    total = max([1, *ends.values()])
    out = []
    for part, cell, block, base, n in placed:
        first, last = (x * shards // total for x in (base, ends[block] - 1))
        out.append((part, cell, block, base, n, int(first) if first == last else -1))
    return out


def subdivide(cells: pd.DataFrame, ranges: int) -> list[tuple[int, int, int, int, int]]:
    """(range, cell, block, bytes before the block, rows before it): a range is one block, or several if overfull."""
    out, block, bytes_before, rows_before = [], -1, 0, 0
    target = cells["bytes"].sum() / max(1, ranges)
    for part, own in cells.sort_values(["range", "cell"]).groupby("range", sort=True):
        limit = target if own["bytes"].sum() > OVERFULL * target else float("inf")
        filled = limit
        fresh = True
        base = (0, 0)
        for cell, size, n in zip(own["cell"], own["bytes"], own["n"], strict=True):
            if fresh or filled >= limit:
                block, filled, fresh = block + 1, 0, False
                base = (bytes_before, rows_before)
            out.append((int(part), int(cell), block, *base))
            filled += size
            bytes_before += int(size)
            rows_before += int(n)
    return out
