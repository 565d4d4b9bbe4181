"""Global row positions without gathering rows in one task, and access to rows by position.

A sorted frame is written once with its partition number and the offset in it; the counts of
partitions, a few numbers each, give the base of every partition."""

from __future__ import annotations

from itertools import accumulate

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from rowloom.sources.scratch import written

#: Rows of a window that looks at neighbours by position.
SPAN = 1 << 16


def numbered(df: DataFrame, name: str = "pos") -> DataFrame:
    """`df` with 0-based positions in its present order: partitions in turn, rows as they stand."""
    fixed = written(df.withColumn("__at", F.monotonically_increasing_id()), "ordered")
    part = F.shiftright("__at", 33)
    counts = fixed.groupBy(part.alias("__part")).count().orderBy("__part").collect()
    bases = [0, *accumulate(r["count"] for r in counts)][: len(counts)]
    if len(counts) <= 1:
        return fixed.withColumn(name, F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))).drop("__at")
    spark = df.sparkSession
    table = spark.createDataFrame(
        pd.DataFrame({"__part": [r["__part"] for r in counts], "__base": bases}), "__part long, __base long"
    )
    return (
        fixed.withColumn("__part", part)
        .join(F.broadcast(table), "__part")
        .withColumn(name, F.col("__base") + F.col("__at").bitwiseAND(F.lit((1 << 33) - 1)))
        .drop("__at", "__part", "__base")
    )


def sorted_with_positions(df: DataFrame, keys: list[Column], name: str = "pos", partitions: int | None = None, drop: list[str] | None = None) -> DataFrame:
    """`df` range-partitioned and sorted by `keys`, with global positions. Keys that tie to the end
    leave the order open, so callers close them with columns that tell rows apart. `drop` goes after the sort."""
    if not keys:
        return numbered(df.drop(*(drop or [])), name)
    dealt = df.repartitionByRange(partitions, *keys) if partitions else df.repartitionByRange(*keys)
    return numbered(dealt.sortWithinPartitions(*keys).drop(*(drop or [])), name)


def neighbours(df: DataFrame, cols: list[str], step: int = -1, pos: str = "pos", by: list[str] | None = None, span: int = SPAN) -> DataFrame:
    """`df` with, for each column, `prev_<c>` (step -1) or `next_<c>` (step 1): the value at the next
    position before or after, and `has_neighbour`. `by` keeps separate position sequences apart.

    Windows hold `span` positions; the row at a border is also sent to the window beside it, so no
    window grows with the data."""
    by = by or []
    block = F.floor(F.col(pos) / span)
    edge = (F.col(pos) + 1) % span == 0 if step < 0 else F.col(pos) % span == 0
    own = df.withColumn("__block", block).withColumn("__guest", F.lit(False))
    guests = df.where(edge).withColumn("__block", block - step).withColumn("__guest", F.lit(True))
    w = W.partitionBy(*by, "__block").orderBy(pos)
    look, word = (F.lag, "prev_") if step < 0 else (F.lead, "next_")
    both = own.union(guests)
    found = both.select("*", look(F.lit(True)).over(w).alias("__has"), *(look(c).over(w).alias(word + c) for c in cols))
    return found.where(~F.col("__guest")).withColumn("has_neighbour", F.coalesce("__has", F.lit(False))).drop("__has", "__block", "__guest")


def assign_blocks(df: DataFrame, rows: int | None = None, by: list[str] | None = None, shift: int = 0, pos: str = "pos") -> DataFrame:
    """`block_id`: positions cut every `rows` rows (moved by `shift`), with `by` also wherever its values
    differ. Ids count from 0 in the order of the blocks' first positions."""
    if not rows:
        raise ValueError("blocks need a bound on their rows")
    cut = F.floor((F.col(pos) + shift) / rows)
    if not by:
        return df.withColumn("block_id", cut.cast("long"))
    keys = {f"__b{i}": F.col(f"`{c}`") for i, c in enumerate(by)} | {"__cut": cut}
    groups = df.groupBy(*[v.alias(k) for k, v in keys.items()]).agg(F.min(pos).alias("__first"))
    ids = sorted_with_positions(groups, [F.asc("__first")], "block_id").drop("__first")
    same = F.lit(True)
    for k, v in keys.items():
        same = same & v.eqNullSafe(F.col(k))
    # a block is one value of `by` and one cut, so no key of this join has more than `rows` rows
    return df.join(ids, same).select(*[F.col(f"`{c}`") for c in df.columns], "block_id")
