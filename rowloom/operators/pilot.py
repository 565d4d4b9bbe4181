"""Predicting gains: a pilot on some blocks, a row sample, and columns shuffled apart."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.operators.blocks import BLOCK_ROWS, block_log, kernel, run_blocks
from rowloom.operators.order import order_by
from rowloom.operators.position import sorted_with_positions
from rowloom.operators.runs import total_runs
from rowloom.sources.scratch import written


def pilot_gain(df: DataFrame, cols: list[str], blocks: int = 20, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """One row (blocks, runs_before, runs_after, gain) of list walks in the first blocks only."""
    coded = order_by(df, "lexicographic", cols, keep_codes=True)
    names = [c for c in coded.columns if c.endswith("__code")]
    first = coded.where(F.col("pos") < blocks * block_rows)
    log = block_log(first, run_blocks(first, [kernel("multiple_lists")], names, block_rows), names, block_rows)
    return log.agg(
        F.count("*").alias("blocks"), F.sum("runs_before").alias("runs_before"), F.sum("runs_after").alias("runs_after"),
        F.round(F.sum("runs_before") / F.sum("runs_after"), 6).alias("gain"),
    )


def row_sample(df: DataFrame, rows: int, seed: int = 0) -> DataFrame:
    """`rows` rows (all, if there are no more), each as likely as any other, equal ones too.

    Rows of a written copy are numbered and the smallest hashes of the numbers taken; a bound on the
    hash, from the count, lets little more than `rows` reach the sort, however many tasks there are."""
    numbered = written(df.withColumn("__row", F.monotonically_increasing_id()), "rows")
    n = numbered.count()
    unit = F.pmod(F.xxhash64("__row", F.lit(seed)), F.lit(1 << 52))
    if n <= rows:
        return numbered.drop("__row")
    numbered = numbered.where(unit < F.lit(int(min(1.0, (rows + 8 * rows**0.5 + 100) / n) * (1 << 52))))
    return numbered.orderBy(unit, "__row").limit(rows).drop("__row")


def sample_gain(df: DataFrame, cols: list[str], rows: int = 65_536, seed: int = 0, order: str = "interleave") -> float:
    """The gain of an order on a row sample: kept as a warning, since it misleads."""
    part = row_sample(df, rows, seed)
    return total_runs(order_by(part, "lexicographic", cols), cols) / max(1, total_runs(order_by(part, order, cols), cols))


def shuffle_columns(df: DataFrame, cols: list[str], id_col: str, seed: int = 0) -> DataFrame:
    """(pos, cols): every column permuted on its own, which keeps histograms and breaks correlations."""
    out = None
    for i, c in enumerate(cols):
        one = sorted_with_positions(df.select(id_col, c), [F.xxhash64(id_col, F.lit(seed + i)).asc(), F.asc(id_col)]).select("pos", c)
        out = one if out is None else out.join(one, "pos")
    return out
