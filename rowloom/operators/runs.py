"""Runs of identical values: counts, run-length encoding and its variants, and work on encoded columns.

All of it takes a frame with `pos`. Runs are counted where the rows are: a task counts the changes
inside each stretch of successive positions that it reads, and only the two border rows of a
stretch leave it. Changes as rows come from position windows of a fixed span, so no step orders a
whole column in one task."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rowloom.operators.position import neighbours, sorted_with_positions


def change_flags(df: DataFrame, cols: list[str], nested: bool = False) -> DataFrame:
    """`pos`, the columns, and `new_<c>`: whether a run starts here. With `nested`, a run also ends
    where one of an earlier column ends, so that runs are disjoint or nested."""
    rows = neighbours(df.select("pos", *[F.col(f"`{c}`") for c in cols]), cols)
    flags, before = [], F.lit(False)
    for c in cols:
        own = ~F.col("has_neighbour") | ~F.col(f"`{c}`").eqNullSafe(F.col(f"`prev_{c}`"))
        before = before | own
        flags.append((before if nested else own).alias(f"new_{c}"))
    return rows.select("pos", *[F.col(f"`{c}`") for c in cols], *flags)


def _long(row: DataFrame, method: str, cols: list[str], values: list[str], name: str) -> DataFrame:
    """One row of totals as (method, col, value) rows."""
    pairs = F.explode(F.array(*[F.struct(F.lit(c).alias("col"), F.coalesce(F.col(f"`{v}`"), F.lit(0)).cast("long").alias(name)) for c, v in zip(cols, values, strict=True)]))
    return row.select(pairs.alias("p")).select(F.lit(method).alias("method"), "p.col", f"p.{name}")


def stretches(pos: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the stretches of successive positions."""
    cuts = np.flatnonzero(pos[1:] != pos[:-1] + 1) + 1
    return np.concatenate([[0], cuts]), np.concatenate([cuts, [len(pos)]])


def _changes(column: pa.Array) -> np.ndarray:
    """Whether each value differs from the one before it: null equals null, NaN equals NaN, and zeros are equal."""
    if pa.types.is_floating(column.type):
        missing = column.is_null().to_numpy(zero_copy_only=False)
        x = pc.fill_null(column, 0.0).to_numpy(zero_copy_only=False)
        same = (x[1:] == x[:-1]) | (np.isnan(x[1:]) & np.isnan(x[:-1]))
        return ~(same & ~missing[1:] & ~missing[:-1] | missing[1:] & missing[:-1])
    if pa.types.is_integer(column.type) and not column.null_count:
        x = column.to_numpy(zero_copy_only=False)
    else:
        x = column.dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False)
    return x[1:] != x[:-1]


def _stretch_counts(nested: bool, names: list[str]):  # noqa: ANN202
    """A row for each stretch: first and next position, border rows, and the changes inside of every column."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            starts, ends = stretches(batch.column(0).to_numpy().astype("int64"))
            columns = batch.columns[1:]
            changed = np.zeros((batch.num_rows, len(columns)), "int64")
            for j, c in enumerate(columns):
                changed[1:, j] = _changes(c)
            changed[starts] = 0
            if nested:
                changed = np.maximum.accumulate(changed, axis=1)
            counts = np.add.reduceat(changed, starts, axis=0)
            first, last = pa.array(starts), pa.array(ends - 1)
            pos = batch.column(0)
            offsets = pa.array(np.arange(len(starts) + 1, dtype="int32") * len(columns))
            yield pa.RecordBatch.from_arrays(
                [
                    pos.take(first).cast(pa.int64()), pc.add(pos.take(last).cast(pa.int64()), 1),
                    *(c.take(first) for c in columns), *(c.take(last) for c in columns),
                    pa.ListArray.from_arrays(offsets, pa.array(counts.ravel())),
                ],
                names=names,
            )

    return run


def few_rows(spark: SparkSession, values: list[int], name: str) -> DataFrame:
    """(i, value) of a few numbers, as literals of the plan."""
    items = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(int(v)).cast("long").alias(name)) for i, v in enumerate(values)]))
    return spark.range(1).select(items.alias("x")).select("x.i", f"x.{name}")


def run_count(df: DataFrame, cols: list[str], method: str = "given", nested: bool = False, facts: dict[str, list[int]] | None = None) -> DataFrame:
    """(method, col, runs): the runs of every column, in one pass and without a shuffle of the rows.

    A row starts a run where there is none before it. Columns are of atomic types. `facts` are a
    `survey` of the same rows and columns, whose runs are not counted again."""
    if facts and "runcount" in facts and not nested:
        names = F.element_at(F.array(*[F.lit(c) for c in cols]), F.col("i") + 1)
        return few_rows(df.sparkSession, facts["runcount"], "runs").select(F.lit(method).alias("method"), names.alias("col"), "runs")
    own = df.select("pos", *[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(cols)])
    kinds = [f.dataType for f in own.schema.fields[1:]]
    fields = [T.StructField("first", T.LongType()), T.StructField("next", T.LongType())]
    fields += [T.StructField(f"{side}{i}", k) for side in "ht" for i, k in enumerate(kinds)]
    schema = T.StructType([*fields, T.StructField("inner", T.ArrayType(T.LongType()))])
    parts = own.mapInArrow(_stretch_counts(nested, schema.names), schema)
    # a stretch's head meets the tail of the stretch before it at its position
    head = F.struct(*[F.col(f"h{i}").alias(f"v{i}") for i in range(len(cols))], F.col("inner"))
    tail = F.struct(*[F.col(f"t{i}").alias(f"v{i}") for i in range(len(cols))])
    ends = parts.select(
        F.explode(F.array(F.struct(F.col("first").alias("at"), head.alias("head"), F.lit(None).cast(_kind(tail, parts)).alias("tail")), F.struct(F.col("next").alias("at"), F.lit(None).cast(_kind(head, parts)).alias("head"), tail.alias("tail")))).alias("e")
    )
    met = ends.select("e.*").groupBy("at").agg(F.first("head", ignorenulls=True).alias("head"), F.first("tail", ignorenulls=True).alias("tail")).where("head is not null")
    counts, before = [], F.col("tail").isNull()
    for i in range(len(cols)):
        starts = F.col("tail").isNull() | ~F.col(f"head.v{i}").eqNullSafe(F.col(f"tail.v{i}"))
        before = before | starts
        counts.append(F.sum((before if nested else starts).cast("long") + F.get(F.col("head.inner"), F.lit(i))).alias(f"n{i}"))
    return _long(met.agg(*counts), method, cols, [f"n{i}" for i in range(len(cols))], "runs")


def _kind(column: Column, frame: DataFrame) -> T.DataType:
    return frame.select(column.alias("x")).schema["x"].dataType


def total_runs(df: DataFrame, cols: list[str]) -> int:
    """Runs over all columns, as a number."""
    return int(run_count(df, cols).agg(F.sum("runs")).first()[0] or 0)


def hamming(a: list[Column], b: list[Column]) -> Column:
    """Differing components, null-safe."""
    return sum(((~x.eqNullSafe(y)).cast("int") for x, y in zip(a, b, strict=True)), F.lit(0))


def rle_encode(df: DataFrame, col: str, nested_in: list[str] | None = None) -> DataFrame:
    """(col, start, len, value) of every run of one column; starts rise with the run number `run`.

    Runs are numbered by a range sort of their starts, and each takes its length from the next
    one's start, so one run that spans many partitions is one row."""
    cols = [*(nested_in or []), col]
    flags = change_flags(df, cols, nested=bool(nested_in))
    starts = flags.where(F.col(f"`new_{col}`")).select(F.col("pos").alias("start"), F.col(f"`{col}`").alias("value"))
    numbered = sorted_with_positions(starts, [F.asc("start")], "run")
    total = df.agg(F.count("*").alias("__n"))
    ahead = neighbours(numbered, ["start"], 1, "run")
    return ahead.crossJoin(F.broadcast(total)).select(
        F.lit(col).alias("col"), "start", (F.coalesce("next_start", "__n") - F.col("start")).alias("len"), "value", "run"
    )


def rle_decode(runs: DataFrame) -> DataFrame:
    """(col, pos, value) of encoded runs."""
    return runs.select(
        "col", F.explode(F.sequence(F.col("start"), F.col("start") + F.col("len") - 1)).alias("pos"), "value"
    )


def run_length_histogram(runs: DataFrame) -> DataFrame:
    """(col, len, runs, rows) by run length."""
    return runs.groupBy("col", "len").agg(F.count("*").alias("runs"), (F.count("*") * F.col("len")).alias("rows"))


def long_runs(runs: DataFrame, least: int) -> DataFrame:
    """(col, runs, rows) of runs of `least` rows or more."""
    return runs.where(F.col("len") >= least).groupBy("col").agg(F.count("*").alias("runs"), F.sum("len").alias("rows"))


def value_at(runs: DataFrame, wanted: DataFrame, span: int = 4096, start: bool = False) -> DataFrame:
    """(pos, value), with `start` also the run's, for the positions of `wanted`: an as-of lookup of the run that holds each.

    Runs are cut at multiples of `span` and joined on it, so a long run is not one hot key."""
    cut = runs.withColumn(
        "__block", F.explode(F.sequence(F.floor(F.col("start") / span), F.floor((F.col("start") + F.col("len") - 1) / span)))
    )
    asked = wanted.select("pos").withColumn("__block", F.floor(F.col("pos") / span))
    return asked.join(cut, "__block").where("pos >= start and pos < start + len").select("pos", "value", *(["start"] if start else []))


def rle_zip(a: DataFrame, b: DataFrame, combine: str = "x + y", span: int = 4096) -> DataFrame:
    """(start, len, value): a component-wise operation on two encoded columns, piece by piece.

    Runs of both are cut at multiples of `span`, and pieces that overlap in a block are combined;
    the work follows the number of runs, not of rows."""

    def cut(runs: DataFrame, name: str) -> DataFrame:
        end = F.col("start") + F.col("len")
        block = F.explode(F.sequence(F.floor(F.col("start") / span), F.floor((end - 1) / span)))
        return runs.select("start", end.alias("end"), F.col("value").alias(name), block.alias("__block")).select(
            F.greatest("start", F.col("__block") * span).alias(f"{name}0"), F.least("end", (F.col("__block") + 1) * span).alias(f"{name}1"), name, "__block"
        )

    both = cut(a, "x").join(cut(b, "y"), "__block").where("x0 < y1 and y0 < x1")
    pieces = both.select(F.greatest("x0", "y0").alias("pos"), F.least("x1", "y1").alias("stop"), F.expr(combine).alias("value"))
    # equal pieces in a row are one run again
    ranked = sorted_with_positions(pieces, [F.asc("pos")], "piece")
    seen = neighbours(ranked, ["value"], -1, "piece").where(~F.col("has_neighbour") | ~F.col("value").eqNullSafe(F.col("prev_value")))
    starts = sorted_with_positions(seen.select(F.col("pos").alias("start"), "value"), [F.asc("start")], "run")
    total = F.broadcast(pieces.agg(F.max("stop").alias("__n")))
    return (
        neighbours(starts, ["start"], 1, "run")
        .crossJoin(total)
        .select("start", (F.coalesce("next_start", "__n") - F.col("start")).alias("len"), "value")
    )
