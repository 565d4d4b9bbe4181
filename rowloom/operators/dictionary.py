"""Column dictionaries: values to codes from 0 on, the most frequent value first."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowloom.operators.position import sorted_with_positions
from rowloom.sources.scratch import written


#: Most frequent values of a column that are broadcast, and the bytes that they may have.
HEAD, HEAD_BYTES = 1 << 18, 32 << 20

_COSTLY = re.compile(r"\b(Join|Aggregate|Window|Generate|Sort|Repartition|RepartitionByExpression|Distinct|Intersect|Except|MapInArrow|MapInPandas|FlatMapGroupsInArrow|FlatMapGroupsInPandas|ArrowEvalPython|BatchEvalPython|Expand|Sample)\b")


#: Characters of a plan from which on its expressions count as costly.
LONG_PLAN = 8000


def settled(df: DataFrame) -> DataFrame:
    """`df`, written first if its plan does more than read, filter and compute short expressions:
    dictionaries read it once a column."""
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    return written(df, "input") if len(plan) > LONG_PLAN or _COSTLY.search(plan) else df


def clean(df: DataFrame, cols: list[str]) -> DataFrame:
    """Columns with one form for each value: negative zero as zero, maps as sorted entries."""
    kinds = dict(df.dtypes)
    fixed: list[Column] = []
    for c in df.columns:
        col = F.col(f"`{c}`")
        if c in cols and kinds[c] in ("double", "float"):
            col = F.when(col == 0, F.lit(0.0).cast(kinds[c])).otherwise(col)
        elif c in cols and kinds[c].startswith("map<"):
            col = F.array_sort(F.map_entries(col))
        fixed.append(col.alias(c))
    return df.select(*fixed)


def histogram(df: DataFrame, cols: list[str]) -> DataFrame:
    """(the columns, freq, col_idx): value counts of all columns.

    Column i's values are in its own column, the others are null there. Each column is counted on
    its own, so that a scan reads it alone and its counts are combined on the map side by a
    narrow key; over a frame that is costly to make, write it first."""
    kinds = {f.name: f.dataType for f in df.schema.fields}
    parts = []
    for i, c in enumerate(cols):
        counts = df.groupBy(F.col(f"`{c}`")).agg(F.count(F.lit(1)).alias("freq"))
        values = [F.col(f"`{x}`") if x == c else F.lit(None).cast(kinds[x]).alias(x) for x in cols]
        parts.append(counts.select(*values, "freq", F.lit(i).alias("col_idx")))
    out = parts[0]
    for part in parts[1:]:
        out = out.union(part)
    return out


def build_dictionary(df: DataFrame, cols: list[str], tail: str = "frequency") -> DataFrame:
    """(col_idx, values, freq, code): codes by falling frequency, ties by value, null first.

    One range sort ranks all columns, however large; `tail='natural'` codes by value instead."""
    hist = written(histogram(clean(df, cols), cols), "histogram")
    sizes = cardinalities(hist, cols)
    values = [F.asc_nulls_first(f"`{c}`") for c in cols]
    keys = [F.asc("col_idx"), *([F.desc("freq")] if tail == "frequency" else []), *values]
    ranked = sorted_with_positions(hist, keys, "__rank")
    first = F.element_at(F.array(*[F.lit(sum(sizes[:i])).cast("long") for i in range(len(cols))]), F.col("col_idx") + 1)
    return ranked.withColumn("code", F.col("__rank") - first).drop("__rank")


def cardinalities(dictionary: DataFrame, cols: list[str]) -> list[int]:
    """Distinct values of each column (null counts as one): a few numbers on the driver."""
    got = {r["col_idx"]: r["n"] for r in dictionary.groupBy("col_idx").agg(F.count("*").alias("n")).collect()}
    return [got.get(i, 0) for i in range(len(cols))]


def head_facts(dictionary: DataFrame, cols: list[str]) -> list[tuple[int, int]]:
    """For each column, its distinct values and the bytes of those with codes under HEAD: a few numbers on the driver."""
    size = sum((F.coalesce(F.octet_length(F.col(f"`{c}`").cast("string")), F.lit(0)) for c in cols), F.lit(24))
    got = dictionary.groupBy("col_idx").agg(F.count("*").alias("n"), F.sum(F.when(F.col("code") < HEAD, size)).alias("bytes"))
    facts = {r["col_idx"]: (r["n"], r["bytes"] or 0) for r in got.collect()}
    return [facts.get(i, (0, 0)) for i in range(len(cols))]


def _lookup(out: DataFrame, side: DataFrame, key: str, facts: tuple[int, int], names: list[str]) -> DataFrame:
    """`out` with `names` of `side` (__v, code, names), which has each value of `key` once.

    Codes fall with frequency, so those under HEAD are of the most frequent values: these are
    broadcast, if their bytes are few, and only rows with a rarer value are dealt by it, rows already
    served by a hash of all their columns. So no task gets the rows of a frequent value."""
    n, size = facts
    same = F.col(f"`{key}`").eqNullSafe(F.col("__v"))
    found = [F.col(f"`{x}`") for x in names]
    kept = [F.col(f"`{c}`") for c in out.columns]
    if size > HEAD_BYTES:
        return out.join(side.select("__v", *found), same, "left").drop("__v")
    if n <= HEAD:
        return out.join(F.broadcast(side.select("__v", *found)), same, "left").drop("__v")
    head = side.where(F.col("code") < HEAD).select("__v", F.struct(*found).alias("__head"))
    # a zero that the optimiser cannot fold: it would take the salt out of the join's keys
    zero = F.pmod(F.xxhash64("code"), F.lit(1).cast("long"))
    tail = side.where(F.col("code") >= HEAD).select("__v", zero.alias("__deal"), F.struct(*found).alias("__tail"))
    served = out.join(F.broadcast(head), same, "left").drop("__v")
    served = served.withColumn("__salt", F.when(F.col("__head").isNull(), F.lit(0).cast("long")).otherwise(F.xxhash64(*kept).bitwiseOR(F.lit(1))))
    both = served.join(tail, same & (F.col("__salt") == F.col("__deal")), "left")
    return both.select(*kept, *[F.coalesce(F.col(f"__head.`{x}`"), F.col(f"__tail.`{x}`")).alias(x) for x in names])


def encode(df: DataFrame, dictionary: DataFrame, cols: list[str], suffix: str = "__code", freq: bool = False, lean: bool = False) -> DataFrame:
    """`df` with a code column for each of `cols` (and `__freq` ones). Each join is on the value, null-safe.

    With `lean`, a column goes once it is coded, broadcast ones first, so that later joins move less."""
    out = clean(df, cols)
    facts = head_facts(dictionary, cols)
    turn = sorted(range(len(cols)), key=lambda i: facts[i][0] > HEAD or facts[i][1] > HEAD_BYTES) if lean else range(len(cols))
    for i in turn:
        c = cols[i]
        names = [c + suffix, *([c + "__freq"] if freq else [])]
        side = dictionary.where(F.col("col_idx") == i).select(
            F.col(f"`{c}`").alias("__v"), "code", F.col("code").alias(c + suffix), *([F.col("freq").alias(c + "__freq")] if freq else [])
        )
        out = _lookup(out, side, c, facts[i], names)
        out = out.drop(c) if lean else out
    return out


def decode(df: DataFrame, dictionary: DataFrame, cols: list[str], suffix: str = "__code") -> DataFrame:
    """Values back from the code columns, which are dropped."""
    out = df
    facts = head_facts(dictionary, cols)
    for i, c in enumerate(cols):
        side = dictionary.where(F.col("col_idx") == i).select(F.col("code").alias("__v"), "code", F.col(f"`{c}`").alias("__new"))
        out = _lookup(out.drop(c), side, c + suffix, facts[i], ["__new"]).drop(c + suffix).withColumnRenamed("__new", c)
    return out


def column_order(df: DataFrame, cols: list[str], mode: str | list[str] = "asc_card", approx: bool = False) -> list[str]:
    """Columns by non-decreasing or non-increasing distinct counts (ties as given), as given, or as listed."""
    if not isinstance(mode, str):
        return list(mode)
    if mode == "given":
        return list(cols)
    if mode not in ("asc_card", "desc_card"):
        raise ValueError("column order is asc_card, desc_card, given or a list")
    count = (lambda c: F.approx_count_distinct(c)) if approx else (lambda c: F.count_distinct(c))
    null = lambda c: F.max(F.col(f"`{c}`").isNull().cast("int"))
    row = clean(df, cols).agg(*[(count(F.col(f"`{c}`")) + null(c)).alias(f"n{i}") for i, c in enumerate(cols)]).first()
    cards = [row[i] or 0 for i in range(len(cols))]
    ranked = sorted(range(len(cols)), key=lambda i: (cards[i] if mode == "asc_card" else -cards[i], i))
    return [cols[i] for i in ranked]
