"""Characteristics of tables and bounds on what reordering can gain."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowloom.operators.dictionary import clean, column_order, histogram
from rowloom.operators.position import neighbours, sorted_with_positions


def mu_bound(n: Column | int, cards: list[int]) -> float:
    """sum_j min(n, N_1 ... N_j) / (n + c - 1): a bound on how far a sorted table is from the fewest runs."""
    product, total = 1, 0
    for x in cards:
        product = min(n, product * x)
        total += product
    return total / (n + len(cards) - 1) if n else 0.0


def prefix_distincts(df: DataFrame, cols: list[str], approx: bool = False) -> list[int]:
    """Distinct tuples of each column prefix.

    Exact: distinct rows are sorted once, and a row adds one to every prefix from its first column
    that differs from the row before it."""
    if approx:
        tuples = [F.struct(*[F.col(f"`{c}`") for c in cols[: i + 1]]) for i in range(len(cols))]
        return [x or 0 for x in clean(df, cols).agg(*[F.approx_count_distinct(t) for t in tuples]).first()]
    rows = clean(df, cols).select(*[F.col(f"`{c}`") for c in cols]).distinct()
    ordered = sorted_with_positions(rows, [F.asc_nulls_first(f"`{c}`") for c in cols])
    beside = neighbours(ordered, cols)
    first = F.when(~F.col("has_neighbour"), F.lit(0))
    for i, c in enumerate(cols):
        first = first.when(~F.col(f"`{c}`").eqNullSafe(F.col(f"`prev_{c}`")), F.lit(i))
    new = {r["first"]: r["count"] for r in beside.select(first.alias("first")).groupBy("first").count().collect()}
    return list(accumulate(new.get(i, 0) for i in range(len(cols))))


def omega_bound(df: DataFrame, cols: list[str], order: str | list[str] = "asc_card", approx: bool = False) -> float:
    """Sum of the prefix distincts over n + c - 1, n counting distinct rows: the sorted table has at most
    this many times the fewest runs."""
    ordered = column_order(df, cols, order)
    prefixes = prefix_distincts(df, ordered, approx)
    n = prefixes[-1] if prefixes else 0
    return sum(prefixes) / (n + len(cols) - 1) if n else 0.0


def residual_optimality(omega: float, gain: float) -> float:
    """What is left of the bound after a measured gain."""
    return omega / gain


def dispersion(df: DataFrame, cols: list[str]) -> DataFrame:
    """p0: the mean over columns of their top frequency over n, as one row (`p0`)."""
    tops = histogram(clean(df, cols), cols).groupBy("col_idx").agg(F.max("freq").alias("top"), F.sum("freq").alias("n"))
    return tops.agg(F.coalesce(F.round(F.avg(F.col("top") / F.col("n")), 6), F.lit(0.0)).alias("p0"))


def run_lower_bound(df: DataFrame, cols: list[str]) -> int:
    """Distinct rows + c - 1."""
    n = clean(df, cols).select(*[F.col(f"`{c}`") for c in cols]).distinct().count()
    return n + len(cols) - 1 if n else 0


def distinct_rows(df: DataFrame, cols: list[str], approx: bool = True) -> int:
    """Distinct rows, by sketch or exactly."""
    if approx:
        return df.agg(F.approx_count_distinct(F.struct(*[F.col(f"`{c}`") for c in cols]))).first()[0]
    return clean(df, cols).select(*[F.col(f"`{c}`") for c in cols]).distinct().count()


def table_profile(df: DataFrame, cols: list[str], exact: bool = True, order: str | list[str] = "asc_card") -> DataFrame:
    """One row: n_rows, n_distinct, n_cols, sum_card, omega, p0 (rounded to 6 digits).

    `order` is that of the columns whose prefixes omega counts: by the table's own cardinalities
    (asc_card, ties as given), as given, or as listed."""
    hist = histogram(clean(df, cols), cols)
    per = hist.groupBy("col_idx").agg(F.count("*").alias("card"), F.max("freq").alias("top"), F.sum("freq").alias("n")).collect()
    cards = {r["col_idx"]: r["card"] for r in per}
    n = per[0]["n"] if per else 0
    if order == "asc_card":
        ordered = [cols[i] for i in sorted(range(len(cols)), key=lambda i: (cards.get(i, 0), i))]
    else:
        ordered = column_order(df, cols, order)
    prefixes = prefix_distincts(df, ordered, approx=not exact)
    distinct = prefixes[-1] if n else 0
    omega = round(sum(prefixes) / (distinct + len(cols) - 1), 6) if n else 0.0
    p0 = round(sum(r["top"] / r["n"] for r in per) / len(per), 6) if n else 0.0
    return df.sparkSession.createDataFrame(
        [(n, distinct, len(cols), sum(cards.values()), omega, p0)],
        "n_rows long, n_distinct long, n_cols long, sum_card long, omega double, p0 double",
    )


def advise(profile: DataFrame, omega_min: float = 3.0, p0_min: float = 0.3) -> DataFrame:
    """Whether a better order than the lexicographic one is worth a try, and why."""
    skip = F.when(F.col("omega") < 1.05, F.lit("lexicographic is near the bound"))
    skip = skip.when(F.col("omega") <= omega_min, F.lit("omega is low")).when(F.col("p0") <= p0_min, F.lit("p0 is low"))
    return profile.select("*", (~((F.col("omega") <= omega_min) | (F.col("p0") <= p0_min))).alias("try"), skip.otherwise(F.lit("skewed and far from the bound")).alias("reason"))


#: Codecs whose size follows the number of runs.
RUN_CODECS = ("rle", "lz", "runcount")


def choose(profile: DataFrame, codec: str, omega_min: float = 3.0, p0_min: float = 0.3) -> DataFrame:
    """The order to use for a codec: few runs for run-length and LZ coding, long runs for block codes."""
    better = "multiple_lists_blocked" if codec in RUN_CODECS else "interleave"
    advice = advise(profile, omega_min, p0_min)
    return advice.select(F.lit(codec).alias("codec"), F.when(F.col("try"), F.lit(better)).otherwise(F.lit("lexicographic")).alias("method"), "reason")
