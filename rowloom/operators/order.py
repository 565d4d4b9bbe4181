"""Row orders: every method that is a sort by a key, duplicates, and the Gray property."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from rowloom.functions import keys as K
from rowloom.operators.dictionary import build_dictionary, cardinalities, clean, column_order, encode, settled
from rowloom.operators.position import neighbours, numbered, sorted_with_positions
from rowloom.sources.scratch import written

ORDERS = (
    "lexicographic", "alternating", "reflected_gray", "interleave", "frequent_component", "zorder_gray", "hilbert",
    "discriminating", "shuffled",
)


def orderable(df: DataFrame) -> list[str]:
    """Columns that can be reordered by: all but nested ones and `pos`."""
    return [c for c, t in df.dtypes if c != "pos" and not t.startswith(("array", "struct", "binary"))]


def order_by(
    df: DataFrame, order: str = "lexicographic", cols: list[str] | None = None, column_order_mode: str | list[str] = "asc_card",
    normalize: bool = True, tie: list[str] | None = None, triple: str = "freq_col_value", descending: bool = False,
    seed: int = 0, keep_codes: bool = False, dictionary: DataFrame | None = None, bits: int | None = None,
) -> DataFrame:
    """`df` in the named order, with `pos`.

    `cols` are the reordered columns, the rest travels along. With `normalize`, values stand as
    their frequency codes (lexicographic and alternating sort the values themselves unless
    `keep_codes`); without it the columns must be integers. `tie` closes equal rows; without it a
    hash of the other columns does, which also lets a range exchange cut a very frequent row. `bits` fixes the width of
    space-filling curves (default: that of the largest code). `shuffled` numbers the rows of a
    written copy and hashes the numbers. A frame that is costly to make is written first."""
    cols = cols or orderable(df)
    df = settled(df)
    cols = column_order(df, cols, column_order_mode)
    df = clean(df, cols).drop("pos")
    if order == "shuffled":
        df = written(df.withColumn("__row", F.monotonically_increasing_id()), "rows")
    raw = order in ("lexicographic", "alternating", "discriminating", "shuffled") and not keep_codes
    if raw or not normalize:
        coded, codes, freqs = df, [F.col(f"`{c}`") for c in cols], []
        drop: list[str] = []
        cards = []
        if order == "zorder_gray" or order == "hilbert":
            top = df.agg(*[F.max(F.col(f"`{c}`")).cast("long").alias(f"m{i}") for i, c in enumerate(cols)]).first()
            cards = [(top[i] or 0) + 1 for i in range(len(cols))]
        if order == "frequent_component":
            raise ValueError("frequent_component needs normalized columns")
    else:
        dictionary = build_dictionary(df, cols) if dictionary is None else dictionary
        coded = encode(df, dictionary, cols, freq=order == "frequent_component")
        codes = [F.col(f"`{c}__code`") for c in cols]
        freqs = [F.col(f"`{c}__freq`") for c in cols]
        drop = [*([] if keep_codes else [c + "__code" for c in cols]), *([c + "__freq" for c in cols] if order == "frequent_component" else [])]
        cards = cardinalities(dictionary, cols) if order in ("zorder_gray", "hilbert") else []
    if bits is not None and cards:
        cards = [1 << bits] * len(cols)
    if order == "frequent_component":
        keys = K.frequent_component(codes, freqs, triple, descending)
    elif order == "zorder_gray":
        keys = K.zorder_gray(codes, cards)
    elif order == "hilbert":
        keys = K.hilbert(codes, cards)
    elif order == "shuffled":
        keys = K.shuffled(F.col("__row"), seed)
        drop = [*drop, "__row"]
    elif order in K.ORDERS:
        keys = K.ORDERS[order](codes)
    else:
        raise ValueError(f"order is one of {ORDERS}")
    rest = [c for c in df.columns if c not in cols]
    computed = {f"__k{i}": k for i, k in enumerate(keys.computed)}
    if tie:
        close = [F.asc_nulls_first(f"`{c}`") for c in tie]
    elif rest:
        computed["__tie"] = F.xxhash64(*[F.col(f"`{c}`") for c in rest])
        close = [F.asc("__tie")]
    else:
        close = []
    keyed = coded.withColumns(keys.helpers) if keys.helpers else coded
    keyed = keyed.withColumns(computed).drop(*keys.helpers) if computed else keyed
    if not raw and normalize:
        # the range exchange reads its input twice, once to sample it: joins and keys are made once
        keyed = written(keyed, "keyed")
    order_cols = [F.asc(k) for k in computed if k != "__tie"]
    return sorted_with_positions(keyed, [*order_cols, *keys.ready, *close], drop=[*computed, *drop])


def code_table(df: DataFrame, cols: list[str], dictionary: DataFrame, freq: bool = False, path: str | None = None) -> DataFrame:
    """The codes of `cols` alone, as a written table (at `path`, if given) that all orders can be taken from (with `freq`, `__freq` columns too)."""
    return written(encode(df.select(*[F.col(f"`{c}`") for c in cols]), dictionary, cols, freq=freq, lean=True), "coded", path)


def order_codes(coded: DataFrame, order: str, codes: list[str], freqs: list[str] | None = None) -> DataFrame:
    """The code columns of a written `code_table` in order, with `pos`.

    The exchange moves the codes alone: its keys are evaluated where a row is dealt, and are made
    again as columns for the sort behind it."""
    c = [F.col(f"`{x}`") for x in codes]
    f = [F.col(f"`{x}`") for x in freqs or []]
    keys = K.frequent_component(c, f) if order == "frequent_component" else K.ORDERS[order](c)
    if "__pairs" in keys.helpers:
        deal = [F.transform(keys.helpers["__pairs"], lambda x, i: F.when(i % 2 == 0, x).otherwise(-x))]
    else:
        deal = [*keys.helpers.values()] or [*keys.computed, *keys.ready]
    dealt = coded.select(*c, *f).repartitionByRange(*deal)
    keyed = dealt.withColumns(keys.helpers) if keys.helpers else dealt
    computed = {f"__k{i}": k for i, k in enumerate(keys.computed)}
    keyed = keyed.withColumns(computed) if computed else keyed
    return numbered(keyed.sortWithinPartitions(*[F.asc(k) for k in computed], *keys.ready).select(*c))


def make_discriminating(df: DataFrame, cols: list[str]) -> DataFrame:
    """Moves every row up to the first equal one, which never adds runs. `pos` is renewed.

    The first positions are a map-side-combined minimum joined back, so that a very frequent row
    is split over tasks."""
    first = df.groupBy(*[F.col(f"`{c}`").alias(f"__f{i}") for i, c in enumerate(cols)]).agg(F.min("pos").alias("__first"))
    same = F.lit(True)
    for i, c in enumerate(cols):
        same = same & F.col(f"`{c}`").eqNullSafe(F.col(f"__f{i}"))
    joined = df.join(first, same).drop(*[f"__f{i}" for i in range(len(cols))]).withColumnRenamed("pos", "__old")
    return sorted_with_positions(joined, [F.asc("__first"), F.asc("__old")]).drop("__first", "__old")


def collapse_duplicates(df: DataFrame, cols: list[str]) -> DataFrame:
    """Distinct rows with their `frequency`."""
    return clean(df, cols).groupBy(*[F.col(f"`{c}`") for c in cols]).agg(F.count("*").alias("frequency"))


def expand_duplicates(df: DataFrame) -> DataFrame:
    """Every row as often as its `frequency` says; positions, if any, are renewed."""
    copies = df.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("frequency")))).drop("frequency")
    if "pos" not in df.columns:
        return copies.drop("__copy")
    return sorted_with_positions(copies.withColumnRenamed("pos", "__old"), [F.asc("__old"), F.asc("__copy")]).drop("__old", "__copy")


def step_distances(df: DataFrame, cols: list[str]) -> DataFrame:
    """(pos, distance to the row before) for every row but the first."""
    beside = neighbours(df.select("pos", *[F.col(f"`{c}`") for c in cols]), cols)
    distance = sum(((~F.col(f"`{c}`").eqNullSafe(F.col(f"`prev_{c}`"))).cast("int") for c in cols), F.lit(0))
    return beside.where("has_neighbour").select("pos", distance.alias("distance"))


def is_gray(df: DataFrame, cols: list[str]) -> DataFrame:
    """One row: steps, their largest distance, and whether it is 1 at most."""
    return step_distances(df, cols).agg(
        F.count("*").alias("steps"), F.coalesce(F.max("distance"), F.lit(0)).alias("max_distance"),
        (F.coalesce(F.max("distance"), F.lit(0)) <= 1).alias("gray"),
    )


def rank_within(df: DataFrame, by: list[str], order: list[str], name: str = "rank") -> DataFrame:
    """Row numbers within groups (for groups of bounded size)."""
    return df.withColumn(name, F.row_number().over(W.partitionBy(*by).orderBy(*order)))
