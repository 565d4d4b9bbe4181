"""Queries on orders, duplicates and dictionaries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowloom.operators import dictionary as D
from rowloom.operators import order as O
from rowloom.operators import runs as R
from rowloom.plans import oracle as S
from rowloom.plans.registry import query
from rowloom.plans.workloads import WORKS

#: Query name: workload, order, SQL order, options.
_ORDERED = {
    "order_lexicographic": ("lineitem", "lexicographic", "lexicographic", {}),
    "order_alternating": ("lineitem", "alternating", "alternating", {}),
    "order_reflected_gray": ("lineitem", "reflected_gray", "reflected_gray", {}),
    "order_zorder_gray": ("lineitem", "zorder_gray", "zorder_gray", {"bits": 14}),
    "order_frequent_component": ("lineitem", "frequent_component", "frequent_component", {}),
    "order_frequent_component_fvc": ("lineitem", "frequent_component", "frequent_component_fvc", {"triple": "freq_value_col"}),
    "order_interleave": ("lineitem", "interleave", "interleave", {}),
    "order_interleave_raw": ("zipf", "interleave", "interleave_raw", {"normalize": False}),
    "order_interleave_orders": ("orders", "interleave", "interleave", {}),
    "order_interleave_part": ("part", "interleave", "interleave", {}),
    "order_interleave_events": ("events", "interleave", "interleave", {}),
    "toy_lexicographic": ("pair", "lexicographic", "lexicographic", {}),
    "toy_frequent_component": ("toy", "frequent_component", "frequent_component", {}),
    "toy_interleave": ("toy", "interleave", "interleave", {}),
    "toy8_interleave": ("toy8", "interleave", "interleave", {}),
    "toy_reflected_gray": ("toy", "reflected_gray", "reflected_gray", {}),
    "grid_reflected_gray": ("grid44", "reflected_gray", "reflected_gray", {}),
    "grid_interleave": ("grid44", "interleave", "interleave", {}),
    "grid_zorder_gray": ("grid44", "zorder_gray", "zorder_gray", {"bits": 2}),
    "grid222_interleave": ("grid222", "interleave", "interleave", {}),
    "grid333_interleave": ("grid333", "interleave", "interleave", {}),
    "zipf_interleave": ("zipf", "interleave", "interleave", {}),
    "uniform_frequent_component": ("uniform", "frequent_component", "frequent_component", {}),
}


def _register(name: str, work: str, order: str, sql_order: str, opt: dict) -> None:
    w = WORKS[work]

    @query(name, S.order_rows(w.sql, w.cols, sql_order, opt.get("bits", 16)))
    def plan(spark: SparkSession, sf_dir: str) -> DataFrame:
        return O.order_by(w.frame(spark, sf_dir), order, w.cols, "given", **opt).select("pos", *w.cols)


for _name, _spec in _ORDERED.items():
    _register(_name, *_spec)


def _hilbert_sql(source: str, cols: list[str], width: int) -> str:
    """The plane curve, a level a subquery: quadrant, then reflection or rotation of what is left."""
    level = f"SELECT *, k0 AS x, k1 AS y, CAST(0 AS BIGINT) AS d FROM coded"
    for b in range(width - 1, -1, -1):
        s = 1 << b
        level = f"SELECT * EXCLUDE (x, y, d), x & {s - 1} AS lx, y & {s - 1} AS ly, (x >> {b}) & 1 AS rx, (y >> {b}) & 1 AS ry, d FROM ({level})"
        level = (
            f"SELECT * EXCLUDE (lx, ly, rx, ry, d), CASE WHEN ry = 1 THEN lx WHEN rx = 1 THEN {s - 1} - ly ELSE ly END AS x, "
            f"CASE WHEN ry = 1 THEN ly WHEN rx = 1 THEN {s - 1} - lx ELSE lx END AS y, "
            f"d + {s * s} * CASE WHEN rx = 0 AND ry = 0 THEN 0 WHEN rx = 0 THEN 1 WHEN ry = 1 THEN 2 ELSE 3 END AS d FROM ({level})"
        )
    return f"WITH {S.coded(source, cols)}, h AS ({level}) SELECT row_number() OVER (ORDER BY d) - 1 AS pos, {', '.join(cols)} FROM h"


_QD = ["l_discount", "l_quantity"]


@query("order_hilbert", _hilbert_sql("SELECT l_discount, l_quantity FROM lineitem", _QD, 6))
def order_hilbert(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = WORKS["lineitem9"].frame(spark, sf_dir).select(*_QD)
    return O.order_by(df, "hilbert", _QD, "given", bits=6).select("pos", *_QD)


@query("grid_hilbert", _hilbert_sql(WORKS["grid44"].sql, ["c1", "c2"], 2))
def grid_hilbert(spark: SparkSession, sf_dir: str) -> DataFrame:
    return O.order_by(WORKS["grid44"].frame(spark, sf_dir), "hilbert", ["c1", "c2"], "given").select("pos", "c1", "c2")


@query("grid_hilbert_3d", "SELECT CAST(511 AS BIGINT) AS steps, 1 AS max_distance, true AS gray")
def grid_hilbert_3d(spark: SparkSession, sf_dir: str) -> DataFrame:
    """On a cube whose side is a power of two the curve changes one column at a time."""
    from rowloom.sources.synth import grid_table

    cols = ["c1", "c2", "c3"]
    return O.is_gray(O.order_by(grid_table(spark, [8, 8, 8]), "hilbert", cols, "given"), cols)


_GRAY = [("reflected_gray", "grid333"), ("interleave", "grid333"), ("interleave", "grid44"), ("zorder_gray", "grid44"), ("lexicographic", "grid44")]


@query(
    "gray_property",
    " UNION ALL ".join(
        f"SELECT '{o}' AS method, '{g}' AS grid, CAST(count(*) AS BIGINT) AS steps, CAST(max(d) AS INTEGER) AS max_distance, max(d) <= 1 AS gray FROM ("
        f"WITH {S.ordered(WORKS[g].sql, WORKS[g].cols, o, 2)} SELECT "
        + " + ".join(f"CASE WHEN {c} IS DISTINCT FROM lag({c}) OVER (ORDER BY pos) THEN 1 ELSE 0 END" for c in WORKS[g].cols)
        + " AS d, pos FROM o) WHERE pos > 0"
        for o, g in _GRAY
    ),
)
def gray_property(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for o, g in _GRAY:
        w = WORKS[g]
        one = O.is_gray(O.order_by(w.frame(spark, sf_dir), o, w.cols, "given", keep_codes=o == "lexicographic"), w.cols)
        one = one.select(F.lit(o).alias("method"), F.lit(g).alias("grid"), "steps", "max_distance", "gray")
        out = one if out is None else out.union(one)
    return out


@query(
    "column_order_cards",
    "SELECT col, card, row_number() OVER (ORDER BY card, i) - 1 AS place FROM ("
    + " UNION ALL ".join(f"SELECT '{c}' AS col, {i} AS i, count(DISTINCT {c}) AS card FROM ({WORKS['lineitem9'].sql})" for i, c in enumerate(WORKS["lineitem9"].cols))
    + ")",
)
def column_order_cards(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = WORKS["lineitem9"]
    df = w.frame(spark, sf_dir)
    ranked = D.column_order(df, w.cols)
    cards = D.histogram(df, w.cols).groupBy("col_idx").agg(F.count("*").alias("card"))
    names = F.element_at(F.array(*[F.lit(c) for c in w.cols]), F.col("col_idx") + 1)
    place = F.array_position(F.array(*[F.lit(c) for c in ranked]), F.col("col")).cast("long") - 1
    return cards.select(names.alias("col"), "card").select("col", "card", place.alias("place"))


_DICT = " UNION ALL ".join(
    f"SELECT '{c}' AS col, CAST({c} AS VARCHAR) AS value, f AS freq, row_number() OVER (ORDER BY f DESC, {c} ASC NULLS FIRST) - 1 AS code "
    f"FROM (SELECT {c}, count(*) AS f FROM ({WORKS['orders'].sql}) GROUP BY 1)"
    for c in WORKS["orders"].cols
)


@query("dictionary_codes", _DICT)
def dictionary_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = WORKS["orders"]
    made = D.build_dictionary(w.frame(spark, sf_dir), w.cols)
    value, name = F.lit(None).cast("string"), F.lit(None).cast("string")
    for i, c in enumerate(w.cols):
        value = F.when(F.col("col_idx") == i, F.col(c).cast("string")).otherwise(value)
        name = F.when(F.col("col_idx") == i, F.lit(c)).otherwise(name)
    return made.select(name.alias("col"), value.alias("value"), "freq", "code")


_O3 = ["o_orderstatus", "o_orderpriority", "o_custkey"]


@query("dict_join_decode", f"SELECT o_orderstatus, o_orderpriority, o_custkey, count(*) AS n FROM orders GROUP BY ALL")
def dict_join_decode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encoding and decoding gives the rows back."""
    df = WORKS["orders"].frame(spark, sf_dir).select(*_O3)
    made = D.build_dictionary(df, _O3)
    codes = D.encode(df, made, _O3).drop(*_O3)
    empty = codes.select("*", *[F.lit(None).alias(c) for c in _O3])
    return D.decode(empty, made, _O3).groupBy(*_O3).agg(F.count("*").alias("n"))


@query("collapse_duplicates", "SELECT o_orderstatus, o_orderpriority, o_custkey, count(*) AS frequency FROM orders GROUP BY ALL")
def collapse_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return O.collapse_duplicates(WORKS["orders"].frame(spark, sf_dir).select(*_O3), _O3)


@query("expand_duplicates", "SELECT o_orderstatus, o_orderpriority, o_custkey FROM orders")
def expand_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return O.expand_duplicates(O.collapse_duplicates(WORKS["orders"].frame(spark, sf_dir).select(*_O3), _O3))


_SP = ["o_orderstatus", "o_orderpriority"]
_BY_KEY = "SELECT *, row_number() OVER (ORDER BY o_orderkey) - 1 AS pos0 FROM orders"


@query(
    "make_discriminating",
    f"SELECT row_number() OVER (ORDER BY first, pos0) - 1 AS pos, o_orderstatus, o_orderpriority, o_orderkey FROM "
    f"(SELECT *, min(pos0) OVER (PARTITION BY o_orderstatus, o_orderpriority) AS first FROM ({_BY_KEY}))",
)
def make_discriminating(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rowloom.operators.position import sorted_with_positions
    from rowloom.sources.io import read_table

    df = sorted_with_positions(read_table(spark, sf_dir, "orders").select("o_orderkey", *_SP), [F.asc("o_orderkey")])
    return O.make_discriminating(df, _SP).select("pos", *_SP, "o_orderkey")


@query("order_discriminating_inv", "SELECT count(*) AS n_rows, (SELECT count(*) FROM (SELECT DISTINCT o_orderstatus, o_orderpriority, o_custkey FROM orders)) AS groups, true AS bounded FROM orders")
def order_discriminating_inv(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Equal rows stand together: as many stretches of equal rows as distinct rows, and c runs for each at most."""
    df = O.order_by(WORKS["orders"].frame(spark, sf_dir).select(*_O3), "discriminating", _O3, "given")
    steps = O.step_distances(df, _O3)
    runs = R.run_count(df, _O3).agg(F.sum("runs").alias("runs"))
    return (
        steps.agg((F.count("*") + 1).alias("n_rows"), (F.count_if(F.col("distance") > 0) + 1).alias("groups"))
        .crossJoin(runs)
        .select("n_rows", "groups", (F.col("runs") <= F.col("groups") * len(_O3)).alias("bounded"))
    )


@query("permutation_check", "SELECT CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS extra, count(*) AS n, count(*) - 1 AS last_pos FROM lineitem")
def permutation_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A reordered table has the rows of the table, each as often, at positions 0 .. n - 1."""
    w = WORKS["lineitem"]
    df = w.frame(spark, sf_dir)
    new = O.order_by(df, "interleave", w.cols)
    missing = df.select(*w.cols).exceptAll(new.select(*w.cols)).agg(F.count("*").alias("missing"))
    extra = new.select(*w.cols).exceptAll(df.select(*w.cols)).agg(F.count("*").alias("extra"))
    return missing.crossJoin(extra).crossJoin(new.agg(F.count_distinct("pos").alias("n"), F.max("pos").alias("last_pos")))


@query(
    "shuffled_inv",
    "SELECT n, n - 1 AS last_pos, true AS near_expected FROM (SELECT count(*) AS n FROM orders)",
)
def shuffled_inv(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A shuffled table has about as many runs as independent rows would: equal rows are parted too."""
    cols = ["o_orderstatus", "o_orderpriority"]
    df = WORKS["orders"].frame(spark, sf_dir).select(*cols)
    new = O.order_by(df, "shuffled", cols, "given", seed=1)
    n = df.count()
    same = sum(float(df.groupBy(c).agg((F.count("*") / n).alias("p")).agg(F.sum(F.col("p") ** 2)).first()[0]) for c in cols)
    expected = len(cols) + (n - 1) * (len(cols) - same)
    near = abs(R.total_runs(new, cols) - expected) < 0.02 * expected
    return new.agg(F.count("*").alias("n"), F.max("pos").alias("last_pos"), F.lit(near).alias("near_expected"))
