"""Tables of the experiments, re-expressed on the given ones: a Spark frame, its SQL twin, and its columns."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rowloom.sources import synth
from rowloom.sources.io import read_table


@dataclass(frozen=True)
class Work:
    """`cols` in non-decreasing cardinality, ties as the engine breaks them."""

    frame: Callable[[SparkSession, str], DataFrame]
    sql: str
    cols: list[str]


def _day(c: str):  # noqa: ANN202
    return F.unix_date(F.to_date(c)).cast("long")


def _sql_day(c: str) -> str:
    return f"date_diff('day', DATE '1970-01-01', CAST({c} AS DATE))"


L6 = ["l_linestatus", "l_returnflag", "l_linenumber", "l_tax", "l_discount", "ship_day"]
L9 = ["l_linestatus", "l_returnflag", "l_linenumber", "l_tax", "l_discount", "l_quantity", "l_suppkey", "l_partkey", "ship_day"]
O4 = ["o_orderstatus", "o_orderpriority", "o_custkey", "order_day"]
P4 = ["p_type", "p_brand", "p_size", "p_name"]
E4 = ["event_type", "props", "user_id", "hour"]
SSB = [
    "zero", "l_linestatus", "l_returnflag", "o_orderstatus", "o_orderpriority", "l_linenumber", "l_tax", "l_discount",
    "l_quantity", "l_suppkey", "l_partkey", "ship_day", "order_day", "l_orderkey", "l_extendedprice",
]
CENSUS = ["n_regionkey", "c_mktsegment", "o_orderpriority", "n_name", "c_nationkey", "order_day", "c_custkey"]


def lineitem(spark: SparkSession, sf_dir: str, cols: list[str]) -> DataFrame:
    return read_table(spark, sf_dir, "lineitem").withColumn("ship_day", _day("l_shipdate")).select(*cols)


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "orders").withColumn("order_day", _day("o_orderdate")).select(*O4)


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    hour = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600)
    return read_table(spark, sf_dir, "events").withColumn("hour", hour).select(*E4)


def ssb(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority", _day("o_orderdate").alias("order_day"))
    li = read_table(spark, sf_dir, "lineitem").withColumn("ship_day", _day("l_shipdate"))
    return li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).withColumn("zero", F.lit(0)).select(*SSB)


def census(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, n = read_table(spark, sf_dir, "customer"), read_table(spark, sf_dir, "nation")
    o = read_table(spark, sf_dir, "orders").withColumn("order_day", _day("o_orderdate"))
    joined = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.select(*CENSUS)


def _synth_sql(n: int, zipf: bool, c: int = 4, seed: int = 42) -> str:
    ids = f"(SELECT range AS id FROM range({n}))"
    if not zipf:
        return "SELECT id, " + ", ".join(f"CAST({synth.hash_sql('id', seed + j)} % {n} AS INTEGER) AS c{j + 1}" for j in range(c)) + f" FROM {ids}"
    return _zipf_sql(ids, "id", n, c, seed, "id", "id")


def _zipf_sql(rows: str, key: str, support: int, c: int, seed: int, keep: str, unique: str) -> str:
    """Zipf values by an as-of join on running sums of integer weights."""
    z = f"(SELECT range AS i, CAST(sum({synth.SCALE} // range) OVER (ORDER BY range) - {synth.SCALE} // range AS BIGINT) AS start FROM range(1, {support + 1}))"
    total = f"(SELECT CAST(sum({synth.SCALE} // range) AS BIGINT) FROM range(1, {support + 1}))"
    hashes = ", ".join(f"{synth.hash_sql(key, seed + j)} % {total} AS h{j}" for j in range(c))
    joins = " ".join(f"ASOF JOIN {z} z{j} ON t.h{j} >= z{j}.start" for j in range(c))
    picks = ", ".join(f"CAST(z{j}.i AS INTEGER) AS c{j + 1}" for j in range(c))
    return f"SELECT {keep}, {picks} FROM (SELECT *, {hashes} FROM {rows}) t {joins}"


C4 = ["c1", "c2", "c3", "c4"]
_LI = "SELECT *, " + _sql_day("l_shipdate") + " AS ship_day FROM lineitem"

WORKS: dict[str, Work] = {
    "lineitem": Work(lambda s, d: lineitem(s, d, L6), f"SELECT {', '.join(L6)} FROM ({_LI})", L6),
    "lineitem9": Work(lambda s, d: lineitem(s, d, L9), f"SELECT {', '.join(L9)} FROM ({_LI})", L9),
    "orders": Work(orders, f"SELECT o_orderstatus, o_orderpriority, o_custkey, {_sql_day('o_orderdate')} AS order_day FROM orders", O4),
    "part": Work(lambda s, d: read_table(s, d, "part").select(*P4), f"SELECT {', '.join(P4)} FROM part", P4),
    "events": Work(events, "SELECT event_type, props, user_id, CAST(floor(epoch(ts) / 3600) AS BIGINT) AS hour FROM events", E4),
    "ssb": Work(
        ssb,
        f"SELECT {', '.join(SSB)} FROM (SELECT l.*, 0 AS zero, o_orderstatus, o_orderpriority, {_sql_day('o_orderdate')} AS order_day "
        f"FROM ({_LI}) l JOIN orders ON l_orderkey = o_orderkey)",
        SSB,
    ),
    "census": Work(
        census,
        f"SELECT {', '.join(CENSUS)} FROM (SELECT *, {_sql_day('o_orderdate')} AS order_day FROM orders) JOIN customer ON o_custkey = c_custkey "
        "JOIN nation ON c_nationkey = n_nationkey",
        CENSUS,
    ),
    "zipf": Work(lambda s, d: synth.zipf_table(s, 8192).select(*C4), f"SELECT {', '.join(C4)} FROM ({_synth_sql(8192, True)})", C4),
    "uniform": Work(lambda s, d: synth.uniform_table(s, 8192).select(*C4), f"SELECT {', '.join(C4)} FROM ({_synth_sql(8192, False)})", C4),
    "skewed": Work(
        lambda s, d: synth.skewed_lineitem(read_table(s, d, "lineitem")).select(*C4),
        f"SELECT {', '.join(C4)} FROM ({_zipf_sql('lineitem', '(l_orderkey * 8 + l_linenumber)', 4096, 4, 7, 'l_orderkey', 'l_orderkey')})",
        C4,
    ),
}

# Tables whose values are computed from hashed keys by integer arithmetic alone, the same in any engine.


def _mixed_sql(key: str, j: int, share: int, octaves: int) -> str:
    """0 in `share` hundredths of the rows, else about Zipfian: an octave at random, and a value in it."""
    h, g = synth.hash_sql(key, 500 + 2 * j), synth.hash_sql(key, 501 + 2 * j)
    size = f"(CAST(1 AS BIGINT) << CAST(({h} >> 20) % {octaves} AS INTEGER))"
    return f"CASE WHEN {h} % 100 < {share} THEN 0 ELSE {size} + {g} % {size} END"


#: Columns of each: percentage of the top value, octaves of the others.
WIDE_COLS = [(25 + 20 * (j % 4), 1 + j * 14 // 42) for j in range(42)]
DUP_COLS = [(30 + 6 * (j % 4), 9 + j // 2) for j in range(10)]
SKY_COLS = [(20 + 7 * (j % 5), 2 + j % 4) for j in range(8)]
_WIDE = [f"w{j:02d}" for j in range(42)]
_DUP = [f"u{j}" for j in range(10)]
_SKY = ["sky%d" % j for j in range(8)]
#: 19 columns: dates and stations that determine each other in part, and skewed readings by station and day.
WEATHER = ["half", "quarter", "year", "day_of_week", "month", *_SKY, "day_of_month", "zone", "latitude", "longitude", "station", "day"]


def _made(df: DataFrame, key, cols: list[tuple[int, int]], names: list[str], first: int = 0) -> DataFrame:  # noqa: ANN001
    """`df` with a column of the values of `_mixed_sql` for each of `cols`, numbered from `first`. They are
    computed in Arrow batches, where each part of a hash is taken once."""
    keyed = df.withColumn("__key", key.cast("long"))
    made = T.StructType([f for f in keyed.schema.fields if f.name != "__key"] + [T.StructField(n, T.LongType()) for n in names])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.get_field_index("__key")
            none = batch.column(at).is_null().to_numpy(zero_copy_only=False)
            k = batch.column(at).fill_null(0).to_numpy(zero_copy_only=False).astype("int64")
            columns = [pa.array(synth.mixed_values(k, 500 + 2 * (first + j), *spec), mask=none) for j, spec in enumerate(cols)]
            kept = [c for i, c in enumerate(batch.columns) if i != at]
            yield pa.RecordBatch.from_arrays([*kept, *columns], names=made.names)

    return keyed.mapInArrow(run, made)


def _made_sql(rows: str, key: str, cols: list[tuple[int, int]], names: list[str]) -> str:
    return "SELECT " + ", ".join(f"{_mixed_sql(key, j, *spec)} AS {n}" for j, (spec, n) in enumerate(zip(cols, names, strict=True))) + f" FROM ({rows})"


def wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """42 skewed columns, a row for each order."""
    return _made(read_table(spark, sf_dir, "orders").select("o_orderkey"), F.col("o_orderkey"), WIDE_COLS, _WIDE).select(*_WIDE)


# so many rows of the fact table share a key that about two fifths of the rows repeat another one
_DUP_KEY = "(l_orderkey * 8 + l_linenumber) // 2"


def duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """10 skewed columns that follow a key which several rows share."""
    key = F.floor((F.col("l_orderkey") * 8 + F.col("l_linenumber")) / 2)
    return _made(read_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber"), key, DUP_COLS, _DUP).select(*_DUP)


def weather(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = read_table(spark, sf_dir, "lineitem")
    d, s = F.to_date("l_shipdate"), F.col("l_suppkey")
    reading = s * 4096 + F.unix_date(d) % 4096
    half = F.when(F.month(d) <= 6, 0).otherwise(1)
    dates = [half.alias("half"), F.quarter(d).alias("quarter"), F.year(d).alias("year"), F.dayofweek(d).alias("day_of_week"), F.month(d).alias("month")]
    place = [(s % 24).alias("zone"), (s * 7 % 180).alias("latitude"), (s * 13 % 360).alias("longitude"), s.alias("station"), _day("l_shipdate").alias("day")]
    rest = li.select(*dates, F.dayofmonth(d).alias("day_of_month"), *place, reading.alias("reading"))
    return _made(rest, F.col("reading"), SKY_COLS, _SKY, 60).select(*WEATHER)


def _weather_sql() -> str:
    d = "CAST(l_shipdate AS DATE)"
    key = f"(l_suppkey * 4096 + {_sql_day('l_shipdate')} % 4096)"
    sky = ", ".join(f"{_mixed_sql(key, 60 + j, *spec)} AS {n}" for j, (spec, n) in enumerate(zip(SKY_COLS, _SKY, strict=True)))
    return (
        f"SELECT CASE WHEN month({d}) <= 6 THEN 0 ELSE 1 END AS half, quarter({d}) AS quarter, year({d}) AS year, dayofweek({d}) + 1 AS day_of_week, month({d}) AS month, {sky}, "
        f"day({d}) AS day_of_month, l_suppkey % 24 AS zone, l_suppkey * 7 % 180 AS latitude, l_suppkey * 13 % 360 AS longitude, l_suppkey AS station, {_sql_day('l_shipdate')} AS day FROM lineitem"
    )


def ssb_larger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The star-schema table two and a half times: copies with keys and prices of their own."""
    df = ssb(spark, sf_dir)
    second = df.select(*[_shifted(c, 1) for c in SSB])
    third = df.where("l_linenumber <= 3 or (l_linenumber = 4 and l_suppkey % 2 = 0)").select(*[_shifted(c, 2) for c in SSB])
    return df.unionByName(second).unionByName(third)


_SHIFTS = {"l_orderkey": 10_000_000, "l_extendedprice": 1_000_000, "l_partkey": 1_000_000, "l_suppkey": 100_000}


def _shifted(c: str, k: int):  # noqa: ANN202
    return (F.col(c) + k * _SHIFTS[c]).alias(c) if c in _SHIFTS else F.col(c)


def _ssb_larger_sql(source: str) -> str:
    def copy(k: int) -> str:
        return "SELECT " + ", ".join(f"{c} + {k * _SHIFTS[c]} AS {c}" if c in _SHIFTS else c for c in SSB) + f" FROM ({source})"

    return f"SELECT * FROM ({source}) UNION ALL {copy(1)} UNION ALL {copy(2)} WHERE l_linenumber <= 3 OR (l_linenumber = 4 AND l_suppkey % 2 = 0)"


WORKS["wide"] = Work(wide, _made_sql("SELECT * FROM orders", "o_orderkey", WIDE_COLS, _WIDE), _WIDE)
WORKS["duplicates"] = Work(duplicates, _made_sql("SELECT * FROM lineitem", f"({_DUP_KEY})", DUP_COLS, _DUP), _DUP)
WORKS["weather"] = Work(weather, _weather_sql(), WEATHER)
WORKS["ssb_larger"] = Work(ssb_larger, _ssb_larger_sql(WORKS["ssb"].sql), SSB)

# two columns of which the first has more values, as in the toy table
_PAIR = ["p_name", "p_size"]
WORKS["pair"] = Work(lambda s, d: read_table(s, d, "part").select(*_PAIR), f"SELECT {', '.join(_PAIR)} FROM part", _PAIR)

TOY_ROWS = [(1, 3), (2, 1), (2, 2), (3, 3), (4, 1), (4, 2), (5, 3), (6, 1), (6, 2), (7, 4), (8, 3)]
TOY8_ROWS = [(2, 1), (1, 1), (1, 2), (1, 1), (3, 1), (1, 3), (3, 2), (3, 3)]


def values_sql(rows: list[tuple[int, int]]) -> str:
    return "SELECT * FROM (VALUES " + ", ".join(map(str, rows)) + ") t(a, b)"


WORKS["toy"] = Work(lambda s, d: s.createDataFrame(TOY_ROWS, "a int, b int"), values_sql(TOY_ROWS), ["a", "b"])
WORKS["toy8"] = Work(lambda s, d: s.createDataFrame(TOY8_ROWS, "a int, b int"), values_sql(TOY8_ROWS), ["a", "b"])
for _cards in ([4, 4], [2, 2, 2], [3, 3, 3]):
    _names = [f"c{j + 1}" for j in range(len(_cards))]
    _from = " CROSS JOIN ".join(f"(SELECT CAST(range AS INTEGER) AS {c} FROM range(1, {n + 1}))" for c, n in zip(_names, _cards, strict=True))
    WORKS["grid" + "".join(map(str, _cards))] = Work(
        lambda s, d, k=tuple(_cards): synth.grid_table(s, list(k)), f"SELECT {', '.join(_names)} FROM {_from}", _names
    )
