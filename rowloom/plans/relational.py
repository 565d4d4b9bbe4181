"""Queries around the methods: scans, projections, filters, joins, aggregates, windows, sets, functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from rowloom.operators import dictionary as D
from rowloom.operators import order as O
from rowloom.plans import oracle as S
from rowloom.plans.registry import query
from rowloom.plans.workloads import WORKS
from rowloom.sources import io
from rowloom.sources.scratch import scratch_path
from rowloom.sources.synth import skewed_lineitem

T = io.read_table


@query("scan_parquet", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_linenumber) AS BIGINT) AS lines FROM lineitem WHERE l_quantity > 25 GROUP BY ALL")
def scan_parquet(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Filter and columns reach the scan."""
    rows = T(spark, sf_dir, "lineitem").where("l_quantity > 25")
    return rows.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_linenumber").alias("lines"))


_COUNTED = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "embeddings")


@query("scan_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in _COUNTED))
def scan_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for t in _COUNTED:
        one = T(spark, sf_dir, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.union(one)
    return out


@query("scan_formats", "SELECT f AS format, count(*) AS n, CAST(sum(n_nationkey) AS BIGINT) AS keys FROM nation, (VALUES ('csv'), ('json'), ('orc'), ('parquet')) t(f) GROUP BY f")
def scan_formats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same rows through every file format."""
    df = T(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    out = None
    for kind in ("csv", "json", "orc", "parquet"):
        path = scratch_path(spark, kind)
        df.write.format(kind).save(path)
        got = io.read_any(spark, path, kind, "n_nationkey int, n_name string")
        one = got.agg(F.count("*").alias("n"), F.sum("n_nationkey").alias("keys")).select(F.lit(kind).alias("format"), "n", "keys")
        out = one if out is None else out.union(one)
    return out


@query("scan_zipf_source", S.run_rows(WORKS["zipf"].sql, WORKS["zipf"].cols, "lexicographic", "lexicographic"))
def scan_zipf_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The generator as a data source."""
    from rowloom.operators.runs import run_count
    from rowloom.sources.zipf_source import register

    register(spark)
    df = spark.read.format("zipf").option("n", 8192).option("columns", 4).load()
    cols = WORKS["zipf"].cols
    return run_count(O.order_by(df.select(*cols), "lexicographic", cols, "given"), cols, "lexicographic")


@query("zipf_rows", f"SELECT c1, count(*) AS n FROM ({WORKS['skewed'].sql}) GROUP BY 1")
def zipf_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Zipfian values of the keys of the fact table."""
    return skewed_lineitem(T(spark, sf_dir, "lineitem"), 1).groupBy("c1").agg(F.count("*").alias("n"))


@query("sorted_sink", "SELECT count(*) AS n, count(*) AS positions, true AS files_disjoint FROM orders")
def sorted_sink(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A reordered table on disk: files hold successive positions."""
    df = O.order_by(WORKS["orders"].frame(spark, sf_dir), "interleave", WORKS["orders"].cols)
    path = scratch_path(spark, "sorted")
    io.write_ordered(df, path, 1024)
    files = spark.read.parquet(path).withColumn("file", F.input_file_name()).groupBy("file").agg(F.min("pos").alias("lo"), F.max("pos").alias("hi"), F.count("*").alias("n"))
    good = files.agg(F.sum("n").alias("n"), F.sum(F.col("hi") - F.col("lo") + 1).alias("positions"))
    return good.select("n", "positions", (F.col("n") == F.col("positions")).alias("files_disjoint"))


@query("project_unpivot", "SELECT o_orderkey, col, CAST(value AS VARCHAR) AS value FROM (SELECT o_orderkey, o_orderstatus, o_orderpriority FROM orders) UNPIVOT (value FOR col IN (o_orderstatus, o_orderpriority))")
def project_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T(spark, sf_dir, "orders").unpivot(["o_orderkey"], ["o_orderstatus", "o_orderpriority"], "col", "value")


@query("filter_predicates", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_linestatus LIKE 'O%' AND l_discount <> 0.05 AND l_tax IS NOT NULL AND l_linenumber IS DISTINCT FROM 3")
def filter_predicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col
    keep = c("l_quantity").between(10, 20) & c("l_returnflag").isin("A", "R") & c("l_linestatus").like("O%")
    keep = keep & (c("l_discount") != 0.05) & c("l_tax").isNotNull() & ~c("l_linenumber").eqNullSafe(F.lit(3))
    return T(spark, sf_dir, "lineitem").where(keep).select("l_orderkey", "l_linenumber", "l_quantity")


def _dict_join(kind: str, sql: str) -> None:
    @query(f"dict_join_{kind}", f"SELECT o.o_orderkey, d.code FROM orders o {sql} JOIN (SELECT * FROM (SELECT l_orderkey AS v, f, row_number() OVER (ORDER BY f DESC, l_orderkey) - 1 AS code FROM (SELECT l_orderkey, count(*) AS f FROM lineitem GROUP BY 1)) WHERE f > (SELECT count(*) / count(DISTINCT l_orderkey) FROM lineitem)) d ON o.o_orderkey = d.v")
    def plan(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Orders with the codes of those order keys that are more frequent than the mean in the whole fact table."""
        made = D.build_dictionary(T(spark, sf_dir, "lineitem").select("l_orderkey"), ["l_orderkey"])
        mean = F.broadcast(made.agg(F.avg("freq").alias("mean")))
        side = made.crossJoin(mean).where("freq > mean").select(F.col("l_orderkey").alias("v"), "code")
        return T(spark, sf_dir, "orders").join(side, F.col("o_orderkey") == F.col("v"), kind).select("o_orderkey", "code")


for _kind, _sql in (("inner", "INNER"), ("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    _dict_join(_kind, _sql)


@query("join_star", "SELECT n_name, c_mktsegment, l_returnflag, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL")
def join_star(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o = T(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag"), T(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    c, n = T(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment"), T(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    joined = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey"))
    return joined.join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name", "c_mktsegment", "l_returnflag").agg(F.count("*").alias("n"))


_FREQUENT = "SELECT l_suppkey FROM lineitem GROUP BY 1 HAVING count(*) > (SELECT count(*) / count(DISTINCT l_suppkey) FROM lineitem)"


@query("semi_frequent", f"SELECT s_suppkey, s_name FROM supplier WHERE s_suppkey IN ({_FREQUENT})")
def semi_frequent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _frequency_join(spark, sf_dir, "left_semi")


@query("anti_unseen", f"SELECT s_suppkey, s_name FROM supplier WHERE s_suppkey NOT IN ({_FREQUENT})")
def anti_unseen(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _frequency_join(spark, sf_dir, "left_anti")


def _frequency_join(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    hist = T(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("f"))
    mean = F.broadcast(hist.agg(F.avg("f").alias("mean")))
    often = hist.crossJoin(mean).where("f > mean").select("l_suppkey")
    return T(spark, sf_dir, "supplier").select("s_suppkey", "s_name").join(often, F.col("s_suppkey") == F.col("l_suppkey"), kind)


@query("pairs_hamming", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND (a.n_regionkey = b.n_regionkey OR right(a.n_name, 1) = right(b.n_name, 1))")
def pairs_hamming(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs that agree in a component, found by one equality join a component."""
    n = T(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey", F.substring("n_name", -1, 1).alias("head"))
    out = None
    for c in ("n_regionkey", "head"):
        one = n.select(F.col("n_nationkey").alias("a"), c).join(n.select(F.col("n_nationkey").alias("b"), c), c).where("a < b").select("a", "b")
        out = one if out is None else out.union(one)
    return out.distinct()


@query("lateral_components", "SELECT p_partkey, i, v FROM (SELECT p_partkey, unnest([1, 2, 3]) AS i, unnest([p_type, p_brand, CAST(p_size AS VARCHAR)]) AS v FROM part)")
def lateral_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    T(spark, sf_dir, "part").createOrReplaceTempView("part_rows")
    return spark.sql("SELECT p_partkey, t.i + 1 AS i, t.v FROM part_rows LATERAL VIEW posexplode(array(p_type, p_brand, string(p_size))) t AS i, v")


@query("agg_basic", "SELECT l_returnflag, count(*) AS n, min(l_quantity) AS lo, max(l_quantity) AS hi, round(avg(l_quantity), 6) AS mean, arg_max(l_orderkey, l_orderkey) AS last_key, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def agg_basic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(
        F.count("*").alias("n"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"), F.round(F.avg("l_quantity"), 6).alias("mean"),
        F.max_by("l_orderkey", "l_orderkey").alias("last_key"), F.count_distinct("l_suppkey").alias("suppliers"),
    )


_RC = ["o_orderstatus", "o_orderpriority", "o_custkey"]


@query("agg_rollup_prefix", f"SELECT CAST(g AS BIGINT) AS level, count(*) AS tuples FROM (SELECT grouping({_RC[0]}) + grouping({_RC[1]}) + grouping({_RC[2]}) AS g FROM orders GROUP BY ROLLUP ({', '.join(_RC)})) GROUP BY 1")
def agg_rollup_prefix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The prefix distincts of the bound on sorting are the levels of a rollup."""
    levels = T(spark, sf_dir, "orders").rollup(*_RC).agg((F.grouping(_RC[0]) + F.grouping(_RC[1]) + F.grouping(_RC[2])).cast("long").alias("level"))
    return levels.groupBy("level").agg(F.count("*").alias("tuples"))


@query("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("agg_grouping_sets", "SELECT l_returnflag, l_linestatus, l_linenumber, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), (l_linenumber))")
def agg_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The histograms of several columns in one pass."""
    cols = ["l_returnflag", "l_linestatus", "l_linenumber"]
    return T(spark, sf_dir, "lineitem").groupingSets([[c] for c in cols], *cols).agg(F.count("*").alias("n"))


@query("agg_distinct", "SELECT count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts, (SELECT count(*) FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem)) AS both FROM lineitem")
def agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T(spark, sf_dir, "lineitem").agg(F.count_distinct("l_suppkey").alias("suppliers"), F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey", "l_partkey").alias("both"))


@query(
    "agg_sketches",
    "SELECT count(l_partkey) AS kll_n, min(l_partkey) AS kll_least, max(l_partkey) AS kll_greatest, true AS hll, true AS quantile, true AS kll, true AS theta FROM lineitem",
)
def agg_sketches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketches: what they keep exactly, and whether estimates are near exact figures (distinct counts
    within 10 %, medians by rank within 3 %)."""
    li = T(spark, sf_dir, "lineitem")
    exact = li.agg(F.count_distinct("l_partkey").alias("d"), F.count("l_partkey").alias("n"))
    near = li.agg(
        F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", F.lit(12))).alias("h"), F.approx_percentile("l_extendedprice", 0.5, 1000).alias("q"),
        F.theta_sketch_estimate(F.theta_sketch_agg("l_partkey")).alias("t"), F.kll_sketch_agg_bigint("l_partkey").alias("k"),
    )
    middle = F.kll_sketch_get_quantile_bigint("k", F.lit(0.5))
    facts = near.select("h", "q", "t", F.kll_sketch_get_n_bigint("k").alias("kll_n"), *[F.kll_sketch_get_quantile_bigint("k", F.lit(x)).alias(y) for x, y in ((0.0, "kll_least"), (1.0, "kll_greatest"))], middle.alias("m"))
    one = F.broadcast(facts)
    # the ranks of the two medians in the whole table
    ranks = li.crossJoin(one.select("q", "m")).agg(F.count_if(F.col("l_extendedprice") <= F.col("q")).alias("rq"), F.count_if(F.col("l_partkey") <= F.col("m")).alias("rm"))
    close = lambda a, b, part: F.abs(a - b) <= b * part
    return exact.crossJoin(facts).crossJoin(ranks).select(
        "kll_n", "kll_least", "kll_greatest", close(F.col("h"), F.col("d"), 0.1).alias("hll"), close(F.col("rq"), F.col("n") / 2, 0.06).alias("quantile"),
        close(F.col("rm"), F.col("n") / 2, 0.06).alias("kll"), close(F.col("t"), F.col("d"), 0.1).alias("theta"),
    )


@query("agg_count_min", "SELECT l_linenumber AS value, count(*) AS estimate FROM lineitem GROUP BY 1")
def agg_count_min(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of a column with few values from one count-min sketch, whose width leaves them apart."""
    from rowloom.functions.sketches import count_min_estimate

    li = T(spark, sf_dir, "lineitem").select(F.col("l_linenumber").cast("long").alias("value"))
    sketch = li.agg(F.count_min_sketch("value", F.lit(0.0005), F.lit(0.99), F.lit(17)).alias("sketch"))
    asked = li.select("value").distinct().crossJoin(F.broadcast(sketch))
    return asked.select(F.col("value").cast("int").alias("value"), count_min_estimate("sketch", "value").alias("estimate"))


@query("win_ranking", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER p AS rk, dense_rank() OVER p AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER p, 6) AS pr, round(cume_dist() OVER p, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), p AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def win_ranking(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, p = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"), W.partitionBy("o_custkey").orderBy("o_orderpriority")
    return T(spark, sf_dir, "orders").select(
        "o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(p).alias("rk"), F.dense_rank().over(p).alias("dr"), F.ntile(4).over(w).alias("quarter"),
        F.round(F.percent_rank().over(p), 6).alias("pr"), F.round(F.cume_dist().over(p), 6).alias("cd"),
    )


@query("win_lag_runs", "SELECT o_orderkey, lag(o_orderstatus) OVER w AS before, lead(o_orderstatus) OVER w AS after, first_value(o_orderstatus) OVER w AS first, nth_value(o_orderstatus, 2) OVER w AS second FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def win_lag_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = W.partitionBy("o_custkey").orderBy("o_orderkey")
    s = "o_orderstatus"
    return T(spark, sf_dir, "orders").select("o_orderkey", F.lag(s).over(w).alias("before"), F.lead(s).over(w).alias("after"), F.first(s).over(w).alias("first"), F.nth_value(s, 2).over(w).alias("second"))


@query("win_running_run_id", "SELECT o_orderkey, CAST(sum(new) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS BIGINT) AS run_id, CAST(count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS last3, CAST(count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS BIGINT) AS near FROM (SELECT *, CASE WHEN o_orderstatus IS DISTINCT FROM lag(o_orderstatus) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) THEN 1 ELSE 0 END AS new FROM orders)")
def win_running_run_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = W.partitionBy("o_custkey").orderBy("o_orderkey")
    new = (~F.col("o_orderstatus").eqNullSafe(F.lag("o_orderstatus").over(w))).cast("int")
    return T(spark, sf_dir, "orders").withColumn("new", new).select(
        "o_orderkey", F.sum("new").over(w.rowsBetween(W.unboundedPreceding, 0)).alias("run_id"),
        F.count("*").over(w.rowsBetween(-2, 0)).alias("last3"), F.count("*").over(w.rangeBetween(-1000, 0)).alias("near"),
    )


@query("topk_frequent", "SELECT l_returnflag, l_partkey, n FROM (SELECT l_returnflag, l_partkey, count(*) AS n, row_number() OVER (PARTITION BY l_returnflag ORDER BY count(*) DESC, l_partkey) AS rn FROM lineitem GROUP BY 1, 2) WHERE rn <= 5")
def topk_frequent(spark: SparkSession, sf_dir: str) -> DataFrame:
    h = T(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_partkey").agg(F.count("*").alias("n"))
    return h.withColumn("rn", F.row_number().over(W.partitionBy("l_returnflag").orderBy(F.desc("n"), "l_partkey"))).where("rn <= 5").drop("rn")


@query("sort_limit_offset", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def sort_limit_offset(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20)


_A, _B = "SELECT l_orderkey AS k FROM lineitem WHERE l_returnflag = 'A'", "SELECT l_orderkey AS k FROM lineitem WHERE l_returnflag = 'R'"
for _name, _op in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):

    def _set(spark: SparkSession, sf_dir: str, op: str = _name) -> DataFrame:
        li = T(spark, sf_dir, "lineitem")
        a, b = (li.where(F.col("l_returnflag") == x).select(F.col("l_orderkey").alias("k")) for x in "AR")
        got = {
            "union": lambda: a.unionByName(b).distinct(), "union_all": lambda: a.unionByName(b), "intersect": lambda: a.intersect(b),
            "intersect_all": lambda: a.intersectAll(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b),
        }[op]()
        return got.groupBy("k").agg(F.count("*").alias("n"))

    query(f"setop_{_name}", f"SELECT k, count(*) AS n FROM ({_A} {_op} {_B}) GROUP BY k")(_set)


@query("fn_string", "SELECT p_partkey, length(p_name) AS len, upper(p_name) AS up, substr(p_brand, 1, 5) AS head, p_type || '/' || p_brand AS joined, replace(p_brand, 'Brand', 'B') AS short, reverse(p_type) AS back, string_split(p_name, ' ')[1] AS first_word, regexp_extract(p_brand, '[0-9]+') AS digits, lpad(CAST(p_size AS VARCHAR), 4, '0') AS padded, translate(p_type, 'AEIOU', 'aeiou') AS vowels FROM part")
def fn_string(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T(spark, sf_dir, "part").select(
        "p_partkey", F.length("p_name").alias("len"), F.upper("p_name").alias("up"), F.substring("p_brand", 1, 5).alias("head"), F.concat("p_type", F.lit("/"), "p_brand").alias("joined"),
        F.replace("p_brand", F.lit("Brand"), F.lit("B")).alias("short"), F.reverse("p_type").alias("back"), F.split("p_name", " ")[0].alias("first_word"),
        F.regexp_extract("p_brand", "[0-9]+", 0).alias("digits"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"), F.translate("p_type", "AEIOU", "aeiou").alias("vowels"),
    )


@query("fn_date", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS VARCHAR)[1:10] AS month_start, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(dayofmonth(o_orderdate) AS INTEGER) AS d, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS dow, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(CAST(o_orderdate AS DATE) + INTERVAL 10 DAY AS VARCHAR)[1:10] AS later FROM orders")
def fn_date(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    return T(spark, sf_dir, "orders").select(
        "o_orderkey", F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("month_start"), F.year(d).alias("y"), F.month(d).alias("m"), F.dayofmonth(d).alias("d"), F.dayofweek(d).alias("dow"),
        F.datediff(F.to_date(d), F.lit("1992-01-01").cast("date")).alias("days"), F.date_format(F.date_add(F.to_date(d), 10), "yyyy-MM-dd").alias("later"),
    )


@query("fn_array_key", "SELECT l_orderkey, l_linenumber, l_suppkey, list_sort([l_linenumber, l_suppkey, l_orderkey % 10]) AS sorted, list_sum([l_linenumber, l_suppkey])::BIGINT AS total, len(range(1, l_linenumber + 1)) AS steps, list_reverse([l_linenumber, l_suppkey]) AS back FROM lineitem")
def fn_array_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    n, s, k = (F.col(c).cast("long") for c in ("l_linenumber", "l_suppkey", "l_orderkey"))
    return T(spark, sf_dir, "lineitem").select(
        "l_orderkey", "l_linenumber", "l_suppkey", F.sort_array(F.array(n, s, k % 10)).alias("sorted"), F.aggregate(F.array(n, s), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"),
        F.size(F.sequence(F.lit(1).cast("long"), n)).cast("long").alias("steps"), F.reverse(F.array(n, s)).alias("back"),
    )


@query("fn_json_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k, json_extract(props, '$.none') IS NULL AS missing FROM events")
def fn_json_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.get_json_object("props", "$.none").isNull().alias("missing"))


@query("fn_map_dictionary", "SELECT l_returnflag, list_sort(list(l_linenumber || ':' || n)) AS counts FROM (SELECT l_returnflag, l_linenumber, count(*) AS n FROM lineitem GROUP BY ALL) GROUP BY 1")
def fn_map_dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    h = T(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linenumber").agg(F.count("*").alias("n"))
    made = h.groupBy("l_returnflag").agg(F.map_from_entries(F.collect_list(F.struct("l_linenumber", "n"))).alias("m"))
    pairs = F.transform(F.map_entries("m"), lambda e: F.concat(e["key"].cast("string"), F.lit(":"), e["value"].cast("string")))
    return made.select("l_returnflag", F.array_sort(pairs).alias("counts"))


@query("fn_null_safe", "SELECT a, b, a IS NOT DISTINCT FROM b AS same, coalesce(a, b, -1) AS one, nullif(a, b) AS differs, CASE WHEN a IS NULL THEN 'none' WHEN a > 1 THEN 'big' ELSE 'small' END AS kind FROM (SELECT DISTINCT nullif(CAST(l_linenumber % 5 AS INTEGER), 0) AS a, nullif(CAST(l_suppkey % 4 AS INTEGER), 0) AS b FROM lineitem)")
def fn_null_safe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Null-safe functions of the pairs of line number and supplier remainders, zeros standing as nulls."""
    part = lambda c, n: F.nullif((F.col(c) % n).cast("int"), F.lit(0))
    df = T(spark, sf_dir, "lineitem").select(part("l_linenumber", 5).alias("a"), part("l_suppkey", 4).alias("b")).distinct()
    return df.select("a", "b", F.col("a").eqNullSafe(F.col("b")).alias("same"), F.coalesce("a", "b", F.lit(-1)).alias("one"), F.nullif("a", "b").alias("differs"), F.when(F.col("a").isNull(), "none").when(F.col("a") > 1, "big").otherwise("small").alias("kind"))


@query("udtf_runs", f"WITH o AS (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_orderkey) AS rn FROM orders), f AS (SELECT *, CASE WHEN o_orderstatus IS DISTINCT FROM lag(o_orderstatus) OVER (PARTITION BY o_orderpriority ORDER BY rn) THEN 1 ELSE 0 END AS new FROM o) SELECT o_orderpriority, CAST(sum(new) AS BIGINT) AS runs, count(*) AS n FROM f GROUP BY 1")
def udtf_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Run counts of ordered groups by a table function."""
    from rowloom.functions.tables import register_table_functions

    register_table_functions(spark)
    T(spark, sf_dir, "orders").select("o_orderpriority", "o_orderkey", "o_orderstatus").createOrReplaceTempView("ordered_status")
    return spark.sql("SELECT k AS o_orderpriority, runs, n FROM runs_of(TABLE(ordered_status) PARTITION BY o_orderpriority ORDER BY o_orderkey)")


@query("udaf_runs", "WITH f AS (SELECT o_orderpriority, CASE WHEN o_orderstatus IS DISTINCT FROM lag(o_orderstatus) OVER (PARTITION BY o_orderpriority ORDER BY o_orderkey) THEN 1 ELSE 0 END AS new FROM orders) SELECT o_orderpriority, CAST(sum(new) AS BIGINT) AS runs FROM f GROUP BY 1")
def udaf_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Run counts of ordered groups by a grouped aggregate function."""
    from rowloom.functions.tables import group_runs

    return T(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(group_runs("o_orderkey", "o_orderstatus").alias("runs"))
