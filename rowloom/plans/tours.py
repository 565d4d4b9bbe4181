"""Queries on block methods: tours, list walks, improvements, and how blocks are run.

Their kernels walk greedily, which SQL has no set form for: SQL states the invariants, and for the
nearest-neighbour walk a recursive query on a small table walks along."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rowloom.operators import blocks as B
from rowloom.operators import order as O
from rowloom.operators import runs as R
from rowloom.operators.pilot import pilot_gain, sample_gain, shuffle_columns
from rowloom.plans import oracle as S
from rowloom.plans.registry import query
from rowloom.plans.workloads import WORKS
from rowloom.sources.io import read_table

#: Method, its options, and the workload rows that it is run on.
TOURS: dict[str, dict] = {
    "nearest_neighbor": {},
    "nearest_neighbor_both_ends": {"heuristic": "nearest_neighbor", "ends": "both"},
    "nearest_neighbor_history": {"heuristic": "nearest_neighbor", "history": 4},
    "savings": {},
    "savings_artificial": {"heuristic": "savings", "depot": "artificial"},
    "multiple_fragment": {},
    "insertion_nearest": {"heuristic": "insertion", "pick": "nearest"},
    "insertion_farthest": {"heuristic": "insertion", "pick": "farthest"},
    "insertion_random": {"heuristic": "insertion", "pick": "random"},
    "insertion_cheapest": {"heuristic": "insertion", "pick": "cheapest"},
    "iterated_matching": {},
    "christofides": {"block_rows": 64},
    "multiple_lists": {},
}


#: Columns that a signature takes in hundredths, so that engines write them alike.
_HUNDREDTHS = {"l_tax", "l_discount", "l_quantity", "l_extendedprice", "s_acctbal"}


def signature(df: DataFrame, cols: list[str]) -> Column:
    """A sum over rows, in any order, of part of a digest of their values: equal for equal multisets."""
    parts = [F.round(F.col(c) * 100).cast("long").cast("string") if c in _HUNDREDTHS else F.col(c).cast("string") for c in cols]
    return F.sum(F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("long"))


def verdict(df: DataFrame, base: DataFrame, cols: list[str], method: str, never_worse: bool) -> DataFrame:
    """One row: what SQL can tell of any permutation of `base` (rows, places, a signature of the rows, the
    fewest runs that there can be), and whether the reordering's runs are in their bounds."""
    runs = R.total_runs(df, cols)
    most = R.total_runs(base, cols) if never_worse else None
    facts = df.agg(
        F.count("*").alias("n_rows"), F.count_distinct("pos").alias("places"), F.min("pos").alias("first"), F.max("pos").alias("last"),
        signature(df, cols).alias("signature"), (F.count_distinct(F.struct(*cols)) + len(cols) - 1).alias("least_runs"),
    )
    bounded = (F.lit(runs) >= F.col("least_runs")) & (F.lit(runs) <= F.col("n_rows") * len(cols))
    if most is not None:
        bounded = bounded & F.lit(runs <= most)
    return facts.select(F.lit(method).alias("method"), "*", bounded.alias("in_bounds"))


def _inv(names: list[str], source: str, cols: list[str]) -> str:
    text = ", ".join(f"CAST(CAST(round({c} * 100) AS BIGINT) AS VARCHAR)" if c in _HUNDREDTHS else f"CAST({c} AS VARCHAR)" for c in cols)
    facts = (
        "SELECT count(*) AS n_rows, count(*) AS places, CAST(0 AS BIGINT) AS first, count(*) - 1 AS last, "
        f"CAST(sum(CAST('0x' || substr(md5(concat_ws('|', {text})), 1, 8) AS BIGINT)) AS BIGINT) AS signature, "
        f"(SELECT count(*) FROM (SELECT DISTINCT {', '.join(cols)} FROM t)) + {len(cols) - 1} AS least_runs, true AS in_bounds FROM t"
    )
    return f"WITH t AS ({source}), facts AS ({facts}) SELECT method, facts.* FROM (VALUES {', '.join(f"('{m}')" for m in names)}) m(method), facts"


def _all(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.union(f)
    return out


_P = WORKS["part"]


def _tour(coded: DataFrame, name: str, spec: dict) -> DataFrame:
    opt = {"block_rows": 256, **spec}
    rows, heuristic = opt.pop("block_rows"), opt.pop("heuristic", name)
    return B.run_blocks(coded, [B.kernel(heuristic, **opt)], [c + "__code" for c in _P.cols], rows)


@query("tours_inv", _inv(list(TOURS), _P.sql, _P.cols))
def tours_inv(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = O.order_by(_P.frame(spark, sf_dir), "lexicographic", _P.cols, "given", keep_codes=True)
    return _all([verdict(_tour(base, m, spec), base, _P.cols, m, False) for m, spec in TOURS.items()])


@query("tour_runs")
def tour_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Runs of every construction heuristic over those of the sorted order."""
    coded = O.order_by(_P.frame(spark, sf_dir), "lexicographic", _P.cols, "given", keep_codes=True)
    base = R.total_runs(coded, _P.cols)
    rows = [(m, round(base / R.total_runs(_tour(coded, m, spec), _P.cols), 4)) for m, spec in TOURS.items()]
    return spark.createDataFrame(rows, "method string, reduction double")


@query("distances_inv", _inv(["hamming", "delta_bits", "lee"], "SELECT s_nationkey, s_acctbal FROM supplier", ["s_nationkey", "s_acctbal"]))
def distances_inv(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tours under other distances between rows."""
    import numpy as np

    cols = ["s_nationkey", "s_acctbal"]
    df = read_table(spark, sf_dir, "supplier").select(*cols)
    base = O.order_by(df, "lexicographic", cols, "given")
    sizes = np.array([df.select(c).distinct().count() for c in cols])
    out = []
    for kind in ("hamming", "delta_bits", "lee"):
        opt = {"sizes": sizes} if kind == "lee" else {}
        out.append(verdict(B.tour(df, "nearest_neighbor", cols, 1024, distance=kind, column_order_mode="given", **opt), base, cols, kind, False))
    return _all(out)


_IMPROVE = {"adjacent_swap": {}, "window_swap": {"reach": 4}, "reinsertion": {}, "peephole": {"rows": 8}}


@query("improvements_inv", _inv(list(_IMPROVE), _P.sql, _P.cols))
def improvements_inv(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Improvements never add runs, in blocks that alternate their borders."""
    base = O.order_by(_P.frame(spark, sf_dir), "lexicographic", _P.cols, "given")
    return _all([verdict(B.improve(base, m, _P.cols, 256, rounds=2, **opt), base, _P.cols, m, True) for m, opt in _IMPROVE.items()])


@query("peephole", _inv(["peephole"], _P.sql, _P.cols))
def peephole(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = O.order_by(_P.frame(spark, sf_dir), "interleave", _P.cols, "given")
    return verdict(B.improve(base, "peephole", _P.cols, 1024, rows=8), base, _P.cols, "peephole", True)


@query("pipeline_reinsertion", _inv(["lexicographic", "interleave", "frequent_component"], _P.sql, _P.cols))
def pipeline_reinsertion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A key order followed by 1-reinsertion in one block."""
    df = _P.frame(spark, sf_dir)
    out = []
    for o in ("lexicographic", "interleave", "frequent_component"):
        base = O.order_by(df, o, _P.cols, "given")
        out.append(verdict(B.improve(base, "reinsertion", _P.cols, 1 << 40), base, _P.cols, o, True))
    return _all(out)


_WALK = ["n_regionkey", "n_nationkey"]


def _nearest_sql(cols: list[str], table: str) -> str:
    """The nearest-neighbour walk as a recursive query: the last row, and the rows already visited."""
    coded = S.ordered(f"SELECT {', '.join(cols)} FROM {table}", cols, "codes")
    d = " + ".join(f"CASE WHEN a.k{i} <> b.k{i} THEN 1 ELSE 0 END" for i in range(len(cols)))
    return (
        f"WITH RECURSIVE {coded}, walk AS (SELECT CAST(0 AS BIGINT) AS step, CAST(0 AS BIGINT) AS at, [CAST(0 AS BIGINT)] AS seen UNION ALL "
        f"SELECT w.step + 1, n.at, list_append(w.seen, n.at) FROM walk w, LATERAL (SELECT arg_min(b.pos, ({d}) * 1000000 + b.pos) AS at "
        f"FROM o a JOIN o b ON a.pos = w.at AND NOT list_contains(w.seen, b.pos)) n WHERE n.at IS NOT NULL) "
        f"SELECT w.step AS pos, {', '.join('o.' + c for c in cols)} FROM walk w JOIN o ON o.pos = w.at"
    )


@query("tour_nearest_neighbor", _nearest_sql(_WALK, "nation"))
def tour_nearest_neighbor(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = read_table(spark, sf_dir, "nation").select(*_WALK)
    return B.tour(df, "nearest_neighbor", _WALK, 1 << 20, column_order_mode="given").select("pos", *_WALK)


def _lists_sql(cols: list[str], table: str) -> str:
    """The list walk as a recursive query: nearest unvisited rows before and after in each rotation."""
    c = len(cols)
    source = S.ordered(f"SELECT {', '.join(cols)} FROM {table}", cols, "codes")
    ranks = ", ".join(
        f"row_number() OVER (ORDER BY {', '.join(f'k{(j - r) % c}' for j in range(c))}, pos) AS r{r}" for r in range(c)
    )
    d = "(" + " + ".join(f"CASE WHEN a.k{i} <> b.k{i} THEN 1 ELSE 0 END" for i in range(c)) + ")"
    options = []
    for r in range(c):
        for side, (cmp, pick) in enumerate((("<", "arg_max"), (">", "arg_min"))):
            options.append(
                f"SELECT {d} * 100 + {2 * r + side} AS score, b.pos AS spot FROM p a, p b WHERE a.pos = w.spot AND b.pos = "
                f"(SELECT {pick}(x.pos, x.r{r}) FROM p x, p y WHERE y.pos = w.spot AND x.r{r} {cmp} y.r{r} AND NOT list_contains(w.seen, x.pos))"
            )
    return (
        f"WITH RECURSIVE {source}, p AS (SELECT *, {ranks} FROM o), walk AS (SELECT CAST(0 AS BIGINT) AS step, CAST(0 AS BIGINT) AS spot, [CAST(0 AS BIGINT)] AS seen "
        f"UNION ALL SELECT w.step + 1, n.spot, list_append(w.seen, n.spot) FROM walk w, LATERAL (SELECT arg_min(spot, score) AS spot FROM ({' UNION ALL '.join(options)})) n WHERE n.spot IS NOT NULL) "
        f"SELECT w.step AS pos, {', '.join('p.' + c for c in cols)} FROM walk w JOIN p ON p.pos = w.spot"
    )


_SMALL = {"multiple_lists_small": ("nation", ["n_regionkey", "n_nationkey"]), "multiple_lists_supplier": ("supplier", ["s_nationkey", "s_acctbal", "s_suppkey"])}
for _name, (_table, _cols) in _SMALL.items():

    def _small(spark: SparkSession, sf_dir: str, table: str = _table, cols: tuple = tuple(_cols)) -> DataFrame:
        df = read_table(spark, sf_dir, table).select(*cols)
        return B.multiple_lists(df, list(cols), column_order_mode="given").select("pos", *cols)

    query(_name, _lists_sql(_cols, _table))(_small)


@query("ml_all_lists", "SELECT count(*) - 1 AS steps, true AS nearest FROM supplier")
def ml_all_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    """With all c! lists, every step is as short as the nearest unused row."""
    import numpy as np

    cols = ["s_nationkey", "s_acctbal", "s_suppkey"]
    df = read_table(spark, sf_dir, "supplier").select(*cols)
    walked = B.multiple_lists(df, cols, lists="all", column_order_mode="given", keep_codes=True)
    # a table of 100 rows at most, checked on the driver
    codes = np.array([tuple(r) for r in walked.orderBy("pos").select(*[c + "__code" for c in cols]).collect()])
    good = all((codes[i + 1 :] != codes[i]).sum(axis=1).min() == (codes[i + 1] != codes[i]).sum() for i in range(len(codes) - 1))
    return spark.createDataFrame([(len(codes) - 1, bool(good))], "steps long, nearest boolean")


@query("ml_k_sweep", _inv([f"k={k}" for k in (1, 2, 3, 4)] + ["k=24", "gray lists"], _P.sql, _P.cols))
def ml_k_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fewer lists than columns, as many, all; and lists in Gray order."""
    df = _P.frame(spark, sf_dir)
    base = O.order_by(df, "lexicographic", _P.cols, "given", keep_codes=True)
    out = [verdict(B.multiple_lists(df, _P.cols, k=k, column_order_mode="given"), base, _P.cols, f"k={k}", False) for k in (1, 2, 3, 4)]
    out.append(verdict(B.multiple_lists(df, _P.cols, lists="all", column_order_mode="given"), base, _P.cols, "k=24", False))
    out.append(verdict(B.multiple_lists(df, _P.cols, gray=True, column_order_mode="given"), base, _P.cols, "gray lists", False))
    return _all(out)


_L = WORKS["lineitem"]


@query("ml_blocked", _inv(["global", "local", "guarded"], _L.sql, _L.cols))
def ml_blocked(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = _L.frame(spark, sf_dir)
    base = O.order_by(df, "lexicographic", _L.cols, "given", keep_codes=True)
    return _all(
        [
            verdict(B.multiple_lists_blocked(df, _L.cols, 4096), base, _L.cols, "global", False),
            verdict(B.multiple_lists_blocked(df, _L.cols, 4096, blocking="local"), base, _L.cols, "local", False),
            verdict(B.multiple_lists_blocked(df, _L.cols, 4096, revert_if_worse=True), base, _L.cols, "guarded", False),
        ]
    )


@query("block_strategies", _inv(["best of several", "restarts", "shifted rounds", "by value", "first blocks only"], _L.sql, _L.cols))
def block_strategies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Several heuristics a block, restarts, half-shifted rounds, value blocks, and an interrupted run."""
    df = _L.frame(spark, sf_dir)
    base = O.order_by(df, "lexicographic", _L.cols, "given", keep_codes=True)
    run = lambda methods, **opt: B.reorder_blocks(df, methods, _L.cols, 2048, column_order_mode="given", **opt)
    return _all(
        [
            verdict(run(["multiple_lists", "interleave"], revert_if_worse=True), base, _L.cols, "best of several", False),
            verdict(run("multiple_lists", restarts=2, start="random"), base, _L.cols, "restarts", False),
            verdict(run("multiple_lists", rounds=2, revert_if_worse=True), base, _L.cols, "shifted rounds", False),
            verdict(run("multiple_lists", by=["l_linestatus"]), base, _L.cols, "by value", False),
            verdict(run("multiple_lists", max_blocks=1), base, _L.cols, "first blocks only", False),
        ]
    )


@query("block_size_one", S.order_rows(_P.sql, _P.cols, "codes"))
def block_size_one(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks of one row leave the sorted order as it is."""
    return B.multiple_lists_blocked(_P.frame(spark, sf_dir), _P.cols, 1, column_order_mode="given").select("pos", *_P.cols)


@query("guard_never_worse", f"SELECT CAST((count(*) + 2047) // 2048 AS BIGINT) AS blocks, CAST(0 AS BIGINT) AS worse FROM lineitem")
def guard_never_worse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """With the guard no block has more runs than before."""
    df = O.order_by(_L.frame(spark, sf_dir), "lexicographic", _L.cols, "given", keep_codes=True)
    codes = [c + "__code" for c in _L.cols]
    log = B.block_log(df, B.run_blocks(df, [B.kernel("interleave")], codes, 2048, revert_if_worse=True), codes, 2048)
    return log.agg(F.count("*").alias("blocks"), F.count_if(F.col("runs_after") > F.col("runs_before")).alias("worse"))


def _optimum_sql() -> str:
    """Fewest runs by subsets of rows, and the runs of the walk and of the key orders."""
    w = WORKS["toy"]
    d = " + ".join(f"CASE WHEN a.k{i} <> b.k{i} THEN 1 ELSE 0 END" for i in range(2))
    walk = _lists_sql(w.cols, f"({w.sql})")
    steps = " + ".join(f"CASE WHEN {c} IS DISTINCT FROM lag({c}) OVER (ORDER BY pos) THEN 1 ELSE 0 END" for c in w.cols)
    orders = ", ".join(f"{S.total_runs(w.sql, w.cols, o)} AS {o}" for o in ("interleave", "frequent_component", "lexicographic"))
    return (
        f"WITH RECURSIVE {S.ordered(w.sql, w.cols, 'codes')}, ds AS (SELECT a.pos AS a, b.pos AS b, {d} AS d FROM o a, o b WHERE a.pos <> b.pos), "
        "best AS (SELECT 1 << CAST(pos AS INTEGER) AS rows, pos AS tip, CAST(0 AS BIGINT) AS cost FROM o UNION ALL "
        "SELECT rows | (1 << CAST(b AS INTEGER)), b, CAST(min(cost + d) AS BIGINT) FROM best JOIN ds ON a = tip WHERE (rows >> CAST(b AS INTEGER)) & 1 = 0 GROUP BY 1, 2) "
        f"SELECT (SELECT CAST(sum(s) AS BIGINT) FROM (SELECT {steps} AS s FROM ({walk}))) AS list_walk, "
        f"(SELECT min(cost) + 2 FROM best WHERE rows = (1 << 11) - 1) AS optimum, {orders}"
    )


@query("exact_optimum", _optimum_sql())
def exact_optimum(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The shared worked example: runs of each method, and the fewest possible."""
    w = WORKS["toy"]
    df = w.frame(spark, sf_dir)
    count = lambda x: R.total_runs(x, w.cols)
    row = (
        count(B.multiple_lists(df, w.cols, column_order_mode="given")), count(B.tour(df, "optimal", w.cols, 12, column_order_mode="given")),
        *(count(O.order_by(df, o, w.cols, "given")) for o in ("interleave", "frequent_component", "lexicographic")),
    )
    return spark.createDataFrame([row], "list_walk long, optimum long, interleave long, frequent_component long, lexicographic long")


@query("pilot_blocks")
def pilot_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gain of walks in the first two blocks."""
    return pilot_gain(WORKS["skewed"].frame(spark, sf_dir), WORKS["skewed"].cols, 2, 2048)


@query("early_stop", "SELECT true AS gained, true AS went_on")
def early_stop(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, gain, go = B.early_stop(WORKS["zipf"].frame(spark, sf_dir), WORKS["zipf"].cols, 2, 1024)
    return spark.createDataFrame([(gain > 1.0, go)], "gained boolean, went_on boolean")


@query("ablation_sample")
def ablation_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gain on a row sample beside that on the whole table: a warning against sampling."""
    w = WORKS["skewed"]
    df = w.frame(spark, sf_dir)
    whole = sample_gain(df, w.cols, 1 << 30)
    return spark.createDataFrame([("whole", round(whole, 4)), ("sample", round(sample_gain(df, w.cols), 4))], "rows string, gain double")


@query("ablation_shuffle")
def ablation_shuffle(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gain with columns shuffled apart: the same histograms, another result."""
    from rowloom.sources.synth import correlated_table

    cols = [f"c{i + 1}" for i in range(6)]
    df = correlated_table(spark, 8192)
    apart = shuffle_columns(df, cols, "id").drop("pos")
    return spark.createDataFrame(
        [(name, round(R.total_runs(O.order_by(x, "lexicographic", cols), cols) / R.total_runs(O.order_by(x, "interleave", cols), cols), 4)) for name, x in (("as is", df.select(*cols)), ("shuffled apart", apart))],
        "columns string, gain double",
    )


@query("ablation_shuffle_histograms", "SELECT CAST(6 AS BIGINT) AS columns, CAST(0 AS BIGINT) AS changed_histograms")
def ablation_shuffle_histograms(spark: SparkSession, sf_dir: str) -> DataFrame:
    from rowloom.operators.dictionary import histogram
    from rowloom.sources.synth import correlated_table

    cols = [f"c{i + 1}" for i in range(6)]
    df = correlated_table(spark, 4096)
    a, b = histogram(df, cols), histogram(shuffle_columns(df, cols, "id"), cols)
    changed = a.exceptAll(b).select("col_idx").union(b.exceptAll(a).select("col_idx")).distinct()
    return changed.agg(F.lit(6).cast("long").alias("columns"), F.count("*").alias("changed_histograms"))


def _both_ways(w: str) -> str:
    work = WORKS[w]
    up, down = (S.total_runs(work.sql, cols, "interleave") for cols in (work.cols, work.cols[::-1]))
    return f"SELECT up, down, abs(up - down) / CAST(up AS DOUBLE) < 0.01 AS close FROM (SELECT {up} AS up, {down} AS down)"


@query("interleave_colorder", _both_ways("zipf"))
def interleave_colorder(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Columns in one order or the reverse: the interleave order's runs are close."""
    w = WORKS["zipf"]
    df = w.frame(spark, sf_dir)
    up, down = (R.total_runs(O.order_by(df, "interleave", cols, "given"), w.cols) for cols in (w.cols, w.cols[::-1]))
    return spark.createDataFrame([(up, down, abs(up - down) / up < 0.01)], "up long, down long, close boolean")


_F5 = WORKS["toy8"]


@query(
    "interleave_f5",
    f"SELECT first_at = 0 AS value_first, spread = n AS value_together, {S.total_runs(_F5.sql, _F5.cols, 'interleave')} AS runs, {S.total_runs(_F5.sql, _F5.cols, 'interleave_raw')} AS raw_runs FROM ("
    f"WITH {S.ordered(_F5.sql, _F5.cols, 'interleave')} SELECT min(pos) FILTER (a = 1) AS first_at, max(pos) FILTER (b = 1) - min(pos) FILTER (b = 1) + 1 AS spread, count(*) FILTER (b = 1) AS n FROM o)",
)
def interleave_f5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The most frequent value of column 1 comes first, and that of column 2 stands together across its border."""
    w = WORKS["toy8"]
    df = O.order_by(w.frame(spark, sf_dir), "interleave", w.cols, "given")
    first = df.where("a = 1").agg(F.max("pos")).first()[0] + 1 == df.where("a = 1").count()
    spot = df.where("b = 1").agg(F.min("pos"), F.max("pos"), F.count("*")).first()
    raw = R.total_runs(O.order_by(w.frame(spark, sf_dir), "interleave", w.cols, "given", normalize=False), w.cols)
    row = (bool(first), spot[1] - spot[0] + 1 == spot[2], R.total_runs(df, w.cols), raw)
    return spark.createDataFrame([row], "value_first boolean, value_together boolean, runs long, raw_runs long")


_BANDS = [("zipf", "interleave", 1.154, 0.02), ("zipf", "frequent_component", 1.151, 0.02), ("zipf", "multiple_lists", 1.167, 0.03), ("uniform", "interleave", 1.020, 0.01), ("uniform", "frequent_component", 1.022, 0.01), ("uniform", "multiple_lists", 1.127, 0.01)]


@query("synthetic_bands", " UNION ALL ".join(f"SELECT '{w}' AS workload, '{m}' AS method, true AS within_band" for w, m, _, _ in _BANDS))
def synthetic_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Run reductions on the synthetic tables of 8192 rows against the published figures."""
    rows = []
    for work, method, value, band in _BANDS:
        w = WORKS[work]
        df = w.frame(spark, sf_dir)
        base = R.total_runs(O.order_by(df, "lexicographic", w.cols, "given", keep_codes=True), w.cols)
        new = B.multiple_lists(df, w.cols, column_order_mode="given") if method == "multiple_lists" else O.order_by(df, method, w.cols, "given")
        rows.append((work, method, abs(base / R.total_runs(new, w.cols) - value) <= band))
    return spark.createDataFrame(rows, "workload string, method string, within_band boolean")
