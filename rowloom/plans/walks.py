"""Tours and improvements of one small table, each with a recursive query that walks along by itself."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowloom.operators import blocks as B
from rowloom.operators import order as O
from rowloom.plans import oracle as S
from rowloom.plans.registry import query
from rowloom.sources.io import read_table

COLS = ["third", "n_regionkey", "quarter"]
_SOURCE = "SELECT n_nationkey % 3 AS third, n_regionkey, n_nationkey // 4 AS quarter FROM nation"


def table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """25 rows of three columns with 3, 5 and 7 values."""
    return read_table(spark, sf_dir, "nation").select(
        (F.col("n_nationkey") % 3).alias("third"), "n_regionkey", F.floor(F.col("n_nationkey") / 4).alias("quarter")
    )


_D = " + ".join(f"CASE WHEN a.k{i} <> b.k{i} THEN 1 ELSE 0 END" for i in range(len(COLS)))
#: CTEs: the coded rows `o`, all distances `ds`, their count `nn`; `far` and a row `nn` far from all for open tours.
_BASE = (
    f"{S.ordered(_SOURCE, COLS, 'codes')}, ds AS (SELECT a.pos AS a, b.pos AS b, {_D} AS d FROM o a, o b), "
    "cst AS (SELECT count(*) AS nn, (SELECT max(d) + 1 FROM ds) AS far FROM o), "
    "dsf AS (SELECT * FROM ds UNION ALL SELECT nn, pos, far FROM o, cst UNION ALL SELECT pos, nn, far FROM o, cst)"
)


def _rows(path: str) -> str:
    """The rows along a list of positions."""
    return f"SELECT t.i - 1 AS pos, {', '.join('o.' + c for c in COLS)} FROM (SELECT unnest({path}) AS at, unnest(range(1, len({path}) + 1)) AS i FROM fin) t JOIN o ON o.pos = t.at"


def _insertion_sql(pick: str) -> str:
    """State: the path, and its rows in the order of insertion after the artificial one, which decides ties of places."""
    places = (
        "SELECT x.r, g.i, g.a, (p.d + q.d - s.d) AS cost FROM {rows} x, "
        "(SELECT i, keys[i] AS a, CASE WHEN keys[i] = nn THEN path[1] ELSE coalesce(path[list_position(path, keys[i]) + 1], nn) END AS b "
        "FROM (SELECT unnest(range(1, len(w.keys) + 1)) AS i, w.keys AS keys, w.path AS path, c.nn AS nn)) g "
        "JOIN dsf p ON p.a = g.a AND p.b = x.r JOIN dsf q ON q.a = x.r AND q.b = g.b JOIN dsf s ON s.a = g.a AND s.b = g.b"
    )
    free = "(SELECT pos AS r FROM o WHERE NOT list_contains(w.path, pos))"
    if pick == "cheapest":
        chosen = f"SELECT arg_min({{'r': r, 'a': a}}, cost * 10000 + r * 100 + i) AS x FROM ({places.format(rows=free)})"
    else:
        worst = "arg_min(r, closest * 100 + r)" if pick == "nearest" else "arg_min(r, -closest * 100 + r)"
        one = f"(SELECT {worst} AS r FROM (SELECT f.r, min(ds.d) AS closest FROM {free} f JOIN ds ON ds.a = f.r WHERE list_contains(w.path, ds.b) GROUP BY f.r))"
        chosen = f"SELECT arg_min({{'r': r, 'a': a}}, cost * 100 + i) AS x FROM ({places.format(rows=one)})"
    return (
        f"WITH RECURSIVE {_BASE}, w AS (SELECT 0 AS step, [CAST(0 AS BIGINT)] AS path, [nn, CAST(0 AS BIGINT)] AS keys FROM cst UNION ALL "
        "SELECT w.step + 1, CASE WHEN z.x.a = c.nn THEN list_prepend(z.x.r, w.path) ELSE "
        "list_concat(list_append(w.path[:list_position(w.path, z.x.a)], z.x.r), w.path[list_position(w.path, z.x.a) + 1:]) END, list_append(w.keys, z.x.r) "
        f"FROM w, cst c, LATERAL ({chosen}) z WHERE w.step < c.nn - 1 AND z.x IS NOT NULL), fin AS (SELECT path FROM w ORDER BY step DESC LIMIT 1) {_rows('path')}"
    )


def _links_sql(kind: str) -> str:
    """Links in rising order (of cost, or of falling saving) taken where degrees and cycles allow; then the path along them."""
    if kind == "multiple_fragment":
        ranked = "SELECT a, b, row_number() OVER (ORDER BY d, a, b) AS rn FROM ds WHERE a < b"
        whole, first = "nodes", "0"
    else:
        ranked = (
            "SELECT x.a, x.b, row_number() OVER (ORDER BY x.d - p.d - q.d, x.a, x.b) AS rn FROM ds x JOIN ds p ON p.a = x.a AND p.b = 0 "
            "JOIN ds q ON q.a = 0 AND q.b = x.b WHERE x.a < x.b AND x.a > 0"
        )
        whole, first = "list_prepend(CAST(0 AS BIGINT), nodes)", "1"
    return (
        f"WITH RECURSIVE {_BASE}, pr AS ({ranked}), w AS (SELECT CAST(0 AS BIGINT) AS rn, (SELECT list(CAST(0 AS BIGINT)) FROM o) AS deg, (SELECT list(pos ORDER BY pos) FROM o) AS comp, "
        "[]::STRUCT(a BIGINT, b BIGINT)[] AS links UNION ALL "
        "SELECT pr.rn, CASE WHEN ok THEN list_transform(w.deg, lambda v, i: v + CASE WHEN i = pr.a + 1 OR i = pr.b + 1 THEN 1 ELSE 0 END) ELSE w.deg END, "
        "CASE WHEN ok THEN list_transform(w.comp, lambda v: CASE WHEN v = w.comp[pr.a + 1] THEN w.comp[pr.b + 1] ELSE v END) ELSE w.comp END, "
        "CASE WHEN ok THEN list_append(w.links, {'a': pr.a, 'b': pr.b}) ELSE w.links END "
        "FROM w JOIN pr ON pr.rn = w.rn + 1, LATERAL (SELECT w.deg[pr.a + 1] < 2 AND w.deg[pr.b + 1] < 2 AND w.comp[pr.a + 1] <> w.comp[pr.b + 1] AS ok) t), "
        "done AS (SELECT * FROM w ORDER BY rn DESC LIMIT 1), lk AS (SELECT l.a AS a, l.b AS b FROM (SELECT unnest(links) AS l FROM done)), "
        "nb AS (SELECT a, b FROM lk UNION ALL SELECT b, a FROM lk), "
        f"walk AS (SELECT CAST(1 AS BIGINT) AS n, [min(a)] AS nodes FROM (SELECT a FROM nb WHERE a >= {first} GROUP BY a HAVING count(*) = 1) UNION ALL "
        "SELECT walk.n + 1, list_append(walk.nodes, nb.b) FROM walk JOIN nb ON nb.a = walk.nodes[-1] AND NOT list_contains(walk.nodes, nb.b)), "
        f"fin AS (SELECT {whole} AS path FROM walk ORDER BY n DESC LIMIT 1) {_rows('path')}"
    )


def _step(a: str, b: str) -> str:
    return f"(SELECT d FROM ds WHERE a = {a} AND b = {b})"


_SWAP_SQL = (
    f"WITH RECURSIVE {_BASE}, w AS (SELECT 0 AS step, 1 AS i, false AS changed, (SELECT list(pos ORDER BY pos) FROM o) AS path UNION ALL "
    "SELECT step + 1, CASE WHEN i = nn - 1 THEN 1 ELSE i + 1 END, CASE WHEN i = nn - 1 THEN false ELSE changed OR gain > 0 END, "
    "CASE WHEN gain > 0 THEN list_concat(list_append(list_append(path[:i - 1], path[i + 1]), path[i]), path[i + 2:]) ELSE path END "
    "FROM (SELECT w.*, c.nn, coalesce(" + _step("w.path[w.i - 1]", "w.path[w.i]") + " - " + _step("w.path[w.i - 1]", "w.path[w.i + 1]") + ", 0) + "
    "coalesce(" + _step("w.path[w.i + 1]", "w.path[w.i + 2]") + " - " + _step("w.path[w.i]", "w.path[w.i + 2]") + ", 0) AS gain FROM w, cst c) "
    # a pass that changes nothing is the last one
    "WHERE NOT (i = nn - 1 AND NOT (changed OR gain > 0))), "
    f"fin AS (SELECT path FROM w ORDER BY step DESC LIMIT 1) {_rows('path')}"
)

_REINSERT_SQL = (
    f"WITH RECURSIVE {_BASE}, w AS (SELECT CAST(0 AS BIGINT) AS r, (SELECT list(pos ORDER BY pos) FROM o) AS path UNION ALL "
    "SELECT r + 1, list_concat(list_append(rest[:k - 1], r), rest[k:]) FROM (SELECT w.r, z.rest, z.k FROM w, cst c, LATERAL ("
    "SELECT any_value(rest) AS rest, CASE WHEN min(cost) = min(CASE WHEN k = own THEN cost END) THEN any_value(own) ELSE arg_min(k, cost * 100 + k) END AS k FROM ("
    "SELECT rest, own, k, CASE WHEN k = 1 THEN q.d WHEN k = c.nn THEN p.d ELSE p.d + q.d - s.d END AS cost FROM ("
    "SELECT list_filter(w.path, lambda v: v <> w.r) AS rest, list_position(w.path, w.r) AS own, unnest(range(1, c.nn + 1)) AS k) g "
    "LEFT JOIN ds p ON p.a = g.rest[k - 1] AND p.b = w.r AND k > 1 LEFT JOIN ds q ON q.a = w.r AND q.b = g.rest[k] LEFT JOIN ds s ON s.a = g.rest[k - 1] AND s.b = g.rest[k] AND k > 1"
    ")) z WHERE w.r < c.nn)), "
    f"fin AS (SELECT path FROM w ORDER BY r DESC LIMIT 1) {_rows('path')}"
)

#: Query name: SQL, and heuristic with options or improvement.
WALKS: dict[str, tuple[str, str, dict]] = {
    "tour_insertion_nearest": (_insertion_sql("nearest"), "insertion", {"pick": "nearest"}),
    "tour_insertion_farthest": (_insertion_sql("farthest"), "insertion", {"pick": "farthest"}),
    "tour_insertion_cheapest": (_insertion_sql("cheapest"), "insertion", {"pick": "cheapest"}),
    "tour_multiple_fragment": (_links_sql("multiple_fragment"), "multiple_fragment", {}),
    "tour_savings": (_links_sql("savings"), "savings", {}),
    "improve_adjacent_swap": (_SWAP_SQL, "adjacent_swap", {}),
    "improve_reinsertion": (_REINSERT_SQL, "reinsertion", {}),
}


def _register(name: str, sql: str, method: str, opt: dict) -> None:
    @query(name, sql)
    def plan(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = table(spark, sf_dir)
        if name.startswith("improve"):
            base = O.order_by(df, "lexicographic", COLS, "given", keep_codes=True)
            return B.run_blocks(base, [B.kernel(method)], [c + "__code" for c in COLS], 64).select("pos", *COLS)
        return B.tour(df, method, COLS, 64, column_order_mode="given", **opt).select("pos", *COLS)


for _name, _spec in WALKS.items():
    _register(_name, *_spec)
