"""SQL text (DuckDB) of dictionaries, orders and measures, written apart from the Spark plans."""

from __future__ import annotations


def coded(source: str, cols: list[str]) -> str:
    """CTEs `base` and `coded`: the rows of a SELECT, with frequency codes k0.. and frequencies f0.."""
    parts = [f"base AS ({source})"]
    for i, c in enumerate(cols):
        parts.append(
            f"d{i} AS (SELECT v, f, row_number() OVER (ORDER BY f DESC, v ASC NULLS FIRST) - 1 AS k "
            f"FROM (SELECT {c} AS v, count(*) AS f FROM base GROUP BY 1))"
        )
    joins = " ".join(f"JOIN d{i} ON b.{c} IS NOT DISTINCT FROM d{i}.v" for i, c in enumerate(cols))
    picks = ", ".join(f"d{i}.k AS k{i}, d{i}.f AS f{i}" for i in range(len(cols)))
    return ", ".join([*parts, f"coded AS (SELECT b.*, {picks} FROM base b {joins})"])


def keys(order: str, cols: list[str], bits: int = 16) -> str:
    """ORDER BY text of an order over `coded`."""
    c = len(cols)
    if order == "lexicographic":
        return ", ".join(f"{x} ASC NULLS FIRST" for x in cols)
    if order == "codes":
        return ", ".join(f"k{i}" for i in range(c))
    if order == "alternating":
        return ", ".join(f"{x} ASC NULLS FIRST" if i % 2 == 0 else f"{x} DESC NULLS LAST" for i, x in enumerate(cols))
    if order in ("interleave", "interleave_raw"):
        values = [f"k{i}" if order == "interleave" else cols[i] for i in range(c)]
        pairs = "list_sort([" + ", ".join(f"{{'v': CAST({v} AS BIGINT), 'k': {i}}}" for i, v in enumerate(values)) + "])"
        return ", ".join(f"({pairs})[{i + 1}] {'ASC' if i % 2 == 0 else 'DESC'}" for i in range(c))
    if order in ("frequent_component", "frequent_component_fvc"):
        fields = "{{'f': f{i}, 'k': {i}, 'v': k{i}}}" if order == "frequent_component" else "{{'f': f{i}, 'v': k{i}, 'k': {i}}}"
        return "list_sort([" + ", ".join(fields.format(i=i) for i in range(c)) + "], 'DESC') ASC"
    if order == "reflected_gray":
        terms = []
        for i in range(c):
            before = " + ".join(["0", *(f"k{j}" for j in range(i))])
            terms.append(f"CASE WHEN ({before}) % 2 = 0 THEN k{i} ELSE -k{i} END")
        return ", ".join(terms)
    if order == "zorder_gray":
        seen, ranks = [], []
        for b in range(bits - 1, -1, -1):
            for i in range(c):
                seen.append(f"((k{i} >> {b}) & 1)")
                ranks.append(f"({' + '.join(seen)}) % 2")
        return "[" + ", ".join(ranks) + "]"
    raise ValueError(order)


def ordered(source: str, cols: list[str], order: str, bits: int = 16) -> str:
    """CTEs up to `o`: the ordered rows with `pos`."""
    return f"{coded(source, cols)}, o AS (SELECT *, row_number() OVER (ORDER BY {keys(order, cols, bits)}) - 1 AS pos FROM coded)"


def order_rows(source: str, cols: list[str], order: str, bits: int = 16) -> str:
    return f"WITH {ordered(source, cols, order, bits)} SELECT pos, {', '.join(cols)} FROM o"


def flags(cols: list[str], frm: str = "o") -> str:
    """CTE `fl`: n0.. are 1 where a run of column i starts."""
    terms = ", ".join(
        f"CASE WHEN pos = 0 OR {c} IS DISTINCT FROM lag({c}) OVER (ORDER BY pos) THEN 1 ELSE 0 END AS n{i}" for i, c in enumerate(cols)
    )
    return f"fl AS (SELECT *, {terms} FROM {frm})"


def run_rows(source: str, cols: list[str], order: str, method: str) -> str:
    """SELECT text of (method, col, runs)."""
    union = " UNION ALL ".join(f"SELECT '{method}' AS method, '{c}' AS col, CAST(sum(n{i}) AS BIGINT) AS runs FROM fl" for i, c in enumerate(cols))
    return f"SELECT * FROM (WITH {ordered(source, cols, order)}, {flags(cols)} {union})"


def total_runs(source: str, cols: list[str], order: str) -> str:
    """A scalar subquery."""
    terms = " + ".join(f"sum(n{i})" for i in range(len(cols)))
    return f"(WITH {ordered(source, cols, order)}, {flags(cols)} SELECT CAST({terms} AS BIGINT) FROM fl)"


def bits(x: str) -> str:
    """ceil(log2 x) by integers."""
    return f"CASE WHEN {x} <= 1 THEN 0 ELSE length(bin(CAST({x} - 1 AS BIGINT))) END"


def long_codes(cols: list[str], frm: str = "o") -> str:
    return " UNION ALL ".join(f"SELECT {i} AS i, pos, k{i} AS code FROM {frm}" for i in range(len(cols)))


def column_facts(cols: list[str]) -> str:
    """CTE `facts`: i, col, card, n."""
    rows = " UNION ALL ".join(f"SELECT {i} AS i, '{c}' AS col, (SELECT count(*) FROM d{i}) AS card, (SELECT count(*) FROM base) AS n" for i, c in enumerate(cols))
    return f"facts AS ({rows})"


def sizes(source: str, cols: list[str], order: str, codec: str, method: str, p: int = 128) -> str:
    """SELECT text of (method, codec, col, bits), columns named as code columns."""
    # a coded table is sorted by its codes
    start = f"WITH {ordered(source, cols, 'codes' if order == 'lexicographic' else order)}, {column_facts(cols)}, lc AS ({long_codes(cols)})"
    name = f"'{method}' AS method, '{codec}' AS codec, f.col || '__code' AS col"
    w = bits("f.card")
    if codec == "dictionary":
        body = f"SELECT {name}, CAST(f.n * ({w}) AS BIGINT) AS bits FROM facts f"
    elif codec in ("indirect", "sparse"):
        own = bits("b.own")
        cost = f"b.own * ({w}) + b.b * ({own})" if codec == "indirect" else f"(b.b - b.top + 1) * ({w}) + b.b"
        start += (
            f", pc AS (SELECT i, pos // {p} AS cb, code, count(*) AS k FROM lc GROUP BY ALL), "
            "b AS (SELECT i, cb, count(*) AS own, max(k) AS top, CAST(sum(k) AS BIGINT) AS b FROM pc GROUP BY i, cb)"
        )
        body = f"SELECT {name}, CAST(sum({cost}) AS BIGINT) AS bits FROM b JOIN facts f USING (i) GROUP BY f.col"
    elif codec == "prefix":
        start += (
            f", fv AS (SELECT i, pos // {p} AS cb, pos % {p} AS place, code, first_value(code) OVER (PARTITION BY i, pos // {p} ORDER BY pos) AS head FROM lc), "
            f"b AS (SELECT i, cb, count(*) AS b, coalesce(min(CASE WHEN code <> head THEN place END), count(*)) AS l FROM fv GROUP BY i, cb)"
        )
        body = f"SELECT {name}, CAST(sum({(p - 1).bit_length()} + ({w}) + (b.b - b.l) * ({w})) AS BIGINT) AS bits FROM b JOIN facts f USING (i) GROUP BY f.col"
    elif codec in ("rle", "rle_pair", "rle_nested"):
        start += ", ch AS (SELECT i, pos, code <> lag(code) OVER (PARTITION BY i ORDER BY pos) AS differs FROM lc)"
        if codec == "rle_nested":
            start += ", runs AS (SELECT a.i, count(*) AS r FROM (SELECT i FROM facts) a JOIN (SELECT pos, min(i) AS lead FROM (SELECT i, pos FROM ch WHERE differs OR pos = 0) GROUP BY pos) s ON s.lead <= a.i GROUP BY a.i)"
        else:
            start += ", runs AS (SELECT i, count(*) AS r FROM ch WHERE differs OR pos = 0 GROUP BY i)"
        body = f"SELECT {name}, CAST(r.r * (({w}) + {1 if codec == 'rle_pair' else 2} * ({bits('f.n')})) AS BIGINT) AS bits FROM runs r JOIN facts f USING (i)"
    elif codec == "delta":
        length = lambda x: f"CASE WHEN {x} <= 0 THEN 0 ELSE length(bin(CAST({x} AS BIGINT))) END"
        start += ", g AS (SELECT i, pos, code, abs(code - lag(code) OVER (PARTITION BY i ORDER BY pos)) AS gap FROM lc)"
        each = f"CASE WHEN pos = 0 THEN {length('code')} ELSE {length('gap')} + CASE WHEN gap > 0 THEN 1 ELSE 0 END END"
        body = f"SELECT {name}, CAST(sum({each}) AS BIGINT) AS bits FROM g JOIN facts f USING (i) GROUP BY f.col"
    elif codec == "entropy":
        start += ", h AS (SELECT i, code, count(*) AS k FROM lc GROUP BY ALL)"
        body = f"SELECT {name}, CAST(ceil(sum(-h.k * log2(h.k / CAST(f.n AS DOUBLE)))) AS BIGINT) AS bits FROM h JOIN facts f USING (i) GROUP BY f.col"
    else:
        raise ValueError(codec)
    return f"SELECT * FROM ({start} {body})"


def prefix_sum(cols: list[str], frm: str) -> str:
    """Scalar text: the distinct tuples of all prefixes, summed."""
    return " + ".join(f"(SELECT count(*) FROM (SELECT DISTINCT {', '.join(cols[: i + 1])} FROM {frm}))" for i in range(len(cols)))
