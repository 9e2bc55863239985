"""SQL texts that replay eliminations on Gram matrices: the oracles of the factorizations."""

from __future__ import annotations

from tilerank.functions.keyed import gaussian_sql

EMB = "SELECT vec_id AS row_id, unnest(range(len(embedding))) AS col_id, CAST(unnest(embedding) AS DOUBLE) AS v FROM embeddings"


def unpivot(columns: list[str], table: str, key: str = "row_number() OVER ()") -> str:
    inner = ", ".join(f"CAST({c} AS DOUBLE) AS c{i}" for i, c in enumerate(columns))
    base = f"(SELECT {key} AS row_id, {inner} FROM {table})"
    return " UNION ALL ".join(f"SELECT row_id, {i} AS col_id, c{i} AS v FROM {base}" for i in range(len(columns)))


LINE4 = unpivot(["l_quantity", "l_extendedprice", "l_discount", "l_tax"], "lineitem")
USERHOUR = "SELECT user_id AS row_id, hour(ts) AS col_id, sum(value) AS v FROM events GROUP BY 1, 2"
DESIGN_COLUMNS = [
    "1.0", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_extendedprice * (1 - l_discount)", "l_extendedprice * l_discount",
    *[f"(l_returnflag = '{x}')::INT" for x in "ANR"], *[f"(l_linestatus = '{x}')::INT" for x in "OF"],
]
DESIGN = f"WITH d AS MATERIALIZED ({unpivot(DESIGN_COLUMNS, 'lineitem', 'row_number() OVER ()')}) SELECT row_id, col_id, v / sqrt(sum(v * v) OVER (PARTITION BY col_id)) AS v FROM d"
SUPPMONTH = "SELECT l_suppkey AS row_id, month(l_shipdate) - 1 AS col_id, sum(l_quantity) AS v FROM lineitem WHERE year(l_shipdate) = 1995 GROUP BY 1, 2"
SUPPPART = "SELECT l_suppkey AS row_id, l_partkey % 64 AS col_id, sum(l_quantity) AS v FROM lineitem GROUP BY 1, 2"


def gram(entries: str, name: str = "g0") -> str:
    return f"e AS MATERIALIZED ({entries}), {name} AS MATERIALIZED (SELECT a.col_id AS i, b.col_id AS j, sum(a.v * b.v) AS v FROM e a JOIN e b USING (row_id) GROUP BY 1, 2)"


def eliminated(table: str, pivot: str) -> str:
    """One step: the pivot's row and column go, the rest is the Schur complement."""
    return (
        f"SELECT g.i, g.j, g.v - coalesce(c.v, 0) * coalesce(r.v, 0) / p.d AS v FROM {table} g CROSS JOIN {pivot} p "
        f"LEFT JOIN {table} c ON c.i = g.i AND c.j = p.p LEFT JOIN {table} r ON r.i = p.p AND r.j = g.j WHERE g.i <> p.p AND g.j <> p.p"
    )


def classical(entries: str, k: int) -> str:
    """-> CTEs p0..p(k-1) (p, d): greedy pivots of the Gram matrix; largest diagonal, ties to the smaller column."""
    parts = [gram(entries)]
    for t in range(k):
        parts.append(f"p{t} AS MATERIALIZED (SELECT i AS p, v AS d FROM g{t} WHERE i = j ORDER BY v DESC, i LIMIT 1)")
        if t + 1 < k:
            parts.append(f"g{t + 1} AS MATERIALIZED ({eliminated(f'g{t}', f'p{t}')})")
    return ", ".join(parts)


def pivots(k: int) -> str:
    return " UNION ALL ".join(f"SELECT CAST({t} AS BIGINT) AS k, CAST(p AS BIGINT) AS pivot, round(sqrt(d), 6) + 0.0 AS r_kk FROM p{t}" for t in range(k))


def classical_pivots(entries: str, k: int) -> str:
    return f"WITH {classical(entries, k)} {pivots(k)}"


def fixed_r(entries: str, n: int, scale: str = "1.0") -> str:
    """R of the unpivoted factorization, from elimination in the given order; entries over ``scale``."""
    parts = [gram(entries)]
    out = []
    for t in range(n):
        parts.append(f"p{t} AS MATERIALIZED (SELECT i AS p, v AS d FROM g{t} WHERE i = {t} AND j = {t})")
        out.append(f"SELECT CAST({t} AS BIGINT) AS i, CAST(g.j AS BIGINT) AS j, round(g.v / sqrt(p.d) / {scale}, 6) + 0.0 AS r_ij FROM g{t} g, p{t} p WHERE g.i = {t}")
        if t + 1 < n:
            parts.append(f"g{t + 1} AS MATERIALIZED ({eliminated(f'g{t}', f'p{t}')})")
    return f"WITH {', '.join(parts)} {' UNION ALL '.join(out)}"


FIRST_DRAW = 100_000


def sketched(entries: str, rows: str, k: int, b: int, seed: int, once: bool = False) -> str:
    """CTEs p0..: pivots that keyed sketches choose. The Gram matrix of [A | draws] is eliminated; its (draw, column) part is the
    sketch at every step. ``once``: the first block's draws serve all blocks."""
    draws = b if once else k
    augmented = (
        f"SELECT row_id, col_id, v FROM ({entries}) UNION ALL SELECT row_id, {FIRST_DRAW} + s, {gaussian_sql(seed, 'row_id', 's')} "
        f"FROM ({rows}) CROSS JOIN (SELECT unnest(range({draws})) AS s)"
    )
    parts = [gram(augmented)]
    for t in range(k):
        lo = t // b * b
        if t == lo:
            first = FIRST_DRAW + (0 if once else lo)
            last = first + min(b, draws if once else k - lo)
            parts.append(
                f"y{t} AS MATERIALIZED (SELECT a.j AS i, c.j AS j, sum(a.v * c.v) AS v FROM g{t} a JOIN g{t} c ON a.i = c.i "
                f"WHERE a.i >= {first} AND a.i < {last} AND a.j < {FIRST_DRAW} AND c.j < {FIRST_DRAW} GROUP BY 1, 2)"
            )
        parts.append(f"c{t} AS MATERIALIZED (SELECT i AS p, v AS d FROM y{t} WHERE i = j ORDER BY v DESC, i LIMIT 1)")
        parts.append(f"p{t} AS MATERIALIZED (SELECT c.p, g.v AS d FROM c{t} c JOIN g{t} g ON g.i = c.p AND g.j = c.p)")
        if t + 1 < k:
            parts.append(f"g{t + 1} AS MATERIALIZED ({eliminated(f'g{t}', f'p{t}')})")
            if (t + 1) % b:
                parts.append(f"y{t + 1} AS MATERIALIZED ({eliminated(f'y{t}', f'c{t}')})")
    return ", ".join(parts)


def sketched_pivots(entries: str, rows: str, k: int, b: int, seed: int, once: bool = False) -> str:
    return f"WITH {sketched(entries, rows, k, b, seed, once)} {pivots(k)}"


def rank(entries: str, n: int, bar: float = 1e-12) -> str:
    """Pivots of the Gram matrix above ``bar`` times the first (so the triangle's above its root)."""
    ds = " UNION ALL ".join(f"SELECT d FROM p{t}" for t in range(n))
    return f'WITH {classical(entries, n)} SELECT CAST(count(*) AS BIGINT) AS "rank" FROM ({ds}) WHERE d > {bar} * (SELECT d FROM p0)'


def half_log_volume(method: str, body: str, k: int) -> str:
    """Logarithm of the product of the triangle's first k diagonal entries, from CTEs p0..p(k-1)."""
    total = " + ".join(f"(SELECT ln(d) FROM p{t})" for t in range(k))
    return f"SELECT method, log_volume FROM (WITH {body} SELECT '{method}' AS method, round(0.5 * ({total}), 6) + 0.0 AS log_volume)"


def sketched_rows(entries: str, rows: str, n: int, k: int, b: int, seed: int, moved: bool) -> str:
    """Rows of R of the sketched factorization, for the columns not yet finished: at the columns' own numbers, or (``moved``)
    at their places in pivot order, the chosen first and then the rest by number."""
    parts = [f"SELECT CAST({t} AS BIGINT) AS i, g.j AS c, g.v / sqrt(p.d) AS v FROM g{t} g, p{t} p WHERE g.i = p.p AND g.j < {FIRST_DRAW}" for t in range(k)]
    body = f"WITH {sketched(entries, rows, k, b, seed)}, found AS MATERIALIZED ({' UNION ALL '.join(parts)})"
    if not moved:
        return f"{body} SELECT i, CAST(c AS BIGINT) AS col, round(v, 6) + 0.0 AS r FROM found"
    chosen = " UNION ALL ".join(f"SELECT p AS c, {t} AS pos FROM p{t}" for t in range(k))
    return (
        f"{body}, chosen AS ({chosen}), places AS (SELECT c, pos FROM chosen UNION ALL SELECT c, {k} - 1 + row_number() OVER (ORDER BY c) FROM (SELECT unnest(range({n})) AS c) "
        f"WHERE c NOT IN (SELECT c FROM chosen)) SELECT i, CAST(pos AS BIGINT) AS pos, round(v, 6) + 0.0 AS r FROM found JOIN places USING (c)"
    )


def sketched_residuals(entries: str, rows: str, k: int, b: int, seed: int) -> str:
    """Norm of what is left after each block."""
    parts = [f"SELECT CAST({t} AS BIGINT) AS k, round(sqrt((SELECT sum(v) FROM g{t} WHERE i = j AND i < {FIRST_DRAW})), 6) + 0.0 AS residual" for t in range(b, k + 1, b)]
    return f"WITH {sketched(entries, rows, k + 1, b, seed)} {' UNION ALL '.join(parts)}"
