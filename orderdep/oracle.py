"""DuckDB SQL for the results, written from the definitions and apart from the search and the Spark checks."""

from __future__ import annotations

from itertools import combinations

CALENDAR = """SELECT CAST(row_number() OVER (ORDER BY d_date) - 1 AS BIGINT) AS d_date_sk, d_date, CAST(year(d_date) AS INT) AS d_year, CAST(quarter(d_date) AS INT) AS d_quarter,
 CAST(month(d_date) AS INT) AS d_month, CAST(ceil(dayofyear(d_date) / 7.0) AS INT) AS d_week FROM (SELECT DISTINCT CAST(o_orderdate AS DATE) AS d_date FROM orders)"""

ORDERS_CAL = """SELECT CAST(o_orderdate AS DATE) AS d_date, year(o_orderdate) AS d_year, quarter(o_orderdate) AS d_quarter, month(o_orderdate) AS d_month,
 year(o_orderdate) * 100 + month(o_orderdate) AS d_ym, o_orderstatus, o_orderpriority FROM orders"""

CUSTOMER_GEO = "SELECT c_custkey, c_nationkey, n_name, n_regionkey, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def ranked(relation: str, columns: list[str]) -> str:
    """Different rows as dense ranks c0, c1, ..., null first."""
    codes = ", ".join(f'dense_rank() OVER (ORDER BY "{c}" NULLS FIRST) AS c{k}' for k, c in enumerate(columns))
    return f"SELECT DISTINCT {codes} FROM ({relation})"


def _ctx(mask: int, m: int) -> list[str]:
    return [f"c{k}" for k in range(m) if mask >> k & 1]


def constancy_bad(mask: int, a: int, m: int, r: str = "r") -> str:
    ctx = _ctx(mask, m)
    return f"SELECT 1 FROM {r} " + (f"GROUP BY {', '.join(ctx)} " if ctx else "") + f"HAVING min(c{a}) <> max(c{a})"


def compat_bad(mask: int, a: int, b: int, m: int, r: str = "r") -> str:
    ctx = _ctx(mask, m)
    part = f"PARTITION BY {', '.join(ctx)} " if ctx else ""
    groups = f"SELECT {', '.join([*ctx, f'c{a}'])}, min(c{b}) AS lo, max(c{b}) AS hi FROM {r} GROUP BY {', '.join([*ctx, f'c{a}'])}"
    return f"SELECT 1 FROM (SELECT lo, max(hi) OVER ({part}ORDER BY c{a} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM ({groups})) WHERE top > lo"


def _names(mask: int, columns: list[str]) -> str:
    return ",".join(c for k, c in enumerate(columns) if mask >> k & 1)


def verdicts(relation: str, columns: list[str], pairs: bool = True) -> str:
    """WITH clause: r, fd(ctx, a, ok) and oc(ctx, a, b, ok) for every non-trivial candidate."""
    m = len(columns)
    fd = [f"SELECT {x} AS ctx, {a} AS a, count(*) = 0 AS ok FROM ({constancy_bad(x, a, m)})" for x in range(1 << m) for a in range(m) if not x >> a & 1]
    oc = [f"SELECT {x} AS ctx, {a} AS a, {b} AS b, count(*) = 0 AS ok FROM ({compat_bad(x, a, b, m)})" for x in range(1 << m) for a, b in combinations(range(m), 2) if not x >> a & 1 and not x >> b & 1]
    out = f"WITH r AS MATERIALIZED ({ranked(relation, columns)}), fd AS MATERIALIZED ({' UNION ALL '.join(fd)})"
    return out + (f", oc AS MATERIALIZED ({' UNION ALL '.join(oc)})" if pairs and oc else ", oc AS (SELECT 0 AS ctx, 0 AS a, 0 AS b, false AS ok WHERE false)")


def discovery(relation: str, columns: list[str], pairs: bool = True) -> str:
    """The minimal dependencies by brute force, as rows of OD_SCHEMA."""
    m = len(columns)
    names = ", ".join(f"({x}, '{_names(x, columns)}', {bin(x).count('1')})" for x in range(1 << m))
    cols = ", ".join(f"({k}, '{c}')" for k, c in enumerate(columns))
    return f"""{verdicts(relation, columns, pairs)}, sets(ctx, context, n) AS (VALUES {names}), cols(k, name) AS (VALUES {cols})
SELECT 'constancy' AS kind, s.context, CAST(NULL AS VARCHAR) AS "left", c.name AS "right", CAST(s.n + 1 AS INT) AS level, CAST(s.n AS INT) AS context_size
FROM fd f JOIN sets s ON f.ctx = s.ctx JOIN cols c ON f.a = c.k
WHERE f.ok AND NOT EXISTS (SELECT 1 FROM fd g WHERE g.ok AND g.a = f.a AND g.ctx <> f.ctx AND g.ctx & f.ctx = g.ctx)
UNION ALL
SELECT 'compat', s.context, c.name, d.name, CAST(s.n + 2 AS INT), CAST(s.n AS INT)
FROM oc f JOIN sets s ON f.ctx = s.ctx JOIN cols c ON f.a = c.k JOIN cols d ON f.b = d.k
WHERE f.ok AND NOT EXISTS (SELECT 1 FROM oc g WHERE g.ok AND g.a = f.a AND g.b = f.b AND g.ctx <> f.ctx AND g.ctx & f.ctx = g.ctx)
AND NOT EXISTS (SELECT 1 FROM fd g WHERE g.ok AND g.ctx = f.ctx AND g.a IN (f.a, f.b))"""


def valid_counts(relation: str, columns: list[str]) -> str:
    return f"{verdicts(relation, columns)} SELECT (SELECT count(*) FROM fd WHERE ok) AS n_fd, (SELECT count(*) FROM oc WHERE ok) AS n_ocd"


def checks(relation: str, columns: list[str], tasks: list[tuple[str, int, int, int | None]]) -> str:
    """Rows (label, holds); a task is (label, context mask, a, b or None)."""
    m = len(columns)
    rows = [f"SELECT '{label}' AS od, count(*) = 0 AS holds FROM ({constancy_bad(x, a, m) if b is None else compat_bad(x, a, b, m)})" for label, x, a, b in tasks]
    return f"WITH r AS MATERIALIZED ({ranked(relation, columns)}) {' UNION ALL '.join(rows)}"


def list_checks(relation: str, tasks: list[tuple[list[str], list[str]]]) -> str:
    """Rows (lhs, rhs, holds, n_split_groups, n_swap_groups) straight from the definition of list dependencies."""
    out = []
    for x, y in tasks:
        lx, ly = ", ".join(f"{c} NULLS FIRST" for c in x), ", ".join(f"{c} NULLS FIRST" for c in y)
        g = f"SELECT rx, min(ry) AS lo, max(ry) AS hi FROM (SELECT dense_rank() OVER (ORDER BY {lx}) AS rx, dense_rank() OVER (ORDER BY {ly}) AS ry FROM ({relation})) GROUP BY rx"
        w = f"SELECT lo, hi, max(hi) OVER (ORDER BY rx ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM ({g})"
        out.append(f"SELECT '{','.join(x)}' AS lhs, '{','.join(y)}' AS rhs, count(*) FILTER (lo <> hi OR top > lo) = 0 AS holds, count(*) FILTER (lo <> hi) AS n_split_groups, count(*) FILTER (top > lo) AS n_swap_groups FROM ({w})")
    return " UNION ALL ".join(out)
