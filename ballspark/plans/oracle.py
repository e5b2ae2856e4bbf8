"""SQL for DuckDB that the queries are held against: brute force over the same views, query sets and formulas."""

from __future__ import annotations

from ballspark.sources.queries import FIRST, MODULUS, WRAP, quadratic
from ballspark.sources.views import VIEWS, View


def number(v: float) -> str:
    return f"CAST({v!r} AS DOUBLE)"


def points(name: str, as_: str = "pts") -> str:
    """CTEs that end in ``as_`` (pid, x0, ...), scaled as the view is."""
    v = VIEWS[name]
    raw = ", ".join(f"{e} AS c{j}" for j, e in enumerate(v.oracle))
    good = " AND ".join(f"c{j} IS NOT NULL AND NOT isnan(c{j})" for j in range(v.dim))
    ctes = [f"{as_}_raw AS (SELECT CAST({v.pid} AS BIGINT) AS pid, {raw} FROM {v.table} WHERE {v.where})", f"{as_}_good AS (SELECT * FROM {as_}_raw WHERE {good})"]
    if not v.unit:
        return ", ".join([*ctes, f"{as_} AS (SELECT pid, {', '.join(f'c{j} AS x{j}' for j in range(v.dim))} FROM {as_}_good)"])
    bounds = ", ".join(f"min(c{j}) AS lo{j}, max(c{j}) - min(c{j}) AS w{j}" for j in range(v.dim))
    scaled = ", ".join(f"(c{j} - lo{j}) / CASE WHEN w{j} = 0 THEN 1 ELSE w{j} END AS x{j}" for j in range(v.dim))
    return ", ".join([*ctes, f"{as_}_box AS (SELECT {bounds} FROM {as_}_good)", f"{as_} AS (SELECT pid, {scaled} FROM {as_}_good, {as_}_box)"])


def uniform(dim: int, m: int, low: float = 0.0, high: float = 1.0) -> str:
    """The CTE qs (qid, q0, ...)."""
    cols = []
    for j in range(dim):
        a, b, c = quadratic(j)
        s = f"(i + {FIRST})"
        cols.append(f"{number(low)} + {number(high - low)} * (CAST(({a} * {s} * {s} + {b} * {s} + {c}) % {MODULUS} AS DOUBLE) / {number(float(MODULUS))}) AS q{j}")
    return f"qs AS (SELECT i AS qid, {', '.join(cols)} FROM range({m}) t(i))"


def uniform_of(table: str, id_col: str, dim: int) -> str:
    """The CTE qs (qid, q0, ...) of a point for each row of a table."""
    cols = []
    for j in range(dim):
        a, b, c = quadratic(j)
        cols.append(f"CAST(({a} * s * s + {b} * s + {c}) % {MODULUS} AS DOUBLE) / {number(float(MODULUS))} AS q{j}")
    return f"qs AS (SELECT qid, {', '.join(cols)} FROM (SELECT CAST({id_col} AS BIGINT) AS qid, CAST({id_col} AS BIGINT) % {WRAP} + {FIRST} AS s FROM {table}))"


def sampled(dim: int, m: int, of: str = "pts") -> str:
    """The CTE qs of the m points of the smallest hash."""
    return f"qs AS (SELECT pid AS qid, {', '.join(f'x{j} AS q{j}' for j in range(dim))} FROM {of} ORDER BY ((pid % 1000003) * 48271) % {MODULUS}, pid LIMIT {m})"


def d2(dim: int) -> str:
    return " + ".join(f"(x{j} - q{j}) * (x{j} - q{j})" for j in range(dim))


def pairs(dim: int, r: float | None = None, of: str = "pts") -> str:
    limit = f" WHERE d2 <= {number(r)} * {number(r)}" if r is not None else ""
    return f"pairs AS (SELECT * FROM (SELECT *, {d2(dim)} AS d2 FROM qs, {of}){limit})"


RANKED = "ranked AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d2, pid) AS rank FROM pairs)"


def in_range(name: str, queries: str, r: float) -> str:
    return f"WITH {points(name)}, {queries}, {pairs(VIEWS[name].dim, r)} SELECT qid, pid, round(sqrt(d2), 6) AS dist FROM pairs"


def k_nearest(name: str, queries: str, k: int, r: float | None = None, select: str = "qid, CAST(rank AS INTEGER) AS rank, pid, round(sqrt(d2), 6) AS dist", joins: str = "") -> str:
    return f"WITH {points(name)}, {queries}, {pairs(VIEWS[name].dim, r)}, {RANKED} SELECT {select} FROM ranked {joins} WHERE rank <= {k}"


# --- splits ---------------------------------------------------------------------------------------


def axis(xx: str, xy: str, yy: str) -> tuple[str, str]:
    """First component in two dimensions from second moments, the larger component positive."""
    t = f"(0.5 * atan2(2 * ({xy}), ({xx}) - ({yy})))"
    lead = f"(CASE WHEN abs(cos({t})) >= abs(sin({t})) * (1 - 1e-9) THEN cos({t}) ELSE sin({t}) END)"
    sign = f"(CASE WHEN {lead} < 0 THEN -1 ELSE 1 END)"
    return f"cos({t}) * {sign}", f"sin({t}) * {sign}"


def pab_step(at: str, gram: bool = False, sections: int = 64, alpha: float = 0.5, offset: str = "centred", tag: str = "") -> str:
    """CTEs from ``at`` (code, pid, x0, x1) to cut{tag}, one row a node, and side{tag}, one row a point with its child's code."""
    c = ("x0 * x0", "x0 * x1", "x1 * x1") if gram else ("(x0 - m0) * (x0 - m0)", "(x0 - m0) * (x1 - m1)", "(x1 - m1) * (x1 - m1)")
    w0, w1 = axis("xx", "xy", "yy")
    f2 = "abs(2 * share - 1)" if offset == "centred" else "share"
    n2 = 2 * sections
    return ", ".join(
        [
            f"mean{tag} AS (SELECT code, count(*) AS n, avg(x0) AS m0, avg(x1) AS m1 FROM {at} GROUP BY code)",
            f"mom{tag} AS (SELECT code, any_value(n) AS n, sum({c[0]}) AS xx, sum({c[1]}) AS xy, sum({c[2]}) AS yy FROM {at} JOIN mean{tag} USING (code) GROUP BY code)",
            f"axis{tag} AS (SELECT code, n, {w0} AS w0, {w1} AS w1 FROM mom{tag})",
            f"place{tag} AS (SELECT code, pid, x0, x1, n, x0 * w0 + x1 * w1 AS t FROM {at} JOIN axis{tag} USING (code))",
            f"ext{tag} AS (SELECT code, min(t) AS t_min, max(t) AS t_max, count(*) AS n FROM place{tag} GROUP BY code)",
            f"half{tag} AS (SELECT code, pid, x0, x1, t, least({n2 - 1}, CAST(floor((t - t_min) / (t_max - t_min) * {n2}) AS INTEGER)) AS half FROM place{tag} JOIN ext{tag} USING (code) WHERE t_max > t_min)",
            f"grid{tag} AS (SELECT code, t_min, t_max, n, CAST(s AS INTEGER) AS section, (s + 0.5e0) / {sections} AS share FROM ext{tag}, range({sections}) r(s) WHERE t_max > t_min)",
            f"hist{tag} AS (SELECT code, half, count(*) AS c FROM half{tag} GROUP BY code, half)",
            f"scan{tag} AS (SELECT code, section, t_min, t_max, n, share, t_min + (t_max - t_min) * share AS t_c, CAST(coalesce((SELECT sum(c) FROM hist{tag} h WHERE h.code = g.code AND h.half <= 2 * g.section), 0) AS BIGINT) AS n_below FROM grid{tag} g)",
            f"goal{tag} AS (SELECT *, abs(n - 2 * n_below) / CAST(n AS DOUBLE) AS f1, {f2} AS f2, abs(n - 2 * n_below) / CAST(n AS DOUBLE) + {number(alpha)} * {f2} AS f FROM scan{tag})",
            f"cut{tag} AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY code ORDER BY round(f, 12), section) AS best FROM goal{tag}) WHERE best = 1)",
            f"side{tag} AS (SELECT h.code * 2 + CASE WHEN half > 2 * section THEN 1 ELSE 0 END AS code, pid, x0, x1 FROM half{tag} h JOIN cut{tag} USING (code))",
        ]
    )


def fpb_step(at: str, tag: str = "") -> str:
    d = "(x0 - {0}0) * (x0 - {0}0) + (x1 - {0}1) * (x1 - {0}1)"
    return ", ".join(
        [
            f"mean{tag} AS (SELECT code, count(*) AS n, avg(x0) AS m0, avg(x1) AS m1 FROM {at} GROUP BY code)",
            f"one{tag} AS (SELECT code, x0 AS a0, x1 AS a1 FROM (SELECT code, x0, x1, row_number() OVER (PARTITION BY code ORDER BY {d.format('m')} DESC, pid) AS i FROM {at} JOIN mean{tag} USING (code)) WHERE i = 1)",
            f"two{tag} AS (SELECT code, a0, a1, x0 AS b0, x1 AS b1 FROM (SELECT code, a0, a1, x0, x1, row_number() OVER (PARTITION BY code ORDER BY {d.format('a')} DESC, pid) AS i FROM {at} JOIN one{tag} USING (code)) WHERE i = 1)",
            f"side{tag} AS (SELECT code * 2 + CASE WHEN {d.format('b')} < {d.format('a')} THEN 1 ELSE 0 END AS code, pid, x0, x1 FROM {at} JOIN two{tag} USING (code))",
        ]
    )


def kdt_step(at: str, tag: str = "") -> str:
    return ", ".join(
        [
            f"box{tag} AS (SELECT code, count(*) AS n, CASE WHEN max(x0) - min(x0) >= max(x1) - min(x1) THEN 0 ELSE 1 END AS dim FROM {at} GROUP BY code)",
            f"kcut{tag} AS (SELECT code, any_value(n) AS n, any_value(dim) AS dim, quantile_cont(CASE WHEN dim = 0 THEN x0 ELSE x1 END, 0.5) AS cut, min(CASE WHEN dim = 0 THEN x0 ELSE x1 END) AS least FROM {at} JOIN box{tag} USING (code) GROUP BY code)",
            f"side{tag} AS (SELECT code * 2 + CASE WHEN CASE WHEN cut <= least THEN (CASE WHEN dim = 0 THEN x0 ELSE x1 END) > cut ELSE (CASE WHEN dim = 0 THEN x0 ELSE x1 END) >= cut END THEN 1 ELSE 0 END AS code, pid, x0, x1 FROM {at} JOIN kcut{tag} USING (code))",
        ]
    )


def root(name: str) -> str:
    return f"{points(name)}, top AS (SELECT CAST(1 AS BIGINT) AS code, * FROM pts)"


def level3(name: str, step) -> str:
    ctes, at = [root(name)], "top"
    for d in range(3):
        ctes.append(step(at, tag=f"_{d}"))
        at = f"side_{d}"
    return f"WITH {', '.join(ctes)} SELECT CAST(code AS BIGINT) AS code, count(*) AS n FROM {at} GROUP BY code"


def table_of(name: str) -> View:
    return VIEWS[name]
