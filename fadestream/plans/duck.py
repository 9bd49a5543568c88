"""A small builder of DuckDB SQL for the checks: it shares no formula code with the engine.

Points are wide rows (id, b, v1..vd) of BIGINT features; centroids are (k, c1..cd); every step is one CTE.
"""

from __future__ import annotations

N, K, D = 200, 4, 4
EV = f"ev AS (SELECT event_id AS id, event_id // {N} AS b, CAST(round(value * 10) AS BIGINT) AS v1, CAST(json_extract_string(props, '$.k') AS BIGINT) * 10 AS v2, CAST(hour(ts) AS BIGINT) * 40 AS v3, (CAST(dayofweek(ts) AS BIGINT) + 1) * 100 AS v4 FROM events)"
EM_D = 64
EM = "em AS (SELECT vec_id AS id, vec_id // 50 AS b, label, " + ", ".join(f"CAST(round(CAST(embedding[{j}] AS DOUBLE) * 1000) AS BIGINT) AS v{j}" for j in range(1, EM_D + 1)) + " FROM embeddings)"
LI = "li AS (SELECT md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, CAST(round(l_quantity*100) AS BIGINT), CAST(round(l_extendedprice*100) AS BIGINT), l_returnflag, l_linestatus, strftime(l_shipdate, '%Y-%m-%d'))) AS id, date_trunc('month', l_shipdate) AS mon, CAST(round(l_quantity * 10) AS BIGINT) AS v1, CAST(round(l_extendedprice / 10) AS BIGINT) AS v2 FROM lineitem), lim AS (SELECT li.*, dense_rank() OVER (ORDER BY mon) - 1 AS b FROM li)"


def cols(p: str, d: int, by: str = ", ") -> str:
    return by.join(f"{p}{j}" for j in range(1, d + 1))


def first_rows(name: str, pts: str, k: int, d: int, where: str = "b = 0") -> str:
    cs = ", ".join(f"CAST(v{j} AS DOUBLE) AS c{j}" for j in range(1, d + 1))
    return f"{name} AS (SELECT CAST(row_number() OVER (ORDER BY id) - 1 AS INTEGER) AS k, {cs} FROM (SELECT * FROM {pts} WHERE {where} ORDER BY id LIMIT {k}))"


def d2(p: str, c: str, d: int, pv: str = "v", cv: str = "c") -> str:
    return " + ".join(f"({p}.{pv}{j} - {c}.{cv}{j}) * ({p}.{pv}{j} - {c}.{cv}{j})" for j in range(1, d + 1))


def near(name: str, pts: str, cents: str, d: int) -> str:
    e = d2("p", "c", d)
    return f"{name} AS (SELECT * FROM (SELECT p.*, c.k AS k, {e} AS d2, row_number() OVER (PARTITION BY p.id ORDER BY {e}, c.k) AS r FROM {pts} p CROSS JOIN {cents} c) WHERE r = 1)"


def mean(name: str, assigned: str, old: str, d: int, w: str = "1") -> str:
    body = ", ".join(f"CASE WHEN count(a.k) > 0 AND sum({w}) > 0 THEN sum({w} * a.v{j}) / sum({w}) ELSE c.c{j} END AS c{j}" for j in range(1, d + 1))
    return f"{name} AS (SELECT c.k, {body} FROM {old} c LEFT JOIN {assigned} a ON a.k = c.k GROUP BY c.k, {', '.join(f'c.c{j}' for j in range(1, d + 1))})"


def lloyd(prefix: str, pts: str, start: str, n: int, d: int, w: str = "CAST(1 AS DOUBLE)") -> tuple[str, str]:
    """CTEs of n updates; the name of the last centroids."""
    out, now = [], start
    for i in range(1, n + 1):
        out += [near(f"{prefix}a{i}", pts, now, d), mean(f"{prefix}c{i}", f"{prefix}a{i}", now, d, w)]
        now = f"{prefix}c{i}"
    return ",\n".join(out), now


def flat(cents: str, d: int, more: str = "") -> str:
    """Rows k, dim, value (rounded) of centroids, as selects joined by UNION ALL."""
    return " UNION ALL ".join(f"SELECT k, CAST({j - 1} AS INTEGER) AS dim, round(c{j}, 6) AS value{more} FROM {cents}" for j in range(1, d + 1))


def uniform(expr: str) -> str:
    return f"((CAST(('0x' || substr(md5({expr}), 1, 8)) AS BIGINT) + 0.5) / 4294967296.0)"


def race(prefix: str, pts: str, k: int, d: int, power: int = 2, w: str = "1", seed: int = 0) -> tuple[str, str]:
    """CTEs of sequential seeding by races; the name of the relation (rnd, id, v..)."""
    out = [f"{prefix}0 AS (SELECT CAST(0 AS INTEGER) AS rnd, * FROM {pts} WHERE {w} > 0 ORDER BY -ln({uniform(f'''id || '-{seed}.0' ''')}) / {w}, CAST(id AS VARCHAR) LIMIT 1)"]
    for r in range(1, k):
        e = d2("p", "s", d, "v", "v")
        dist = f"min({e})" if power == 2 else f"sqrt(CAST(min({e}) AS DOUBLE))"
        out.append(
            f"{prefix}d{r} AS (SELECT p.id, {dist} AS dd FROM {pts} p CROSS JOIN {prefix}{r - 1} s GROUP BY p.id),\n"
            f"{prefix}{r} AS (SELECT * FROM {prefix}{r - 1} UNION ALL (SELECT CAST({r} AS INTEGER) AS rnd, p.* FROM {pts} p JOIN {prefix}d{r} q ON p.id = q.id WHERE dd > 0 AND {w} > 0 ORDER BY -ln({uniform(f'''p.id || '-{seed}.{r}' ''')}) / ({w} * dd), CAST(p.id AS VARCHAR) LIMIT 1))"
        )
    return ",\n".join(out), f"{prefix}{k - 1}"


def with_(*parts: str, select: str) -> str:
    return "WITH " + ",\n".join(p for p in parts if p) + "\n" + select
