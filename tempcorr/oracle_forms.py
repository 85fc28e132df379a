"""Parts of DuckDB SQL that several oracles share."""

from __future__ import annotations


def rounded(*columns: str) -> str:
    return ", ".join(f"(round({c}, 6) + 0.0) AS {c}" for c in columns)


def bins(source: str) -> str:
    """Rows of source (pair_id, x, y) with their six equal-width bins bx and b_y."""
    one = "CASE WHEN max({0}) OVER w = min({0}) OVER w THEN 0 ELSE CAST(least(floor(({0} - min({0}) OVER w) / (max({0}) OVER w - min({0}) OVER w) * 6), 5) AS INT) END AS {1}"
    return f"SELECT *, {one.format('x', 'bx')}, {one.format('y', 'b_y')} FROM {source} WINDOW w AS (PARTITION BY pair_id)"


def info(cells: str, by: str) -> str:
    """From rows (by, bx, b_y) to table j: n, hx, hy, hxy, mi and the normalised forms."""
    return f"""c AS (SELECT {by}, bx, b_y, count(*) AS c FROM {cells} GROUP BY ALL),
    t AS (SELECT *, sum(c) OVER (PARTITION BY {by}, bx) AS cx, sum(c) OVER (PARTITION BY {by}, b_y) AS cy, sum(c) OVER (PARTITION BY {by}) AS n FROM c),
    i AS (SELECT {by}, CAST(n AS BIGINT) AS n, sum(-c / n * ln(cx / n)) AS hx, sum(-c / n * ln(cy / n)) AS hy, sum(-c / n * ln(c / n)) AS hxy, sum(c / n * ln(c * n / (cx * cy))) AS mi FROM t GROUP BY {by}, n),
    j AS (SELECT *, hxy / ln(n) AS h_norm, mi / ln(n) AS mi_norm1, CASE WHEN hxy > 0 THEN mi / hxy END AS mi_norm2 FROM i)"""


#: From p (pair_id, idx, x, y) to table r: the steps in equal and in opposite direction, and the degree mu.
STEPS = "z AS (SELECT *, sign(x - lag(x) OVER w) * sign(y - lag(y) OVER w) AS t FROM p WINDOW w AS (PARTITION BY pair_id ORDER BY idx)), u AS (SELECT pair_id, count(*) AS n, CAST(sum(CASE WHEN t > 0 THEN 1 ELSE 0 END) AS BIGINT) AS pp, CAST(sum(CASE WHEN t < 0 THEN 1 ELSE 0 END) AS BIGINT) AS np FROM z GROUP BY 1), r AS (SELECT *, (pp - np) / (n - 1) AS mu FROM u)"
