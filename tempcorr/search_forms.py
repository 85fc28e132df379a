"""DuckDB SQL of searches: planted series, nearest-neighbour scores of grid windows, scans as recursive queries.

The SQL shares no code with the engine: it joins every two points of a window, and takes windows one after the other.
"""

from __future__ import annotations


from tempcorr.oracle_forms import rounded

HOUR = "CAST(date_diff('hour', TIMESTAMP '2024-01-01', ts) AS BIGINT)"
QUARTER = "CAST(floor(date_diff('minute', TIMESTAMP '2024-01-01', ts) / 15) AS BIGINT)"
MEAN = "round(round(sum(value), 2) / count(*), 6)"
PSI = "(CASE WHEN {0} > 1 THEN list_sum(list_transform(range(1, CAST({0} AS BIGINT)), lambda j: 1.0::DOUBLE / j)) ELSE 0 END - 0.5772156649015329)"


def noise(salt: str, idx: str = "idx") -> str:
    return f"(CAST('0x' || substr(md5(CAST({idx} AS VARCHAR) || '{salt}'), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE)"


def shape(kind: str) -> str:
    u, v, pi = noise("c"), noise("d"), "3.141592653589793::DOUBLE"
    branch = f"(CASE WHEN {u} < 0.5 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END)"
    return {
        "independent": v,
        "independent_outliers": f"(CASE WHEN {u} < 0.1 THEN x ELSE {v} END)",
        "linear": "x",
        "negative": "(1 - x)",
        "linear_outliers": f"(CASE WHEN {u} < 0.1 THEN {v} ELSE x END)",
        "exponential": "(exp(4 * x) / 54.598150033144236::DOUBLE)",
        "quadratic": "pow(2 * x - 1, 2)",
        "diamond": f"(0.5 + {branch} * (0.5 - abs(x - 0.5)) * {v})",
        "circle": f"(0.5 + {branch} * sqrt(greatest(0.0::DOUBLE, 0.25 - pow(x - 0.5, 2))))",
        "sine": f"(0.5 + 0.5 * sin(4 * {pi} * x))",
        "cross": f"(CASE WHEN {u} < 0.5 THEN x ELSE 1 - x END)",
    }[kind]


def related(spans, name: str, source: str = "rk", out: str = "p") -> str:
    """Table out (pair_id, idx, x, y): y a function of x in the spans, noise elsewhere. A span of None is the whole series."""
    whole = " ".join(f"WHEN {'true' if s is None else f'idx >= {s} AND idx < {e}'} THEN {shape(k)} + 0.02 * {noise('b')}" for s, e, k in reversed(spans))
    return f"{out} AS (SELECT '{name}' AS pair_id, idx, x, CASE {whole} ELSE {noise('a')} END AS y FROM {source})"


def ranked(idx: str = HOUR, value: str = MEAN, where: str = "", filled: bool = False) -> str:
    """Tables up to rk (idx, x): a series of events without gaps, as ranks."""
    h = f"h AS (SELECT {idx} AS idx, {value} AS v FROM events {where} GROUP BY 1)"
    spine = "sp AS (SELECT unnest(range((SELECT min(idx) FROM h), (SELECT max(idx) + 1 FROM h))) AS idx)"
    if filled:
        even = "ev AS (SELECT sp.idx, coalesce(v, 0) AS v FROM sp LEFT JOIN h ON sp.idx = h.idx)"
    else:
        even = """sf AS (SELECT sp.idx, h.v, last_value(h.idx IGNORE NULLS) OVER a AS ia, first_value(h.idx IGNORE NULLS) OVER z AS ib, last_value(h.v IGNORE NULLS) OVER a AS va, first_value(h.v IGNORE NULLS) OVER z AS vb FROM sp LEFT JOIN h ON sp.idx = h.idx
        WINDOW a AS (ORDER BY sp.idx ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), z AS (ORDER BY sp.idx ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)),
        ev AS (SELECT idx, CASE WHEN v IS NOT NULL THEN v ELSE va + (vb - va) * (idx - ia) / (ib - ia) END AS v FROM sf)"""
    return f"{h}, {spine}, {even}, rk AS (SELECT CAST(idx AS BIGINT) AS idx, row_number() OVER (ORDER BY v, idx) / count(*) OVER ()::DOUBLE AS x FROM ev)"


def evened(source: str = "raw", out: str = "p") -> str:
    """Table out (pair_id, idx, x, y) from source: without gaps, interpolated, for every pair from its first to its last step."""
    sides = ", ".join(f"last_value(r.{c} IGNORE NULLS) OVER a AS {c}a, first_value(r.{c} IGNORE NULLS) OVER z AS {c}b" for c in "xy")
    value = ", ".join(f"CASE WHEN {c} IS NOT NULL THEN {c} ELSE {c}a + ({c}b - {c}a) * (idx - ia) / (ib - ia) END AS {c}" for c in "xy")
    return f"""es AS (SELECT pair_id, unnest(range(min(idx), max(idx) + 1)) AS idx FROM {source} GROUP BY pair_id),
    ef AS (SELECT es.pair_id, es.idx, r.x, r.y, {sides}, last_value(r.idx IGNORE NULLS) OVER a AS ia, first_value(r.idx IGNORE NULLS) OVER z AS ib FROM es LEFT JOIN {source} r ON es.pair_id = r.pair_id AND es.idx = r.idx
    WINDOW a AS (PARTITION BY es.pair_id ORDER BY es.idx ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), z AS (PARTITION BY es.pair_id ORDER BY es.idx ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)),
    {out} AS (SELECT pair_id, idx, {value} FROM ef)"""


def untied(source: str = "p", out: str = "u") -> str:
    spread = f"(SELECT pair_id, coalesce(nullif(stddev_pop(x), 0), 1) AS sx, coalesce(nullif(stddev_pop(y), 0), 1) AS sy FROM {source} GROUP BY 1)"
    return f"{out} AS (SELECT pair_id, idx, x + 1e-6::DOUBLE * sx * ({noise('tiex')} - 0.5) AS x, y + 1e-6::DOUBLE * sy * ({noise('tiey')} - 0.5) AS y FROM {source} JOIN {spread} USING (pair_id))"


def neighbours(by: str, source: str, k: int = 6) -> str:
    """Table km (by, n, mi): the nearest-neighbour information of every group of points of source (by, idx, x, y)."""
    return f"""kd AS (SELECT a.{by}, a.idx, abs(b.x - a.x) AS ax, abs(b.y - a.y) AS ay, row_number() OVER (PARTITION BY a.{by}, a.idx ORDER BY greatest(abs(b.x - a.x), abs(b.y - a.y)), b.idx) AS rn FROM {source} a JOIN {source} b ON a.{by} = b.{by} AND a.idx <> b.idx),
    kx AS (SELECT {by}, idx, max(ax) AS dx, max(ay) AS dy FROM kd WHERE rn <= {k} GROUP BY ALL),
    kc AS (SELECT kx.{by}, kx.idx, sum(CASE WHEN ax <= dx THEN 1 ELSE 0 END) AS nx, sum(CASE WHEN ay <= dy THEN 1 ELSE 0 END) AS ny, count(*) + 1 AS n FROM kx JOIN kd ON kd.{by} = kx.{by} AND kd.idx = kx.idx GROUP BY ALL),
    km AS (SELECT {by}, CAST(max(n) AS BIGINT) AS n, {PSI.format(k)} - 1.0::DOUBLE / {k} - avg({PSI.format('nx')} + {PSI.format('ny')}) + {PSI.format('max(n)')} AS mi FROM kc GROUP BY {by})"""


def bins_for(n: int) -> int:
    return max(3, round((n / 5) ** 0.5))


def entropies(by: str, source: str, bins: str) -> str:
    """Table he (by, hxy): the joint entropy of every group in equal-width bins; bins is an expression."""
    one = "CASE WHEN max({0}) OVER w = min({0}) OVER w THEN 0 ELSE CAST(least(floor(({0} - min({0}) OVER w) / (max({0}) OVER w - min({0}) OVER w) * " + bins + "), " + bins + " - 1) AS INT) END"
    return f"""hb AS (SELECT {by}, {one.format('x')} AS bx, {one.format('y')} AS b_y FROM {source} WINDOW w AS (PARTITION BY {by})),
    hc AS (SELECT {by}, bx, b_y, count(*) AS c, sum(count(*)) OVER (PARTITION BY {by}) AS n FROM hb GROUP BY {by}, bx, b_y),
    he AS (SELECT {by}, sum(-c / n * ln(c / n)) AS hxy, ln(max(n)) AS log_n FROM hc GROUP BY {by})"""


def steps(by: str, source: str) -> str:
    """Table st (by, mu, sign)."""
    return f"""sd AS (SELECT {by}, sign(x - lag(x) OVER w) * sign(y - lag(y) OVER w) AS t FROM {source} WINDOW w AS (PARTITION BY {by} ORDER BY idx)),
    sm AS (SELECT {by}, (sum(CASE WHEN t > 0 THEN 1 ELSE 0 END) - sum(CASE WHEN t < 0 THEN 1 ELSE 0 END)) / (count(*) - 1) AS mu FROM sd GROUP BY 1),
    st AS (SELECT *, CASE WHEN mu > 0 THEN 'positive' WHEN mu < 0 THEN 'negative' WHEN mu = 0 THEN 'neither' END AS sign FROM sm)"""


def windows(layers, source: str = "u") -> str:
    """Tables up to sc (pair_id, layer, s, e, n, mi, hxy, h_norm, mi_norm1, mi_norm2, mu, sign): all grid windows of all layers."""
    wl = " UNION ALL ".join(f"SELECT pair_id, {i} AS layer, {g} AS g, {bins_for(g)} AS bins, CAST(unnest(range(lo, hi - {g} + 1, {step})) AS BIGINT) AS s FROM (SELECT pair_id, min(idx) AS lo, max(idx) + 1 AS hi FROM {source} GROUP BY 1)" for i, (g, step) in enumerate(layers))
    return f"""wl AS (SELECT *, s + g AS e, pair_id || '/' || layer || '/' || s AS w FROM ({wl})),
    pw AS (SELECT w, idx, x, y, bins FROM {source} JOIN wl ON {source}.pair_id = wl.pair_id AND idx >= s AND idx < e),
    {neighbours('w', 'pw')}, {entropies('w', 'pw', 'bins')}, {steps('w', 'pw')},
    sc AS (SELECT pair_id, layer, s, e, n, mi, hxy, hxy / log_n AS h_norm, mi / log_n AS mi_norm1, CASE WHEN hxy > 0 THEN mi / hxy END AS mi_norm2, mu, sign FROM wl JOIN km USING (w) JOIN he USING (w) JOIN st USING (w))"""


def scans(n: int, rule: str, independent: bool = False) -> str:
    """Tables up to sel (pair_id, layer, s, e): layer by layer the first window that passes and begins after the last one taken."""
    out = []
    for i in range(n):
        free = " ".join(f"AND NOT EXISTS (SELECT 1 FROM g{j} t WHERE t.pair_id = sc.pair_id AND t.s < sc.e AND t.e > sc.s)" for j in range(i)) if not independent else ""
        out.append(f"ok{i} AS (SELECT pair_id, s, e FROM sc WHERE layer = {i} AND {rule} {free})")
        out.append(f"g{i} AS (SELECT * FROM (SELECT pair_id, min(s) AS s, min(e) AS e FROM ok{i} GROUP BY 1) UNION ALL SELECT t.pair_id, t.s, t.e FROM g{i}, LATERAL (SELECT * FROM ok{i} o WHERE o.pair_id = g{i}.pair_id AND o.s >= g{i}.e ORDER BY o.s LIMIT 1) t)")
    out.append(f"sel AS ({' UNION ALL '.join(f'SELECT {i} AS layer, * FROM g{i}' for i in range(n))})")
    return ", ".join(out)


def search(series: str, layers, rule: str, columns: str, independent: bool = False, top: int = 0) -> str:
    """A whole search over the table p that `series` ends with. rule: over the columns of sc. top: only a pair's best windows."""
    found = "SELECT sc.* FROM sel JOIN sc USING (pair_id, layer, s, e)"
    if top:
        found = f"SELECT * FROM ({found}) QUALIFY row_number() OVER (PARTITION BY pair_id ORDER BY mi DESC, s) <= {top}"
    return f"WITH RECURSIVE {series}, {untied()}, {windows(layers)}, {scans(len(layers), rule, independent)}, fin AS ({found}) SELECT {columns} FROM fin"


def overall(series: str, columns: str, bins: str = "CAST(greatest(3, round_even(sqrt(count(*) OVER (PARTITION BY pair_id) / 5.0::DOUBLE), 0)) AS INT)") -> str:
    """One window over all of each pair of the table p, its ties broken."""
    return f"WITH {series}, {untied()}, ub AS (SELECT *, {bins} AS bins FROM u), {neighbours('pair_id', 'u')}, {entropies('pair_id', 'ub', 'bins')}, {steps('pair_id', 'u')}, ov AS (SELECT *, mi / log_n AS mi_norm1, hxy / log_n AS h_norm, CASE WHEN hxy > 0 THEN mi / hxy END AS mi_norm2 FROM km JOIN he USING (pair_id) JOIN st USING (pair_id)) SELECT {columns} FROM ov"


SHOWN = f"pair_id, CAST(layer AS INT) AS layer, s, e, {rounded('mi', 'mi_norm2', 'mu')}, sign"
