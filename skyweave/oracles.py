"""DuckDB SQL of the queries: shared fragments first."""

from __future__ import annotations

PI = "3.141592653589793"
DAY = "date_diff('day', DATE '2024-01-01', CAST(ts AS DATE))"
E0 = f"e0 AS (SELECT {DAY} AS interval_id, row_number() OVER (PARTITION BY CAST(ts AS DATE) ORDER BY ts, event_id) - 1 AS t, row_number() OVER (ORDER BY ts, event_id) - 1 AS g, user_id AS pix, value AS d FROM events)"
W0 = f"{E0}, tod AS (SELECT interval_id, t, pix, 0.0 AS phi, d, interval_id % 2 AS noise_id, g FROM e0)"
W0P = f"{E0}, tod AS (SELECT interval_id, t, pix, {PI} / 4 * (g % 4) AS phi, d, interval_id % 2 AS noise_id, g FROM e0)"


def kernel(knees: dict[int, float], lambda_: int, grid: int = 1024) -> str:
    """CTE kern(noise_id, lag, w): cosine sum of the inverse spectrum, times the Gaussian window."""
    fk = ", ".join(f"({k}, {v})" for k, v in knees.items())
    return f"""kn(noise_id, fk) AS (VALUES {fk}),
modes AS (SELECT noise_id, m, (least(m, {grid} - m) / {grid}.0)**2 / ((least(m, {grid} - m) / {grid}.0)**2 + fk * fk) AS ip FROM kn, range({grid}) r(m)),
kern AS (SELECT noise_id, k AS lag, sum(ip * cos(2 * pi() * ((m * k) % {grid}) / {grid})) / {grid} * exp(-2 * (k / {lambda_}.0)**2) AS w FROM modes, range({lambda_} + 1) s(k) GROUP BY noise_id, k)"""


KERN0 = kernel({0: 0.05, 1: 0.1}, 128)
A0 = "am AS (SELECT a.pix AS p, b.pix AS q, sum(w) AS v FROM tod a JOIN tod b ON a.interval_id = b.interval_id AND b.t BETWEEN a.t - 128 AND a.t + 128 JOIN kern ON kern.noise_id = a.noise_id AND kern.lag = abs(a.t - b.t) GROUP BY ALL)"
Y0 = "y0 AS (SELECT a.interval_id, a.t, a.pix, a.phi, sum(w * b.d) AS y FROM tod a JOIN tod b ON a.interval_id = b.interval_id AND b.t BETWEEN a.t - 128 AND a.t + 128 JOIN kern ON kern.noise_id = a.noise_id AND kern.lag = abs(a.t - b.t) GROUP BY ALL)"

#: Days of the event stream with their numbers of samples: the intervals whose modes, bands and kernels the noise queries describe.
DAYS = f"days AS (SELECT {DAY} AS interval_id, count(*) AS n FROM events GROUP BY 1)"


def solved(columns: str) -> str:
    """CTEs that solve a dense system: cells(p, q, v) and b(p, v) with consecutive row numbers; sol(p, x) by elimination."""
    return f"""{columns},
dim AS (SELECT count(*) AS n FROM bv),
rws AS (SELECT c.p, list(coalesce(v, 0.0) ORDER BY q) AS r FROM (SELECT x.p, y.p AS q, cells.v FROM bv x CROSS JOIN bv y LEFT JOIN cells ON cells.p = x.p AND cells.q = y.p) c GROUP BY c.p),
mat AS (SELECT list(list_append(r, bv.v) ORDER BY rws.p) AS m FROM rws JOIN bv USING (p)),
el(k, m) AS (SELECT CAST(1 AS BIGINT), m FROM mat UNION ALL
  SELECT k + 1, list_transform(m, lambda r, i: CASE WHEN i = k THEN r ELSE list_transform(r, lambda v, j: v - r[k] / piv[k] * piv[j]) END)
  FROM (SELECT k, m, m[k] AS piv FROM el, dim WHERE k <= n)),
fin AS (SELECT m FROM el, dim WHERE k = n + 1),
sol AS (SELECT p, m[p][len(m) + 1] / m[p][p] AS x FROM fin, bv)"""


W0_SYSTEM = f"""{W0}, {KERN0}, {A0}, {Y0},
num AS (SELECT pix, row_number() OVER (ORDER BY pix) AS p FROM (SELECT DISTINCT pix FROM tod)),
cells AS (SELECT x.p, y.p AS q, v FROM am JOIN num x ON x.pix = am.p JOIN num y ON y.pix = am.q),
bv AS (SELECT num.p, sum(y) AS v FROM y0 JOIN num USING (pix) GROUP BY num.p)"""
MAP_W0 = f"WITH RECURSIVE {solved(W0_SYSTEM)} SELECT num.pix, round(x, 6) + 0.0 AS i FROM sol JOIN num USING (p)"

LINE = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice"
W1 = f"""g0 AS (SELECT *, l_suppkey % 20 AS gx, CAST(floor((l_quantity - 1) * 20 / 50) AS BIGINT) AS gy FROM lineitem),
g1 AS (SELECT *, row_number() OVER (PARTITION BY gx, gy ORDER BY {LINE}) - 1 AS sweep FROM g0),
g2 AS (SELECT *, CASE WHEN sweep % 2 = 0 THEN gy ELSE gx END AS major, CASE WHEN sweep % 2 = 0 THEN gx ELSE gy END AS minor FROM g1),
tod AS (SELECT 0 AS interval_id, row_number() OVER (ORDER BY sweep, major, minor) - 1 AS t, gy * 20 + gx AS pix, sweep, l_extendedprice AS d FROM g2)"""


def circle(angle: str, lon0: str, radius: float, rows: int, cols: int) -> str:
    import math

    r = math.radians(radius)
    lat = f"({math.sin(r)!r} * cos({angle}))"
    turn = f"(({lon0} + atan2(sin({angle}) * {math.sin(r)!r}, {math.cos(r)!r})) / {2 * math.pi!r})"
    turn = f"({turn} - floor(round({turn}, 9)))"
    return f"CAST(floor(round(({lat} + 1) / 2 * {rows}, 9)) * {cols} + (CAST(floor(round({turn} * {cols}, 9)) AS BIGINT) % {cols} + {cols}) % {cols} AS BIGINT)"


TWO_PI = "6.283185307179586"
W2 = f"""o0 AS (SELECT o_custkey % 32 AS circle, year(o_orderdate) AS year, dayofyear(o_orderdate) AS doy, o_orderkey, o_totalprice FROM orders),
tod AS (SELECT 0 AS interval_id, row_number() OVER (ORDER BY circle, year, doy, o_orderkey) - 1 AS t, {circle(f"(doy * ({TWO_PI} / 366))", f"(circle * ({TWO_PI} / 32))", 7.5, 64, 128)} AS pix, year, o_totalprice AS d FROM o0)"""
W3 = f"""l0 AS (SELECT {LINE}, year(l_shipdate) AS year, dayofyear(l_shipdate) AS doy FROM lineitem),
nc AS (SELECT count(*) AS n FROM supplier),
tod AS (SELECT l_suppkey AS interval_id, row_number() OVER (PARTITION BY l_suppkey ORDER BY year, doy, l_orderkey, l_linenumber, l_partkey, l_extendedprice) - 1 AS t, {circle(f"(doy * ({TWO_PI} / 366))", f"(l_suppkey * ({TWO_PI} / n))", 30.0, 32, 64)} AS pix, year, l_suppkey % 2 AS noise_id, l_extendedprice AS d FROM l0, nc)"""
W6 = "tod AS (SELECT c_nationkey AS pix, o_totalprice AS d FROM orders JOIN customer ON c_custkey = o_custkey)"
BD3 = "bl AS (SELECT pix, sum(1.0) AS c11, sum(cos(2 * phi)) AS c12, sum(sin(2 * phi)) AS c13, sum(cos(2 * phi)**2) AS c22, sum(cos(2 * phi) * sin(2 * phi)) AS c23, sum(sin(2 * phi)**2) AS c33 FROM tod GROUP BY pix)"
PZ = "hp AS (SELECT pix, interval_id, count(*) AS h FROM tod GROUP BY ALL), zs AS (SELECT pix, interval_id, h / CAST(sum(h) OVER (PARTITION BY pix) AS DOUBLE) AS z FROM hp)"
W4 = """tod AS (SELECT CAST(regexp_extract(source, '(\\d+)$', 1) AS BIGINT) AS interval_id, row_number() OVER (PARTITION BY source ORDER BY doc_id, n_chars) - 1 AS t, list_position(['de', 'en', 'es', 'fr'], lang) - 1 AS pix, n_chars AS d, 0 AS noise_id FROM documents WHERE lang IN ('de', 'en', 'es', 'fr') AND source IS NOT NULL AND n_chars IS NOT NULL)"""
W5 = """tod AS (SELECT conv_id AS interval_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role, text) - 1 AS t, CASE role WHEN 'user' THEN 0 WHEN 'assistant' THEN 1 ELSE 2 END AS pix, length(coalesce(text, '')) AS d, 0 AS noise_id FROM conversations WHERE conv_id IS NOT NULL AND turn IS NOT NULL AND role IS NOT NULL)"""


def fourier_map(tod: str, knee: float, grid: int = 1024) -> str:
    """Exact map of a small intensity workload with weights diagonal in each interval's Fourier modes."""
    f = "(greatest(least(m, n - m), 0.5) / CAST(n AS DOUBLE))"
    system = f"""{tod}, len AS (SELECT interval_id, count(*) AS n FROM tod GROUP BY 1),
ip AS (SELECT interval_id, n, m, {f}**2 / ({f}**2 + {knee * knee!r}) AS p FROM len, range(len.n) r(m)),
h AS (SELECT interval_id, n, k, sum(p * cos(2 * pi() * ((m * k) % n) / n)) / n AS w FROM ip, range(ip.n) s(k) GROUP BY interval_id, n, k),
cells0 AS (SELECT a.pix AS p, b.pix AS q, sum(w) AS v FROM tod a JOIN tod b USING (interval_id) JOIN h ON h.interval_id = a.interval_id AND h.k = abs(a.t - b.t) GROUP BY ALL),
b0 AS (SELECT a.pix, sum(w * b.d) AS v FROM tod a JOIN tod b USING (interval_id) JOIN h ON h.interval_id = a.interval_id AND h.k = abs(a.t - b.t) GROUP BY ALL),
num AS (SELECT pix, row_number() OVER (ORDER BY pix) AS p FROM (SELECT DISTINCT pix FROM tod)),
cells AS (SELECT x.p, y.p AS q, v FROM cells0 JOIN num x ON x.pix = cells0.p JOIN num y ON y.pix = cells0.q),
bv AS (SELECT num.p, v FROM b0 JOIN num USING (pix))"""
    return f"WITH RECURSIVE {solved(system)} SELECT CAST(num.pix AS BIGINT) AS pix, round(x, 6) + 0.0 AS i FROM sol JOIN num USING (p)"


def small_map(tod: str, knee: float, lambda_: int, whole: bool = False) -> str:
    """Exact map of a small intensity workload; ``whole`` leaves the band without a window."""
    near = f"a.interval_id = b.interval_id AND b.t BETWEEN a.t - {lambda_} AND a.t + {lambda_} JOIN kern ON kern.lag = abs(a.t - b.t)"
    kern = kernel({0: knee}, lambda_)
    if whole:
        kern = kern.replace(f" * exp(-2 * (k / {lambda_}.0)**2)", "")
    system = f"""{tod}, {kern},
cells0 AS (SELECT a.pix AS p, b.pix AS q, sum(w) AS v FROM tod a JOIN tod b ON {near} GROUP BY ALL),
b0 AS (SELECT a.pix, sum(w * b.d) AS v FROM tod a JOIN tod b ON {near} GROUP BY ALL),
num AS (SELECT pix, row_number() OVER (ORDER BY pix) AS p FROM (SELECT DISTINCT pix FROM tod)),
cells AS (SELECT x.p, y.p AS q, v FROM cells0 JOIN num x ON x.pix = cells0.p JOIN num y ON y.pix = cells0.q),
bv AS (SELECT num.p, v FROM b0 JOIN num USING (pix))"""
    return f"WITH RECURSIVE {solved(system)} SELECT CAST(num.pix AS BIGINT) AS pix, round(x, 6) + 0.0 AS i FROM sol JOIN num USING (p)"


W0_POL = f"""WITH RECURSIVE {{sys}} SELECT num.pix, round(max(CASE s WHEN 0 THEN x END), 6) + 0.0 AS i, round(max(CASE s WHEN 1 THEN x END), 6) + 0.0 AS q, round(max(CASE s WHEN 2 THEN x END), 6) + 0.0 AS u FROM sol JOIN num USING (p) GROUP BY num.pix"""
_POL_SYSTEM = f"""{W0P}, {KERN0}, {Y0},
num AS (SELECT pix, s, row_number() OVER (ORDER BY pix, s) AS p FROM (SELECT DISTINCT pix FROM tod), range(3) r(s)),
resp AS (SELECT tod.*, s, CASE s WHEN 0 THEN 1.0 WHEN 1 THEN round(cos(2 * phi)) ELSE round(sin(2 * phi)) END AS c FROM tod, range(3) r(s)),
nz AS (SELECT resp.interval_id, resp.t, resp.noise_id, num.p, c FROM resp JOIN num ON num.pix = resp.pix AND num.s = resp.s WHERE c <> 0),
cells AS (SELECT a.p, b.p AS q, sum(w * a.c * b.c) AS v FROM nz a JOIN nz b ON a.interval_id = b.interval_id AND b.t BETWEEN a.t - 128 AND a.t + 128 JOIN kern ON kern.noise_id = a.noise_id AND kern.lag = abs(a.t - b.t) GROUP BY ALL),
bv AS (SELECT nz.p, sum(y * c) AS v FROM y0 JOIN nz ON nz.interval_id = y0.interval_id AND nz.t = y0.t GROUP BY nz.p)"""
MAP_W0_POL = W0_POL.replace("{sys}", solved(_POL_SYSTEM))
