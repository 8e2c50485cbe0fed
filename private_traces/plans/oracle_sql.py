"""Pieces of DuckDB SQL that the oracles are put together from."""

from __future__ import annotations

SEED = 42


def uniform(stage: str, *keys: str, seed: int = SEED) -> str:
    text = " || '|' || ".join([f"'{seed}|{stage}'", *[f"({k})::VARCHAR" for k in keys]])
    return f"((('0x' || substr(md5({text}), 1, 12))::UBIGINT + 0.5) / 281474976710656.0)"


def laplace(scale: float, stage: str, *keys: str) -> str:
    u = uniform(stage, *keys)
    return f"(-{scale} * sign({u} - 0.5) * ln(1 - 2 * abs({u} - 0.5)))"


def axis(v: str, low: float, high: float, n: int) -> str:
    return f"greatest(0, least({n - 1}, floor(({v} - {low}) / ({high} - {low})::DOUBLE * {n})))::INTEGER"


def cell(x: str, y: str, n: int, b=(0, 1, 0, 1)) -> str:
    return f"({axis(x, b[0], b[1], n)} * {n} + {axis(y, b[2], b[3], n)})"


def allowed(side: str) -> str:
    return f"(CASE WHEN {side} <= 1 THEN 1 WHEN {side} <= 2 THEN 2 WHEN {side} <= 3 THEN 3 ELSE 6 END)"


_LINE = "PARTITION BY l_orderkey ORDER BY l_shipdate, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_quantity"
_DRIFT = f"""drift_trips AS (
  SELECT trace_id, seq, least(999999, greatest(0, first_value(sx) OVER w + sum(CASE WHEN seq = 1 THEN 0 ELSE dx END) OVER w))::DOUBLE / 1000000.0 AS x,
    least(999999, greatest(0, first_value(sy) OVER w + sum(CASE WHEN seq = 1 THEN 0 ELSE dy END) OVER w))::DOUBLE / 1000000.0 AS y, ts
  FROM (SELECT l_orderkey AS trace_id, (row_number() OVER ({_LINE}))::INTEGER AS seq, l_shipdate::TIMESTAMP AS ts,
    round(3000000 * (l_discount - 0.05))::BIGINT AS dx, round(4000000 * (l_tax - 0.04))::BIGINT AS dy,
    round(((l_extendedprice - 900) / 104100) * ((l_extendedprice - 900) / 104100) * 1000000)::BIGINT AS sx,
    round(((l_quantity - 1) / 49) * ((l_quantity - 1) / 49) * 1000000)::BIGINT AS sy FROM lineitem)
  WINDOW w AS (PARTITION BY trace_id ORDER BY seq ROWS UNBOUNDED PRECEDING))"""


def _events(name: str, trace: str) -> str:
    return f"{name} AS (SELECT {trace} AS trace_id, (row_number() OVER (PARTITION BY {trace} ORDER BY ts, event_id))::INTEGER AS seq, value AS x, (props->>'$.k')::DOUBLE AS y, ts::TIMESTAMP AS ts FROM events)"


_VIEWS = {
    "order_trips": f"order_trips AS (SELECT l_orderkey AS trace_id, (row_number() OVER ({_LINE}))::INTEGER AS seq, l_extendedprice AS x, l_quantity AS y, l_shipdate::TIMESTAMP AS ts FROM lineitem)",
    "drift_trips": _DRIFT,
    "subset_trips": _DRIFT + ", subset_trips AS (SELECT * FROM drift_trips WHERE ('0x' || substr(md5('subset|' || trace_id::VARCHAR), 1, 8))::UBIGINT % 10000 < 2028)",
    "user_days": _events("user_days", "(user_id * 100 + day(ts))"),
    "user_long": _events("user_long", "user_id"),
    "customer_long": "customer_long AS (SELECT o_custkey AS trace_id, (row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey))::INTEGER AS seq, o_totalprice AS x, date_diff('day', DATE '1970-01-01', o_orderdate::DATE)::DOUBLE AS y, o_orderdate::TIMESTAMP AS ts FROM orders)",
}


def view(name: str) -> str:
    return f"WITH {_VIEWS[name]} "


SYMBOLS = "WITH symbols AS (SELECT conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS turn_no, ((CASE role WHEN 'user' THEN 0 WHEN 'assistant' THEN 1 ELSE 2 END) * 4 + least(3, coalesce(length(text), 0) // 200))::INTEGER AS cell FROM conversations) "

LEAF = view("drift_trips") + f""", leaf AS (SELECT trace_id, seq, gx, gy, ((gx // 6) * 6 + gy // 6)::INTEGER AS top, count(*) OVER (PARTITION BY trace_id) AS n
  FROM (SELECT trace_id, seq, {axis('x', 0, 1, 36)} AS gx, {axis('y', 0, 1, 36)} AS gy FROM drift_trips)) """

NOISY_GRID = LEAF + f""", dens AS (SELECT top, sum(1.0 / n) AS density FROM leaf GROUP BY top),
noisy AS (SELECT t.top::INTEGER AS top, greatest(0, coalesce(density, 0) + {laplace(4.0, 'grid', 't.top')}) AS density FROM (SELECT range AS top FROM range(36)) t LEFT JOIN dens ON dens.top = t.top),
cut AS (SELECT top, density, {allowed('round(sqrt(round(density, 9) / (SELECT avg(density) FROM noisy)), 9)')} AS m FROM noisy),
spec AS (SELECT top, m, coalesce(sum(m * m) OVER (ORDER BY top ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::INTEGER AS first_cell FROM cut) """

ADAPTIVE = NOISY_GRID + """, adaptive AS (SELECT trace_id, seq, n, (first_cell + ((gx % 6) * m // 6) * m + (gy % 6) * m // 6)::INTEGER AS cell FROM leaf JOIN spec USING (top)) """

GRID6 = view("drift_trips") + f""", cells6 AS (SELECT trace_id, seq, {cell('x', 'y', 6)} AS cell, count(*) OVER (PARTITION BY trace_id) AS n FROM drift_trips),
moves AS (SELECT trace_id, n, src, dst FROM (SELECT trace_id, n, cell AS src, lead(cell) OVER (PARTITION BY trace_id ORDER BY seq) AS dst FROM cells6) WHERE dst IS NOT NULL),
trips6 AS (SELECT trace_id, arg_min(cell, seq) AS start_cell, arg_max(cell, seq) AS end_cell, count(*) AS n FROM cells6 GROUP BY 1) """

_BOX = "SELECT first_cell + s AS cell, (top // 6 + (s // m) / m) / 6.0 AS x0, (top // 6 + (s // m + 1) / m) / 6.0 AS x1, (top % 6 + (s % m) / m) / 6.0 AS y0, (top % 6 + (s % m + 1) / m) / 6.0 AS y1 FROM spec, unnest(range(0, m * m)) AS t(s)"
_MOVES = ADAPTIVE + f""", p AS (SELECT *, lead(cell) OVER (PARTITION BY trace_id ORDER BY seq) AS nxt FROM adaptive),
moved AS (SELECT cell AS src, nxt AS dst, sum(1.0 / (n - 1)) AS weight FROM p WHERE nxt IS NOT NULL GROUP BY 1, 2),
box AS ({_BOX}), pairs AS (SELECT a.cell AS src, b.cell AS dst, a.cell = b.cell OR (least(a.x1, b.x1) - greatest(a.x0, b.x0) > 1e-9 AND abs(least(a.y1, b.y1) - greatest(a.y0, b.y0)) <= 1e-9)
  OR (least(a.y1, b.y1) - greatest(a.y0, b.y0) > 1e-9 AND abs(least(a.x1, b.x1) - greatest(a.x0, b.x0)) <= 1e-9) AS near FROM box a, box b), """
_ROWS = """mobility AS (SELECT src::INTEGER AS src, dst::INTEGER AS dst, CASE WHEN sum(w) OVER r > 0 THEN w / sum(w) OVER r ELSE near::INTEGER / sum(near::INTEGER) OVER r END AS prob FROM w WINDOW r AS (PARTITION BY src)) """
MOBILITY = _MOVES + f"""w AS (SELECT pairs.src, pairs.dst, near, greatest(0, coalesce(weight, 0) + {laplace(4.0, 'move', 'pairs.src', 'pairs.dst')}) AS w FROM pairs LEFT JOIN moved ON moved.src = pairs.src AND moved.dst = pairs.dst),
""" + _ROWS


def mobility_shifted(weight: str) -> str:
    """Rows of noisy masses lowered by one constant each, so that their sum stays."""
    return _MOVES + f"""given AS (SELECT pairs.src, pairs.dst, near, coalesce(weight, 0) AS weight, {laplace(4.0, 'move', 'pairs.src', 'pairs.dst')} AS draw FROM pairs LEFT JOIN moved ON moved.src = pairs.src AND moved.dst = pairs.dst),
raw AS (SELECT src, dst, near, {weight} AS m FROM given),
ranked AS (SELECT src, m, row_number() OVER (PARTITION BY src ORDER BY m DESC) AS i, sum(m) OVER (PARTITION BY src ORDER BY m DESC ROWS UNBOUNDED PRECEDING) AS up, sum(m) OVER (PARTITION BY src) AS total FROM raw),
lev AS (SELECT src, arg_max((up - total) / i, i) AS level FROM ranked WHERE total > 0 AND m > (up - total) / i GROUP BY 1),
w AS (SELECT raw.src, dst, near, CASE WHEN level IS NULL THEN 0 ELSE greatest(0, m - level) END AS w FROM raw LEFT JOIN lev ON lev.src = raw.src),
""" + _ROWS


TRIPS = ADAPTIVE + f""", k AS (SELECT sum(m * m)::INTEGER AS k FROM spec), ends AS (SELECT trace_id, arg_min(cell, seq) AS s, arg_max(cell, seq) AS e FROM adaptive GROUP BY 1),
cnt AS (SELECT s, e, count(*)::DOUBLE AS c FROM ends GROUP BY 1, 2), dom AS (SELECT a.range::INTEGER AS s, b.range::INTEGER AS e FROM range(0, (SELECT k FROM k)) a, range(0, (SELECT k FROM k)) b),
raw AS (SELECT dom.s, dom.e, coalesce(c, 0) + {laplace(4.0, 'trip', 'dom.s', 'dom.e')} AS m FROM dom LEFT JOIN cnt ON cnt.s = dom.s AND cnt.e = dom.e),
ranked AS (SELECT m, row_number() OVER (ORDER BY m DESC) AS i, sum(m) OVER (ORDER BY m DESC ROWS UNBOUNDED PRECEDING) AS up, (SELECT sum(m) FROM raw) AS total FROM raw),
lev AS (SELECT arg_max((up - total) / i, i) AS level FROM ranked WHERE m > (up - total) / i),
clean AS (SELECT s AS start_cell, e AS end_cell, greatest(0, m - (SELECT level FROM lev)) AS mass FROM raw),
noisy_trips AS (SELECT start_cell, end_cell, mass, mass / (SELECT sum(mass) FROM clean) AS prob FROM clean) """

TRIPS_SEPARATE = ADAPTIVE + f""", k AS (SELECT sum(m * m)::INTEGER AS k FROM spec), ends AS (SELECT trace_id, arg_min(cell, seq) AS s, arg_max(cell, seq) AS e FROM adaptive GROUP BY 1),
cnt AS (SELECT s, e, count(*)::DOUBLE AS c FROM ends GROUP BY 1, 2), dom AS (SELECT a.range::INTEGER AS s, b.range::INTEGER AS e FROM range(0, (SELECT k FROM k)) a, range(0, (SELECT k FROM k)) b),
raw AS (SELECT dom.s, dom.e, coalesce(c, 0) + {laplace(8.0, 'trip', 'dom.s', 'dom.e')} AS m FROM dom LEFT JOIN cnt ON cnt.s = dom.s AND cnt.e = dom.e),
ranked AS (SELECT m, row_number() OVER (ORDER BY m DESC) AS i, sum(m) OVER (ORDER BY m DESC ROWS UNBOUNDED PRECEDING) AS up, (SELECT count(*) FROM ends) + {laplace(8.0, 'total', '0')} AS total FROM raw),
lev AS (SELECT arg_max((up - total) / i, i) AS level FROM ranked WHERE m > (up - total) / i),
clean AS (SELECT s AS start_cell, e AS end_cell, greatest(0, m - (SELECT level FROM lev)) AS mass FROM raw),
noisy_trips AS (SELECT start_cell, end_cell, mass, mass / (SELECT sum(mass) FROM clean) AS prob FROM clean) """

DRAWN = f""", upto AS (SELECT start_cell, end_cell, prob, sum(prob) OVER (ORDER BY start_cell, end_cell ROWS UNBOUNDED PRECEDING) AS up, sum(prob) OVER () AS al FROM noisy_trips WHERE prob > 0),
iv AS (SELECT start_cell, end_cell, round((up - prob) / al, 12) AS lo, round(up / al, 12) AS hi FROM upto),
drawn AS (SELECT d.range AS trace_id, start_cell, end_cell FROM (SELECT range, {uniform('draw', 'range')} AS u FROM range(2000)) d JOIN iv ON u >= lo AND (u < hi OR hi >= 0.999999999999)) """

LAWS = GRID6 + f""", h AS (SELECT start_cell, end_cell, least(n, 32) AS len, count(*) AS c FROM trips6 GROUP BY 1, 2, 3),
dom AS (SELECT start_cell, end_cell, range::INTEGER AS len FROM (SELECT DISTINCT start_cell, end_cell FROM h), range(1, 33)),
hist AS (SELECT dom.start_cell, dom.end_cell, dom.len, greatest(0, coalesce(c, 0) + {laplace(4.0, 'length', 'dom.start_cell', 'dom.end_cell', 'dom.len')}) AS n FROM dom LEFT JOIN h ON h.start_cell = dom.start_cell AND h.end_cell = dom.end_cell AND h.len = dom.len),
tot AS (SELECT *, sum(n) OVER w AS total, coalesce(sum(n * len) OVER w / nullif(sum(n) OVER w, 0), 1) AS mean FROM hist WINDOW w AS (PARTITION BY start_cell, end_cell)),
laws AS (SELECT *, CASE WHEN len <= least(32, greatest(1, round(2 * mean - 1))) THEN 1.0 / least(32, greatest(1, round(2 * mean - 1))) ELSE 0 END AS u,
  exp((len - 1) * ln(greatest(mean - 1, 1e-9)) - greatest(mean - 1, 1e-9) - lgamma(len)) AS p, exp(-(len - 1) / greatest(mean, 1e-9)) - exp(-len / greatest(mean, 1e-9)) AS x FROM tot),
expected AS (SELECT start_cell, end_cell, len, n, total, mean, total * coalesce(u / nullif(sum(u) OVER w, 0), 0) AS uniform, total * coalesce(p / nullif(sum(p) OVER w, 0), 0) AS poisson,
  total * coalesce(x / nullif(sum(x) OVER w, 0), 0) AS exponential FROM laws WINDOW w AS (PARTITION BY start_cell, end_cell)) """

BEST = """, fit AS (SELECT start_cell, end_cell, any_value(mean) AS mean, round(sum((n - uniform) ** 2 / greatest(uniform, 0.5)), 9) AS a, round(sum((n - poisson) ** 2 / greatest(poisson, 0.5)), 9) AS b,
  round(sum((n - exponential) ** 2 / greatest(exponential, 0.5)), 9) AS c FROM expected GROUP BY 1, 2)
SELECT start_cell, end_cell, CASE WHEN a <= b AND a <= c THEN 'uniform' WHEN b <= c THEN 'poisson' ELSE 'exponential' END AS family, round(mean, 6) AS p1 FROM fit"""



def best_by(miss: dict[str, str]) -> str:
    """The law with the least misfit; ``miss``: its SQL per family over the rows of a pair."""
    return f""", gaps AS (SELECT *, {', '.join(f"abs(sum(n - {f}) OVER (PARTITION BY start_cell, end_cell ORDER BY len)) AS {f}_gap" for f in miss)} FROM expected),
fit AS (SELECT start_cell, end_cell, any_value(mean) AS mean, {', '.join(f"coalesce(round({sql}, 9), 0) AS m_{f}" for f, sql in miss.items())} FROM gaps GROUP BY 1, 2)
SELECT start_cell, end_cell, CASE WHEN m_uniform <= m_poisson AND m_uniform <= m_exponential THEN 'uniform' WHEN m_poisson <= m_exponential THEN 'poisson' ELSE 'exponential' END AS family, round(mean, 6) AS p1 FROM fit"""


FAMILIES = ("uniform", "poisson", "exponential")
BEST_KS = best_by({f: f"max({f}_gap) / nullif(any_value(total), 0)" for f in FAMILIES})
BEST_LOGLIK = best_by({f: f"-sum(n * ln(greatest({f} / nullif(total, 0), 1e-9)))" for f in FAMILIES})
MOMENTS = GRID6 + f""", s AS (SELECT start_cell, end_cell, count(*)::DOUBLE AS k, sum(least(n, 32))::DOUBLE AS s FROM trips6 GROUP BY 1, 2)
SELECT start_cell, end_cell, round(greatest(1, least(32, (s + {laplace(132.0, 'length-s', 'start_cell', 'end_cell')}) / greatest(1, k + {laplace(132.0, 'length-k', 'start_cell', 'end_cell')}))), 6) AS mean FROM s"""

#: Draws of a whole release: as many as the noisy masses sum to.
RELEASED = TRIPS + """, size AS (SELECT round(sum(mass))::BIGINT AS n FROM noisy_trips WHERE prob > 0),
upto AS (SELECT start_cell, end_cell, prob, sum(prob) OVER (ORDER BY start_cell, end_cell ROWS UNBOUNDED PRECEDING) AS up, sum(prob) OVER () AS al FROM noisy_trips WHERE prob > 0),
iv AS (SELECT start_cell, end_cell, round((up - prob) / al, 12) AS lo, round(up / al, 12) AS hi FROM upto) """
QUOTA = RELEASED + """, share AS (SELECT start_cell, end_cell, round(lo * n)::BIGINT AS a, round(hi * n)::BIGINT AS b FROM iv, size)
SELECT unnest(range(a, b)) AS trace_id, start_cell, end_cell FROM share WHERE b > a"""
RELEASE_DRAWS = RELEASED + f""", ids AS (SELECT range, {uniform('draw', 'range')} AS u FROM range(0, (SELECT n FROM size)))
SELECT range AS trace_id, start_cell, end_cell FROM ids JOIN iv ON u >= lo AND (u < hi OR hi >= 0.999999999999)"""

#: Whether the part of a step inside both slabs of a rectangle is not empty.
def _slab(a: str, b: str, low: str, high: str) -> tuple[str, str]:
    inside, d = f"{a} >= {low} AND {a} < {high}", f"nullif({b} - {a}, 0)"
    return f"coalesce(least(({low} - {a}) / {d}, ({high} - {a}) / {d}), CASE WHEN {inside} THEN 0 ELSE 2 END)", f"CASE WHEN {b} = {a} THEN CASE WHEN {inside} THEN 1 ELSE -1 END ELSE greatest(({low} - {a}) / {d}, ({high} - {a}) / {d}) END"


def segment_counts(regions: str) -> str:
    (a0, a1), (b0, b1) = _slab("x", "nx", "x0", "x1"), _slab("y", "ny", "y0", "y1")
    return regions + f""", {_DRIFT}, steps AS (SELECT trace_id, x, y, lead(x) OVER w AS nx, lead(y) OVER w AS ny FROM drift_trips WINDOW w AS (PARTITION BY trace_id ORDER BY seq))
SELECT qid, count(DISTINCT trace_id) AS n FROM steps JOIN regions ON (x >= x0 AND x < x1 AND y >= y0 AND y < y1) OR (nx IS NOT NULL AND greatest({a0}, {b0}, 0.0) <= least({a1}, {b1}, 1.0)) GROUP BY 1"""


def _region_uniform(i: int) -> str:
    text = f"'{SEED}|region|' || range::VARCHAR || '-{i}'"
    return f"round((('0x' || substr(md5({text}), 1, 12))::UBIGINT + 0.5) / 281474976710656.0, 9)"


REGIONS = f"""WITH us AS (SELECT range::INTEGER AS qid, {_region_uniform(1)} AS a, {_region_uniform(2)} AS b, {_region_uniform(3)} AS c, {_region_uniform(4)} AS d FROM range(200)),
corner AS (SELECT qid, least(least(a, b), 0.95) AS x0, greatest(a, b) AS xm, least(least(c, d), 0.95) AS y0, greatest(c, d) AS ym FROM us),
regions AS (SELECT qid, x0, greatest(xm, x0 + 0.05) AS x1, y0, greatest(ym, y0 + 0.05) AS y1 FROM corner) """

#: The same corners over the extent of a table.
TABLE_REGIONS = REGIONS + """, extent AS (SELECT min(l_extendedprice) AS lx, max(l_extendedprice) AS hx, min(l_quantity) AS ly, max(l_quantity) AS hy FROM lineitem WHERE l_extendedprice IS NOT NULL AND l_quantity IS NOT NULL)
SELECT qid, round(lx + x0 * (hx - lx), 6) AS x0, round(lx + x1 * (hx - lx), 6) AS x1, round(ly + y0 * (hy - ly), 6) AS y0, round(ly + y1 * (hy - ly), 6) AS y1 FROM regions, extent"""

#: The largest share of one trace in each statistic, counted on the leaves.
LEDGER = LEAF + """, one AS (SELECT trace_id, sum(1.0 / n) AS g, CASE WHEN max(n) > 1 THEN sum(CASE WHEN seq > 1 THEN 1.0 / (n - 1) ELSE 0 END) END AS m FROM leaf GROUP BY 1),
seen AS (SELECT coalesce(max(g), 0) AS g, coalesce(max(m), 0) AS m, coalesce(max(1), 0)::DOUBLE AS t, count(*) AS traces, count(m) AS moving FROM one)
SELECT 'grid' AS stage, 'laplace' AS mechanism, round(g, 6) AS sensitivity, 0.25::DOUBLE AS epsilon, 'sequential' AS composition, traces FROM seen
UNION ALL SELECT 'mobility', 'laplace', round(m, 6), 0.25, 'sequential', moving FROM seen UNION ALL SELECT 'trips', 'laplace', t, 0.25, 'sequential', traces FROM seen
UNION ALL SELECT 'lengths', 'laplace', t, 0.125, 'parallel', traces FROM seen UNION ALL SELECT 'length pool', 'laplace', t, 0.125, 'sequential', traces FROM seen
UNION ALL SELECT 'generator', 'post-processing', 0.0, 0.0, 'free', 0 FROM seen"""

SEGMENTS = segment_counts(REGIONS)
QUERY_ERROR = """, hit AS (SELECT qid, count(DISTINCT trace_id) AS a, count(DISTINCT trace_id) FILTER (WHERE trace_id % 2 = 0) AS b FROM drift_trips JOIN regions ON x >= x0 AND x < x1 AND y >= y0 AND y < y1 GROUP BY 1)
SELECT 'query_error' AS metric, round(avg(abs(coalesce(a, 0) - coalesce(b, 0)) / greatest(coalesce(a, 0), 0.01 * (SELECT count(DISTINCT trace_id) FROM drift_trips))), 6) AS value FROM regions LEFT JOIN hit USING (qid)"""


def grams(rows: str, trace: str, order: str) -> str:
    return f""", seqs AS (SELECT {trace} AS trace_id, list(cell ORDER BY {order}) AS c FROM {rows} GROUP BY 1),
grams AS (SELECT trace_id, array_to_string(list_transform(c[i:i + k - 1], lambda v: v::VARCHAR), '>') AS pattern FROM seqs, range(2, 9) AS a(k), unnest(range(1, greatest(1, len(c) - k + 2))) AS b(i) WHERE len(c) >= k) """


PATTERNS = GRID6 + grams("cells6", "trace_id", "seq") + ", supports AS (SELECT pattern, count(*) AS support FROM grams GROUP BY 1) "


def jsd(name: str, on: str) -> str:
    half = lambda x, y: f"(CASE WHEN {x} > 0 THEN 0.5 * {x} * log2(2 * {x} / ({x} + {y})) ELSE 0 END)"
    return f""", twoway AS (SELECT coalesce(p.m, 0) / (SELECT sum(m) FROM p) AS x, coalesce(q.m, 0) / (SELECT sum(m) FROM q) AS y FROM p FULL JOIN q ON {on})
SELECT '{name}' AS metric, round(sum({half('x', 'y')} + {half('y', 'x')}), 6) AS value FROM twoway"""


#: A cell is written between bars, so a pattern's cells in order match bar by bar.
GAPPED = PATTERNS + """, mined AS (SELECT pattern FROM supports ORDER BY support DESC, pattern LIMIT 100), told AS (SELECT trace_id, '|' || array_to_string(c, '||') || '|' AS t FROM seqs)
SELECT pattern, count(*) AS support FROM mined JOIN told ON t LIKE '%|' || replace(pattern, '>', '|%|') || '|%' GROUP BY 1"""

DISTANCES = view("drift_trips") + """, dist AS (SELECT trace_id, round(coalesce(sum(step ORDER BY seq), 0), 9) AS d FROM (SELECT trace_id, seq, sqrt((x - lag(x) OVER w) ** 2 + (y - lag(y) OVER w) ** 2) AS step FROM drift_trips WINDOW w AS (PARTITION BY trace_id ORDER BY seq)) GROUP BY 1),
hist AS (SELECT trace_id, least(floor(d / ((SELECT max(d) FROM dist) / 20)), 19)::INTEGER AS bucket FROM dist) """

RANKING = GRID6 + """, a AS (SELECT cell, row_number() OVER (ORDER BY count(*) DESC, cell) AS rank FROM cells6 GROUP BY cell), b AS (SELECT cell, row_number() OVER (ORDER BY count(*) DESC, cell) AS rank FROM cells6 WHERE trace_id % 2 = 0 GROUP BY cell),
m AS (SELECT row_number() OVER (ORDER BY a.rank) AS ra, row_number() OVER (ORDER BY b.rank) AS rb FROM a JOIN b USING (cell)),
k AS (SELECT count(*) FILTER (WHERE s.rb < r.rb) / count(*) AS v FROM m r JOIN m s ON r.ra < s.ra), n AS (SELECT count(*)::DOUBLE AS n, sum((ra - rb) ** 2) AS d FROM m)
SELECT 'kendall_distance' AS metric, round(v, 6) AS value FROM k UNION ALL SELECT 'spearman_distance', round(6 * d / (n * (n * n - 1)), 6) FROM n
UNION ALL SELECT 'topk_miss', round(1 - (SELECT count(*) FROM a JOIN b USING (cell) WHERE a.rank <= 10 AND b.rank <= 10) / (SELECT count(*) FROM a WHERE rank <= 10), 6)"""

TRAVEL = view("drift_trips") + f""", ab AS (SELECT trace_id, arg_min(c, seq) AS a, arg_max(c, seq) AS b, arg_min(ts, seq)::DATE AS day, (epoch_us(arg_max(ts, seq)) - epoch_us(arg_min(ts, seq))) / 1e6 AS secs FROM (SELECT *, {cell('x', 'y', 6)} AS c FROM drift_trips) GROUP BY 1),
steps AS (SELECT trace_id, {cell('x', 'y', 6)} AS a, CASE WHEN epoch_us(lead(ts) OVER w) > epoch_us(ts) THEN sqrt((lead(x) OVER w - x) ** 2 + (lead(y) OVER w - y) ** 2) / ((epoch_us(lead(ts) OVER w) - epoch_us(ts)) / 1e6) END AS v FROM drift_trips WINDOW w AS (PARTITION BY trace_id ORDER BY seq)) """

VISIT_CHANGE = """WITH v AS (SELECT event_type AS c, ts::DATE AS day, count(*) AS n, count(*) FILTER (WHERE user_id % 2 = 0) AS h FROM events GROUP BY 1, 2), r AS (SELECT c, n AS rn, h AS rh FROM v WHERE day = DATE '2024-01-02')
SELECT 'visit_change_error' AS metric, round(avg(abs(100.0 * (n - rn) / rn - 100.0 * (h - rh) / rh)), 6) AS value FROM v JOIN r USING (c) WHERE h > 0 AND rh > 0"""

HEATMAP = view("drift_trips") + f"SELECT {axis('x', 0, 1, 10)} AS bx, {axis('y', 0, 1, 10)} AS \"by\", count(*) AS n_real, count(*) FILTER (WHERE trace_id % 2 = 0) AS n_syn FROM drift_trips GROUP BY 1, 2"

SESSIONS = """WITH f AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 6 HOURS THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM f)
SELECT user_id, min(ts)::TIMESTAMP AS first_ts, max(ts)::TIMESTAMP AS last_ts, count(*) AS n FROM s GROUP BY user_id, sid"""

ASOF = view("user_long") + """, sec AS (SELECT trace_id, seq, x, y, floor(epoch_us(ts) / 1000000)::BIGINT AS s FROM user_long), span AS (SELECT trace_id, (ceil(arg_min(s, seq) / 21600.0) * 21600)::BIGINT AS a, arg_max(s, seq) AS b FROM sec GROUP BY 1),
g AS (SELECT trace_id, unnest(range(a, b + 1, 21600)) AS g FROM span)
SELECT g.trace_id, make_timestamp(g.g * 1000000) AS at, round(arg_max(x, seq), 6) AS x, round(arg_max(y, seq), 6) AS y FROM g JOIN sec ON sec.trace_id = g.trace_id AND sec.s <= g.g GROUP BY 1, 2"""


def bulk_weights(n: int = 40):
    """Candidates whose trip share runs from 0.05 to 0.83."""
    import numpy as np

    w3 = 0.05 + 0.02 * np.arange(n)
    return np.stack([(1 - w3) / 3, (1 - w3) / 3, w3, (1 - w3) / 3], axis=1)


BULK = GRID6 + f""", cnt AS (SELECT start_cell AS s, end_cell AS e, count(*)::DOUBLE AS c FROM trips6 GROUP BY 1, 2),
base AS (SELECT a.range AS s, b.range AS e, coalesce(c, 0) AS c, {laplace(1.0, 'trip', 'a.range', 'b.range')} AS unit FROM range(36) a CROSS JOIN range(36) b LEFT JOIN cnt ON cnt.s = a.range AND cnt.e = b.range),
raw AS (SELECT v.range::INTEGER AS eval_id, s, e, c, c + unit / (0.05 + 0.02 * v.range) AS m FROM base, range(40) v),
ranked AS (SELECT eval_id, m, row_number() OVER (PARTITION BY eval_id ORDER BY m DESC) AS i, sum(m) OVER (PARTITION BY eval_id ORDER BY m DESC ROWS UNBOUNDED PRECEDING) AS up, sum(m) OVER (PARTITION BY eval_id) AS total FROM raw),
lev AS (SELECT eval_id, arg_max((up - total) / i, i) AS level FROM ranked WHERE m > (up - total) / i GROUP BY 1),
clean AS (SELECT eval_id, c, greatest(0, m - level) AS m FROM raw JOIN lev USING (eval_id)),
sides AS (SELECT eval_id, c / sum(c) OVER (PARTITION BY eval_id) AS x, m / sum(m) OVER (PARTITION BY eval_id) AS y FROM clean)
SELECT eval_id, round(sum((CASE WHEN x > 0 THEN 0.5 * x * log2(2 * x / (x + y)) ELSE 0 END) + (CASE WHEN y > 0 THEN 0.5 * y * log2(2 * y / (x + y)) ELSE 0 END)), 6) AS value FROM sides GROUP BY 1"""
