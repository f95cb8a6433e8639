"""SQL texts, for another engine, that give the rows of the queries. Built from common table expressions."""

from __future__ import annotations

ROW_ORDER = "l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey"
HISTORY_ORDER = "l_partkey, l_suppkey, l_orderkey, l_linenumber, l_shipdate"
MEASURES = (("l_quantity", "25.5", "14.43"), ("l_extendedprice", "53000.0", "30100.0"), ("l_discount", "0.05", "0.02905"), ("l_tax", "0.04", "0.02348"))


def panel(name: str, g: float, sensors: int = 48, keep: int | None = None, history: bool = False, drift: float = 0.0) -> str:
    """name(n, m, x) of the calibrated panel, only sensors below keep."""
    rows = -(-sensors // 4)
    order = HISTORY_ORDER if history else ROW_ORDER
    parts = " UNION ALL ".join(f"SELECT r, {k} AS k, (CAST({c} AS DOUBLE) - {mid}) / {spread} AS z FROM {name}_r" for k, (c, mid, spread) in enumerate(MEASURES))
    back = f" - (c // {rows})" if history else ""
    rise = f" + CAST({drift} AS DOUBLE) * n * m / {sensors}" if drift else ""
    return f"""{name}_r AS (SELECT row_number() OVER (ORDER BY {order}) - 1 AS r, * FROM lineitem),
{name}_z AS (SELECT r // {rows} + 1{back} AS n, CAST((r % {rows}) * 4 + k AS INTEGER) AS m, z FROM ({parts}) a, (SELECT count(*) AS c FROM lineitem) b WHERE r // {rows} < c // {rows}),
{name} AS (SELECT n, m, z + CAST({g} AS DOUBLE) * m + 1.5 * sin(2 * pi() * n / (200 + 17 * m)){rise} AS x FROM {name}_z WHERE m < {keep or sensors})"""


def models(source: str = "hist") -> str:
    return f"models AS (SELECT m, count(*) AS cnt, avg(x) AS mu, stddev_samp(x) AS sigma, min(x) AS lo, max(x) AS hi FROM {source} GROUP BY m)"


def chebyshev(x: str, mu: str = "mu", sigma: str = "sigma") -> str:
    z = f"(({x} - {mu}) / {sigma})"
    return f"(CASE WHEN abs{z} <= 1 THEN 1.0 ELSE 1 / ({z} * {z}) END)"


def example(g: float = 3.0) -> str:
    """clean, bad (corrupted) and models of the five-sensor example, and span(l, r)."""
    return f"""{panel("hist", g, 48, 5, True)},
{panel("clean", g, 48, 5)},
span AS (SELECT CAST(floor(max(n) * 3 / 5.0) AS BIGINT) AS l, CAST(floor(max(n) * 4 / 5.0) AS BIGINT) AS r, max(n) AS last FROM clean),
bad AS (SELECT p.n, p.m, q.x FROM clean p CROSS JOIN span JOIN clean q ON p.n = q.n AND q.m = CASE WHEN p.n BETWEEN l AND r THEN (CASE p.m WHEN 0 THEN 1 WHEN 1 THEN 0 WHEN 2 THEN 4 WHEN 4 THEN 2 ELSE p.m END) ELSE p.m END),
{models()}"""


FLAGS = f"""flags AS (SELECT n, bad.m, x FROM bad JOIN models USING (m) WHERE {chebyshev("x")} < 0.12),
sets AS (SELECT n, list(m ORDER BY m) AS ab, count(*) AS a FROM flags GROUP BY n)"""

WEIGHTS = f"""edges AS (SELECT f.n, f.m AS u, o.m AS v, {chebyshev("f.x", "models.mu", "models.sigma")} AS w
  FROM flags f JOIN sets USING (n) JOIN flags o ON o.n = f.n JOIN models ON models.m = o.m WHERE a >= 2)"""

MATCH = """paths AS (
  SELECT n, ab, 0 AS k, [] :: INTEGER[] AS dst, 0.0 :: DOUBLE AS total FROM sets WHERE a >= 2
  UNION ALL
  SELECT p.n, p.ab, p.k + 1, list_append(p.dst, e.v), p.total + e.w FROM paths p JOIN edges e ON e.n = p.n AND e.u = p.ab[p.k + 1] WHERE NOT list_contains(p.dst, e.v)
),
matched AS (SELECT n, ab AS src, dst, total FROM (SELECT *, row_number() OVER (PARTITION BY n ORDER BY round(total, 12) DESC, dst) AS nth FROM paths WHERE k = len(ab)) WHERE nth = 1)"""

CYCLES = """walks AS (
  SELECT n, src, dst, u AS start, [u] AS walk, dst[list_position(src, u)] AS nxt FROM (SELECT n, src, dst, unnest(src) AS u FROM matched)
  UNION ALL
  SELECT n, src, dst, start, list_append(walk, nxt), dst[list_position(src, nxt)] FROM walks WHERE nxt <> start
),
cyc AS (SELECT n, array_to_string(walk, '>') AS sigma, walk FROM walks WHERE nxt = start AND len(walk) > 1 AND list_min(walk) = start)"""

UNITS = "units AS (SELECT sigma, count(*) AS size, min(n) AS first, max(n) AS last FROM cyc GROUP BY sigma)"


def runs(ones: str, name: str = "runs") -> str:
    """1-runs (sigma, l, r) of ones(sigma, n)."""
    return f"{name} AS (SELECT sigma, min(n) AS l, max(n) AS r FROM (SELECT sigma, n, n - row_number() OVER (PARTITION BY sigma ORDER BY n) AS g FROM {ones}) GROUP BY sigma, g)"


def two_pass(source: str, last: str, theta: float = 0.3, len2: int = 20, mode: str = "guarded") -> str:
    """smooth(sigma, l, r) of 1-runs; last: a scalar expression."""
    guard = f"AND len < {len2}" if mode == "guarded" else ""
    return f"""gaps AS (SELECT *, r - l + 1 AS len, l - lag(r) OVER w - 1 AS gap, lag(r - l + 1) OVER w AS plen FROM {source} WINDOW w AS (PARTITION BY sigma ORDER BY l)),
filled AS (SELECT sigma, min(l) AS l, max(r) AS r FROM (
  SELECT *, sum(CASE WHEN gap < {theta} * (len + plen) THEN 0 ELSE 1 END) OVER (PARTITION BY sigma ORDER BY l ROWS UNBOUNDED PRECEDING) AS g FROM gaps) GROUP BY sigma, g),
around AS (SELECT *, r - l + 1 AS len, l - coalesce(lag(r) OVER w, 0) - 1 AS before, coalesce(lead(l) OVER w, {last} + 1) - r - 1 AS after FROM filled WINDOW w AS (PARTITION BY sigma ORDER BY l)),
smooth AS (SELECT sigma, l, r FROM around WHERE NOT (before > 0 AND after > 0 AND len < {theta} * (before + after) {guard}))"""


GREEDY_PICK = """pick AS (
  SELECT n, 0 AS k, [] :: INTEGER[] AS us, [] :: INTEGER[] AS vs, 0.0 :: DOUBLE AS total, a FROM sets WHERE a >= 2
  UNION ALL
  SELECT n, k + 1, list_append(us, u), list_append(vs, v), total + w, a FROM (
    SELECT p.*, e.u, e.v, e.w, row_number() OVER (PARTITION BY p.n ORDER BY e.w DESC, e.u, e.v) AS nth
    FROM pick p JOIN edges e ON e.n = p.n WHERE p.k < p.a AND NOT list_contains(p.us, e.u) AND NOT list_contains(p.vs, e.v)) WHERE nth = 1
),
done AS (SELECT n, total, unnest(us) AS u, unnest(vs) AS v FROM pick WHERE k = a)"""

GREEDY = f"{GREEDY_PICK},\nmatched AS (SELECT n, list(u ORDER BY u) AS src, list(v ORDER BY u) AS dst, any_value(total) AS total FROM done GROUP BY n)"


def full(match: str = MATCH, base: str | None = None, rows: str = "bad", last: str = "(SELECT last FROM span)", len1: str = "20", len2: str = "20") -> str:
    """Down to intervals(sigma, l, r). rows: the table of readings; len2 must be a scalar expression."""
    return f"""{base or example()},
{FLAGS.replace("FROM bad", f"FROM {rows}").replace("bad.m", f"{rows}.m")},
{WEIGHTS},
{match},
{CYCLES},
{UNITS},
kept AS (SELECT * FROM units WHERE size >= {len1}),
ones AS (SELECT sigma, n FROM cyc SEMI JOIN kept USING (sigma)),
{runs("ones")},
{two_pass("runs", last, len2=len2)},
intervals AS (SELECT * FROM smooth WHERE r - l + 1 >= {len2})"""


FULL = full()

OVERLAY = """cuts AS (SELECT DISTINCT unnest([l, r + 1]) AS l FROM intervals), pieces AS (SELECT l, lead(l) OVER (ORDER BY l) - 1 AS r FROM cuts),
cover AS (SELECT p.l, p.r, string_agg(sigma, '|' ORDER BY CAST(string_split(sigma, '>') AS INTEGER[])) AS phi FROM pieces p JOIN intervals i ON i.l <= p.r AND p.l <= i.r GROUP BY p.l, p.r),
grp AS (SELECT *, sum(CASE WHEN pr + 1 = l AND pp = phi THEN 0 ELSE 1 END) OVER (ORDER BY l ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT *, lag(r) OVER (ORDER BY l) AS pr, lag(phi) OVER (ORDER BY l) AS pp FROM cover)),
final AS (SELECT min(l) AS l, max(r) AS r, any_value(phi) AS phi FROM grp GROUP BY g)"""

#: Runs of points with one and the same candidate.
AS_FOUND = f"""{example()}, {FLAGS}, {WEIGHTS}, {MATCH}, {CYCLES},
cand AS (SELECT n, string_agg(sigma, '|' ORDER BY walk) AS phi FROM cyc GROUP BY n),
final AS (SELECT min(n) AS l, max(n) AS r, phi FROM (SELECT n, phi, n - row_number() OVER (PARTITION BY phi ORDER BY n) AS g FROM cand) GROUP BY phi, g)"""


def block(value: str = "avg(x)") -> str:
    """The example in blocks of the rounded-up square root of its points, judged whole."""
    length = "(SELECT len FROM size)"
    base = f"""{example()}, size AS (SELECT CAST(ceil(floor(sqrt(last) * 1000) / 1000) AS BIGINT) AS len FROM span),
blocked AS (SELECT CAST((n - 1) // {length} + 1 AS BIGINT) AS n, m, {value} AS x FROM bad GROUP BY 1, 2)"""
    few = f"CAST(ceil(20.0 / {length}) AS BIGINT)"
    inner = full(base=base, rows="blocked", last="(SELECT max(n) FROM blocked)", len1=few, len2=few)
    return f"{inner}, {OVERLAY.replace('final AS', 'whole AS')}, final AS (SELECT CAST((l - 1) * {length} + 1 AS BIGINT) AS l, CAST(least(r * {length}, (SELECT last FROM span)) AS BIGINT) AS r, phi FROM whole)"


#: final(l, r, phi) of each method on the example, where no two kept cycles share a sensor (with the last reading of a
#: block as its value two do, so that variant has no text here).
METHODS = {"full": f"{FULL}, {OVERLAY}", "greedy": f"{full(GREEDY)}, {OVERLAY}", "candidate": AS_FOUND, "block": block(), "block_median": block("median(x)")}


def scores(method: str) -> str:
    """One row of counts and measures of a method on the example, whose truth is one interval."""
    return f"""(WITH RECURSIVE {METHODS[method]},
same AS (SELECT f.*, (least(f.r, s.r) - greatest(f.l, s.l) + 1.0) / (greatest(f.r, s.r) - least(f.l, s.l) + 1) AS iou FROM final f, span s),
best AS (SELECT * FROM same WHERE iou >= 0.5 ORDER BY iou DESC, l LIMIT 1),
c AS (SELECT (SELECT count(*) FROM final) AS f, CAST(1 AS BIGINT) AS t, (SELECT count(*) FROM best) AS ok, (SELECT count(*) FROM best WHERE phi = '0>1|2>4') AS fixed)
SELECT '{method}' AS method, f AS n_found, t AS n_true, ok AS n_correct, fixed AS n_repaired, ok / nullif(f, 0) AS p_d, ok / t AS r_d, fixed / nullif(ok, 0) AS p_r, fixed / nullif(f, 0) AS r_r, fixed / nullif(f, 0) AS p_r_alt, fixed / nullif(ok, 0) AS r_r_alt FROM c)"""


def with_(ctes: str, select: str, recursive: bool = True) -> str:
    return f"WITH {'RECURSIVE ' if recursive else ''}{ctes}\n{select}"
