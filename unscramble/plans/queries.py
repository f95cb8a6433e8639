"""Queries of the repair engine on the given tables: the method's own steps, variants, baselines, measures, workloads."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.config import RepairConfig, as_printed
from unscramble.functions import perm
from unscramble.operators import candidates, detect, determine, matching, metrics, model, runs, units
from unscramble.plans import methods, oracle, workloads
from unscramble.scratch import scratch_path, stored
from unscramble.sources import inject, panels
from unscramble.sources.tables import read_table, write_escalations

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable:
    def put(f: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def r6(c: str, name: str | None = None):
    return F.round(F.col(c), 6).alias(name or c)


class Example:
    """The five-sensor example, each part made when asked for."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.clean = stored(panels.example_panel(spark, sf_dir), "clean")
        self.history = panels.example_panel(spark, sf_dir, history=True)
        self.last = inject.extent(self.clean)
        self.truth = inject.example_plan(self.last)
        self.bad = stored(inject.inject(self.clean, self.truth), "bad")
        self.models = stored(model.fit_moments(self.history), "models")
        self.cfg = RepairConfig(match="enum")

    def flags(self) -> DataFrame:
        return detect.flag(self.bad, self.models)

    def weighted(self) -> DataFrame:
        return candidates.gate(self.flags()).withColumn("w", matching.weights())

    def candidates(self) -> DataFrame:
        return candidates.candidate_schemas(self.bad, self.models, self.cfg)


# --- panels, injection ------------------------------------------------------------------------------------------


@query(
    "panel_calibrated_stats",
    oracle.with_(oracle.panel("p", 2.0), "SELECT m, count(*) AS cnt, round(min(x), 6) AS lo, round(max(x), 6) AS hi, round(avg(x), 6) AS mean FROM p GROUP BY m"),
)
def panel_calibrated_stats(spark, sf_dir):
    long = panels.to_long(panels.calibrated_panel(spark, sf_dir, 2.0))
    return long.groupBy("m").agg(F.count("*").alias("cnt"), F.round(F.min("x"), 6).alias("lo"), F.round(F.max("x"), 6).alias("hi"), F.round(F.avg("x"), 6).alias("mean"))


@query(
    "panel_wide_stats",
    oracle.with_(oracle.panel("p", 2.0, 150), "SELECT m, count(*) AS cnt, round(min(x), 6) AS lo, round(max(x), 6) AS hi, round(avg(x), 6) AS mean FROM p GROUP BY m"),
)
def panel_wide_stats(spark, sf_dir):
    long = panels.to_long(panels.calibrated_panel(spark, sf_dir, 2.0, 150))
    return long.groupBy("m").agg(F.count("*").alias("cnt"), F.round(F.min("x"), 6).alias("lo"), F.round(F.max("x"), 6).alias("hi"), F.round(F.avg("x"), 6).alias("mean"))


@query("panel_drift_stats", oracle.with_(oracle.panel("p", 2.0, drift=0.001), "SELECT m, round(avg(x), 6) AS mean, round(stddev_samp(x), 6) AS sd FROM p GROUP BY m"))
def panel_drift_stats(spark, sf_dir):
    long = panels.to_long(panels.calibrated_panel(spark, sf_dir, 2.0, drift=0.001))
    return long.groupBy("m").agg(F.round(F.avg("x"), 6).alias("mean"), F.round(F.stddev_samp("x"), 6).alias("sd"))


@query(
    "panel_equipments",
    "WITH r AS (SELECT CAST(l_suppkey % 4 AS BIGINT) AS eq_id FROM lineitem) SELECT eq_id, CAST(count(*) // 12 AS BIGINT) AS points FROM r GROUP BY eq_id HAVING count(*) >= 12",
)
def panel_equipments(spark, sf_dir):
    p = panels.calibrated_panel(spark, sf_dir, 2.0, equipments=4)
    return p.groupBy("eq_id").agg(F.count("*").alias("points"))


_PLAN_SQL = """WITH b AS (SELECT count(*) // 12 AS last FROM lineitem), c AS (SELECT last, greatest(3, last // 500) AS cnt FROM b),
k AS (SELECT last, cnt, unnest(range(cnt)) AS k FROM c),
i AS (SELECT k, (k * last) // cnt + last // (3 * cnt) + 1 AS l, greatest(least([60, 90, 140, 200][k % 4 + 1], last // (2 * cnt)), 1) AS len FROM k),
s AS (SELECT k, l, l + len - 1 AS r, list_transform(range(12), lambda j: (7 * k + 5 * j) % 48) AS s FROM i),
parts AS (SELECT k, l, r, unnest([s[1:2], s[3:5], s[6:7], s[8:12]]) AS c FROM s),
rot AS (SELECT k, l, r, list_position(c, list_min(c)) AS p, c FROM parts),
canon AS (SELECT k, l, r, list_concat(c[p:], c[1:p - 1]) AS c FROM rot)
SELECT CAST(k AS BIGINT) AS k, CAST(l AS BIGINT) AS l, CAST(r AS BIGINT) AS r, string_agg(array_to_string(c, '>'), '|' ORDER BY c) AS phi FROM canon GROUP BY k, l, r"""


@query("inject_truth", _PLAN_SQL)
def inject_truth(spark, sf_dir):
    truth = inject.plan(inject.extent(panels.calibrated_panel(spark, sf_dir)))
    return truth.select("k", "l", "r", perm.cycles_key(F.col("phi")).alias("phi"))


@query("injected_cells", oracle.with_(oracle.example(), "SELECT bad.n, bad.m, round(bad.x, 6) AS x FROM bad JOIN clean USING (n, m) WHERE bad.x <> clean.x"))
def injected_cells(spark, sf_dir):
    e = Example(spark, sf_dir)
    both = panels.to_long(e.bad).alias("b").join(panels.to_long(e.clean).select("n", "m", F.col("x").alias("t")), ["n", "m"])
    return both.filter("x <> t").select("n", "m", r6("x"))


# --- models -----------------------------------------------------------------------------------------------------

_HIST = oracle.panel("hist", 2.0, history=True)


@query("models_moments", oracle.with_(f"{_HIST}, {oracle.models()}", "SELECT m, cnt, round(mu, 6) AS mu, round(sigma, 6) AS sigma, round(lo, 6) AS lo, round(hi, 6) AS hi FROM models"))
def models_moments(spark, sf_dir):
    fit = model.fit_moments(panels.calibrated_panel(spark, sf_dir, history=True))
    return fit.select("m", "cnt", *map(r6, ("mu", "sigma", "lo", "hi")))


_ROBUST = "mid AS (SELECT m, median(x) AS mu, quantile_cont(x, 0.25) AS q1, quantile_cont(x, 0.75) AS q3 FROM hist GROUP BY m), mad AS (SELECT m, median(abs(x - mu)) * 1.4826 AS sigma FROM hist JOIN mid USING (m) GROUP BY m)"


@query("models_robust", oracle.with_(f"{_HIST}, {_ROBUST}", "SELECT m, round(mu, 6) AS mu, round(sigma, 6) AS sigma, round(q1, 6) AS q1, round(q3, 6) AS q3 FROM mid JOIN mad USING (m)"))
def models_robust(spark, sf_dir):
    return model.fit_robust(panels.calibrated_panel(spark, sf_dir, history=True)).select("m", *map(r6, ("mu", "sigma", "q1", "q3")))


@query("models_robust_approx")
def models_robust_approx(spark, sf_dir):
    return model.fit_robust(panels.calibrated_panel(spark, sf_dir, history=True), True).select("m", *map(r6, ("mu", "sigma", "q1", "q3")))


@query(
    "models_hist",
    oracle.with_(
        f"{_HIST}, {oracle.models()}, b AS (SELECT m, least(CAST(floor((x - lo) / (hi - lo) * 20) AS INTEGER), 19) AS bin FROM hist JOIN models USING (m))",
        "SELECT m, bin, count(*) AS c FROM b GROUP BY m, bin",
    ),
)
def models_hist(spark, sf_dir):
    fit = model.fit_hist(panels.calibrated_panel(spark, sf_dir, history=True))
    return fit.select("m", "cnt", F.posexplode("hist").alias("bin", "share")).filter("share > 0").select("m", "bin", F.round(F.col("share") * F.col("cnt")).cast("long").alias("c"))


_AR1 = """pairs AS (SELECT m, x, lag(x) OVER (PARTITION BY m ORDER BY n) AS p FROM hist), ok AS (SELECT * FROM pairs WHERE p IS NOT NULL),
fit AS (SELECT m, count(*) AS cnt, regr_slope(x, p) AS slope, avg(x) - regr_slope(x, p) * avg(p) AS intercept FROM ok GROUP BY m),
rest AS (SELECT m, stddev_samp(x - slope * p - intercept) AS sigma FROM ok JOIN fit USING (m) GROUP BY m)"""


@query("models_ar1", oracle.with_(f"{_HIST}, {_AR1}", "SELECT m, cnt, round(slope, 6) AS slope, round(intercept, 6) AS intercept, round(sigma, 6) AS sigma FROM fit JOIN rest USING (m)"))
def models_ar1(spark, sf_dir):
    return model.fit_ar1(panels.calibrated_panel(spark, sf_dir, history=True)).select("m", "cnt", *map(r6, ("slope", "intercept", "sigma")))


_FEATURES = """f AS (SELECT m, n, avg(x) OVER w AS f_mean, stddev_samp(x) OVER w AS f_sd, min(x) OVER w AS f_lo, max(x) OVER w AS f_hi, regr_slope(x, n) OVER w AS f_slope, count(*) OVER w AS c
  FROM hist WINDOW w AS (PARTITION BY m ORDER BY n ROWS BETWEEN 9 PRECEDING AND CURRENT ROW))"""


@query(
    "models_features",
    oracle.with_(f"{_HIST}, {_FEATURES}", "SELECT m, round(avg(f_mean), 5) AS f_mean_mu, round(avg(f_sd), 5) AS f_sd_mu, round(avg(f_slope), 5) AS f_slope_mu, round(avg(f_lo), 5) AS f_lo_mu, round(avg(f_hi), 5) AS f_hi_mu FROM f WHERE c = 10 GROUP BY m"),
)
def models_features(spark, sf_dir):
    fit = model.fit_features(panels.calibrated_panel(spark, sf_dir, history=True))
    return fit.select("m", *[F.round(f"{c}_mu", 5).alias(f"{c}_mu") for c in model.FEATURES])


_PROFILE = """g AS (SELECT m, sqrt(avg((x - mu) * (x - mu)) OVER (PARTITION BY m ORDER BY n ROWS BETWEEN 9 PRECEDING AND CURRENT ROW)) AS gap, mu FROM hist JOIN models USING (m))"""


@query("models_profile", oracle.with_(f"{_HIST}, {oracle.models()}, {_PROFILE}", "SELECT m, round(any_value(mu), 5) AS mu, round(avg(gap), 5) AS gap_mu, round(stddev_samp(gap), 5) AS gap_sigma FROM g GROUP BY m"))
def models_profile(spark, sf_dir):
    return model.fit_profile(panels.calibrated_panel(spark, sf_dir, history=True)).select("m", *[F.round(c, 5).alias(c) for c in ("mu", "gap_mu", "gap_sigma")])


@query("models_by_regime", "SELECT l_returnflag AS regime, count(*) AS cnt, round(avg(l_quantity), 6) AS mu, round(stddev_samp(l_quantity), 6) AS sigma FROM lineitem GROUP BY l_returnflag")
def models_by_regime(spark, sf_dir):
    return model.fit_moments(panels.native_panel(spark, sf_dir), regime=True).filter("m = 0").select("regime", "cnt", r6("mu"), r6("sigma"))


@query("models_merged", oracle.with_(f"{_HIST}, {oracle.models()}", "SELECT m, cnt, round(mu, 6) AS mu, round(sigma, 6) AS sigma FROM models"))
def models_merged(spark, sf_dir):
    """Two halves of the history, fitted apart and merged: the models of the whole."""
    h = panels.calibrated_panel(spark, sf_dir, history=True)
    return model.merge_moments(model.fit_moments(h.filter("n % 2 = 0")), model.fit_moments(h.filter("n % 2 <> 0"))).select("m", "cnt", r6("mu"), r6("sigma"))


@query("fit_sampled")
def fit_sampled(spark, sf_dir):
    return model.fit_moments(model.sampled(panels.calibrated_panel(spark, sf_dir, history=True), 5)).select("m", "cnt", r6("mu"), r6("sigma"))


@query(
    "exclude_known_bad",
    oracle.with_(oracle.example(), "SELECT m, count(*) AS cnt, round(avg(x), 6) AS mu, round(stddev_samp(x), 6) AS sigma FROM bad, span WHERE NOT n BETWEEN l AND r GROUP BY m"),
)
def exclude_known_bad(spark, sf_dir):
    e = Example(spark, sf_dir)
    return model.fit_moments(model.without_intervals(e.bad, e.truth.select("eq_id", "l", "r"))).select("m", "cnt", r6("mu"), r6("sigma"))


@query(
    "model_distance_matrix",
    oracle.with_(f"{_HIST}, {oracle.models()}", "SELECT a.m AS m_a, b.m AS m_b, round(abs(a.mu - b.mu) / sqrt((a.sigma * a.sigma + b.sigma * b.sigma) / 2), 6) AS distance FROM models a JOIN models b ON a.m < b.m"),
)
def model_distance_matrix(spark, sf_dir):
    return model.distances(model.fit_moments(panels.calibrated_panel(spark, sf_dir, history=True))).select("m_a", "m_b", r6("distance"))


# --- detection --------------------------------------------------------------------------------------------------

_TAIL = (-1.26551223, 1.00002368, 0.37409196, 0.09678418, -0.18628806, 0.27886807, -1.13520398, 1.48851587, -0.82215223, 0.17087277)


def _support_sql(family: str) -> str:
    z = "((x - mu) / sigma)"
    if family == "chebyshev":
        return oracle.chebyshev("x")
    if family == "kernel":
        return f"greatest(exp(-{z} * {z} / 2), 1e-300)"
    a = f"(abs{z} / sqrt(2.0))"
    t = f"(1 / (1 + {a} / 2))"
    poly = f"({_TAIL[-1]})"
    for c in reversed(_TAIL[:-1]):
        poly = f"({poly} * {t} + ({c}))"
    return f"least(greatest({t} * exp(-{a} * {a} + {poly}), 1e-300), 1.0)"


def _flags_frozen(family: str) -> None:
    theta = {"chebyshev": 0.12, "kernel": 0.02, "tail": 0.005}[family]

    @query(f"flags_frozen_{family}", oracle.with_(oracle.example(), f"SELECT n, count(*) AS abnormal FROM bad JOIN models USING (m) WHERE {_support_sql(family)} < {theta} GROUP BY n"))
    def flags(spark, sf_dir):
        e = Example(spark, sf_dir)
        got = detect.flag(e.bad, e.models, theta, family)
        return got.select("n", F.size("abnormal").cast("long").alias("abnormal")).filter("abnormal > 0")


for _family in ("chebyshev", "kernel", "tail"):
    _flags_frozen(_family)


@query("flags_given_models", oracle.with_(oracle.example(), f"SELECT n, string_agg(m, '>' ORDER BY m) AS abnormal FROM bad WHERE {oracle.chebyshev('x', '(3.0 * m)', '1.5')} < 0.12 GROUP BY n"))
def flags_given_models(spark, sf_dir):
    """Models from prior knowledge in the place of learned ones."""
    given = model.models_from_table(spark.range(5).select(F.lit(0).alias("eq_id"), F.col("id").alias("m"), (F.col("id") * 3).alias("mu"), F.lit(1.5).alias("sigma")))
    got = detect.flag(Example(spark, sf_dir).bad, given)
    return got.filter(F.size("abnormal") > 0).select("n", perm.cycle_key(F.col("abnormal")).alias("abnormal"))


_EMPIRICAL = f"""{_HIST}, {oracle.panel("p", 2.0)}, {oracle.models()},
bins AS (SELECT m, bin, count(*) / any_value(cnt) AS share FROM (SELECT m, cnt, least(CAST(floor((x - lo) / (hi - lo) * 20) AS INTEGER), 19) AS bin FROM hist JOIN models USING (m)) GROUP BY m, bin),
mass AS (SELECT a.m, a.bin, (SELECT sum(b.share) FROM bins b WHERE b.m = a.m AND b.share <= a.share) AS mass FROM bins a),
cells AS (SELECT n, p.m, CASE WHEN x < lo OR x > hi THEN 0 ELSE coalesce(mass, 0) END AS p FROM (SELECT n, p.m, x, lo, hi, least(CAST(floor((x - lo) / (hi - lo) * 20) AS INTEGER), 19) AS bin FROM p JOIN models USING (m)) p LEFT JOIN mass USING (m, bin))"""


@query("flags_frozen_empirical", oracle.with_(_EMPIRICAL, "SELECT n, CAST(count(*) AS INTEGER) AS abnormal FROM cells WHERE p < 0.02 GROUP BY n"))
def flags_frozen_empirical(spark, sf_dir):
    models = model.fit_hist(panels.calibrated_panel(spark, sf_dir, history=True))
    got = detect.flag(panels.calibrated_panel(spark, sf_dir), models, 0.02, "empirical")
    return got.select("n", F.size("abnormal").alias("abnormal")).filter("abnormal > 0")


_ROLL = """roll AS (SELECT n, m, x, count(*) OVER w AS k, coalesce(sum(x) OVER w, 0) AS s, coalesce(sum(x * x) OVER w, 0) AS ss FROM bad WINDOW w AS (PARTITION BY m ORDER BY n ROWS BETWEEN 100 PRECEDING AND 1 PRECEDING)),
est AS (SELECT n, m, x, (s + 100.0 * mu) / (k + 100.0) AS mu2, (ss + 100.0 * (sigma * sigma + mu * mu)) / (k + 100.0) AS sec FROM roll JOIN models USING (m)),
fin AS (SELECT n, m, x, mu2 AS mu, sqrt(greatest(sec - mu2 * mu2, 0)) AS sigma FROM est)"""


@query("flags_rolling", oracle.with_(f"{oracle.example()}, {_ROLL}", f"SELECT n, string_agg(m, '>' ORDER BY m) AS abnormal FROM fin WHERE {oracle.chebyshev('x')} < 0.12 GROUP BY n"))
def flags_rolling(spark, sf_dir):
    e = Example(spark, sf_dir)
    got = detect.rolling(e.bad, e.models)
    return got.filter(F.size("abnormal") > 0).select("n", perm.cycle_key(F.col("abnormal")).alias("abnormal"))


@query("flags_feedback")
def flags_feedback(spark, sf_dir):
    e = Example(spark, sf_dir)
    got = candidates.feedback_candidates(e.bad, e.models, RepairConfig(mode="feedback"))
    return got.select("n", perm.cycle_key(F.col("abnormal")).alias("abnormal"), perm.cycle_key(F.col("dst")).alias("dst"), "status")


_LAGS = "lags AS (SELECT n, m, x, lag(x) OVER (PARTITION BY m ORDER BY n) AS p FROM bad)"
_DETECTOR_SQL = {
    "ksigma": ("", "SELECT n, m FROM bad JOIN models USING (m) WHERE abs(x - mu) > 2.5 * sigma"),
    "iqr": (f", {_ROBUST}", "SELECT n, m FROM bad JOIN mid USING (m) WHERE NOT x BETWEEN q1 - (q3 - q1) * 1.5 AND q3 + (q3 - q1) * 1.5"),
    "range": ("", "SELECT n, m FROM bad JOIN models USING (m) WHERE NOT x BETWEEN lo AND hi"),
    "robust": (f", {_ROBUST}", "SELECT n, m FROM bad JOIN mid USING (m) JOIN mad USING (m) WHERE abs(x - mu) > 2.5 * sigma"),
    "jump": (
        f", {_LAGS}, d AS (SELECT m, stddev_samp(x - p) AS sd FROM (SELECT m, x, lag(x) OVER (PARTITION BY m ORDER BY n) AS p FROM hist) GROUP BY m)",
        "SELECT n, m FROM lags JOIN d USING (m) WHERE abs(x - p) > 2.5 * sd",
    ),
    "ar1": (f", {_LAGS}, {_AR1}", "SELECT n, m FROM lags JOIN fit USING (m) JOIN rest USING (m) WHERE abs(x - slope * p - intercept) > 2.5 * sigma"),
    "hampel": (
        ", near AS (SELECT n, m, x, list(x) OVER (PARTITION BY m ORDER BY n ROWS BETWEEN 7 PRECEDING AND 7 FOLLOWING) AS near FROM bad), mid AS (SELECT *, list_median(near) AS md FROM near), mad AS (SELECT *, list_median(list_transform(near, lambda v: abs(v - md))) * 1.4826 AS mad FROM mid)",
        "SELECT n, m FROM mad WHERE abs(x - md) > 3.0 * mad",
    ),
    "ewma": (
        ", past AS (SELECT n, m, x, mu, sigma, list(x) OVER (PARTITION BY m ORDER BY n ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS past FROM bad JOIN models USING (m)), e AS (SELECT *, list_reduce(list_prepend(mu, coalesce(past, [])), lambda acc, v: acc + 0.2 * (v - acc)) AS ewma FROM past)",
        "SELECT n, m FROM e WHERE abs(x - ewma) > 2.5 * sigma",
    ),
    "features": (
        ", " + ", ".join(
            f"""{t} AS (SELECT m, n, avg(x) OVER w AS f_mean, stddev_samp(x) OVER w AS f_sd, min(x) OVER w AS f_lo, max(x) OVER w AS f_hi, regr_slope(x, n) OVER w AS f_slope, count(*) OVER w AS c
  FROM {source} WINDOW w AS (PARTITION BY m ORDER BY n ROWS BETWEEN 9 PRECEDING AND CURRENT ROW))"""
            for t, source in (("fh", "hist"), ("fb", "bad"))
        ) + ", fm AS (SELECT m, " + ", ".join(f"avg({c}) AS {c}_mu, stddev_samp({c}) AS {c}_sigma" for c in model.FEATURES) + " FROM fh WHERE c = 10 GROUP BY m)",
        "SELECT n, m FROM fb JOIN fm USING (m) WHERE c = 10 AND (" + " OR ".join(f"abs({c} - {c}_mu) > 4.0 * {c}_sigma" for c in model.FEATURES) + ")",
    ),
    "distance": (
        ", g AS (SELECT m, sqrt(avg((x - mu) * (x - mu)) OVER (PARTITION BY m ORDER BY n ROWS BETWEEN 9 PRECEDING AND CURRENT ROW)) AS gap FROM hist JOIN models USING (m)), pr AS (SELECT m, avg(gap) AS gm, stddev_samp(gap) AS gs FROM g GROUP BY m), b AS (SELECT n, m, sqrt(avg((x - mu) * (x - mu)) OVER (PARTITION BY m ORDER BY n ROWS BETWEEN 9 PRECEDING AND CURRENT ROW)) AS gap FROM bad JOIN models USING (m))",
        "SELECT n, m FROM b JOIN pr USING (m) WHERE gap > gm + 4.0 * gs",
    ),
}


def _flags_detector(name: str) -> None:
    parts = _DETECTOR_SQL[name]

    @query(f"flags_{name}", oracle.with_(oracle.example() + parts[0], parts[1]) if parts else None)
    def flags(spark, sf_dir):
        e = Example(spark, sf_dir)
        return detect.DETECTORS[name](e.bad, e.history).filter("flag").select("n", "m")


for _name in _DETECTOR_SQL:
    _flags_detector(_name)


# --- matching and candidates ------------------------------------------------------------------------------------

_TO_WEIGHTS = f"{oracle.example()}, {oracle.FLAGS}, {oracle.WEIGHTS}"
_TO_MATCH = f"{_TO_WEIGHTS}, {oracle.MATCH}"
_MATCH_SQL = oracle.with_(_TO_MATCH, "SELECT n, array_to_string(src, '>') AS src, array_to_string(dst, '>') AS dst, round(total, 6) AS total FROM matched")


@query("gate_two_abnormal", oracle.with_(f"{oracle.example()}, {oracle.FLAGS}", "SELECT n, a FROM sets WHERE a >= 2"))
def gate_two_abnormal(spark, sf_dir):
    return candidates.gate(Example(spark, sf_dir).flags()).select("n", F.size("abnormal").cast("long").alias("a"))


@query("weights_long", oracle.with_(_TO_WEIGHTS, "SELECT n, u, v, round(w, 6) AS w FROM edges"))
def weights_long(spark, sf_dir):
    return matching.edges(Example(spark, sf_dir).weighted()).select("n", "u", "v", r6("w"))


def _match(name: str, how: str, sql: str | None) -> None:
    @query(name, sql)
    def match(spark, sf_dir):
        rows = Example(spark, sf_dir).weighted().withColumn("to", matching.matched(F.col("w"), how))
        total = F.aggregate(F.zip_with("w", "to", lambda row, j: row[j]), F.lit(0.0), lambda a, v: a + v)
        dst = F.transform("to", lambda j: F.col("abnormal")[j])
        return rows.select("n", perm.cycle_key(F.col("abnormal")).alias("src"), perm.cycle_key(dst).alias("dst"), F.round(total, 6).alias("total"))


_match("match_enum", "enum", _MATCH_SQL)
_match("match_exact", "assign", _MATCH_SQL)
_match("match_flow", "flow", _MATCH_SQL)
_match(
    "match_greedy",
    "greedy",
    oracle.with_(
        f"{_TO_WEIGHTS},\n{oracle.GREEDY_PICK}",
        "SELECT n, string_agg(u, '>' ORDER BY u) AS src, string_agg(v, '>' ORDER BY u) AS dst, round(any_value(total), 6) AS total FROM done GROUP BY n",
    ),
)


_LOG = f"{oracle.example()}, {oracle.FLAGS}, {oracle.WEIGHTS.replace('edges AS', 'plain AS')}, edges AS (SELECT n, u, v, ln(greatest(w, 1e-300)) AS w FROM plain), {oracle.MATCH}"


@query("match_log_objective", oracle.with_(_LOG, "SELECT n, array_to_string(dst, '>') AS dst FROM matched"))
def match_log_objective(spark, sf_dir):
    rows = candidates.gate(Example(spark, sf_dir).flags()).withColumn("w", matching.weights(objective="log")).withColumn("to", matching.matched(F.col("w"), "assign"))
    return rows.select("n", perm.cycle_key(F.transform("to", lambda j: F.col("abnormal")[j])).alias("dst"))


_TO_CYCLES = f"{_TO_MATCH}, {oracle.CYCLES}"


@query("candidates_frozen", oracle.with_(_TO_CYCLES, "SELECT n, len(src) AS size, coalesce(string_agg(sigma, '|' ORDER BY walk), '') AS phi FROM matched LEFT JOIN cyc USING (n) GROUP BY n, src"))
def candidates_frozen(spark, sf_dir):
    got = Example(spark, sf_dir).candidates().filter("status = 'repaired'")
    return got.select("n", F.col("size").cast("long").alias("size"), perm.cycles_key(F.col("cycles")).alias("phi"))


@query("cycles", _PLAN_SQL.replace("SELECT CAST(k AS BIGINT) AS k, CAST(l AS BIGINT) AS l, CAST(r AS BIGINT) AS r, string_agg(array_to_string(c, '>'), '|' ORDER BY c) AS phi FROM canon GROUP BY k, l, r", "SELECT CAST(k AS BIGINT) AS k, array_to_string(c, '>') AS sigma, CAST(len(c) AS BIGINT) AS members FROM canon"))
def cycles(spark, sf_dir):
    """Cycles of the true permutations, composed and decomposed again."""
    truth = inject.plan(inject.extent(panels.calibrated_panel(spark, sf_dir)))
    pairs = truth.select("k", perm.sources(F.col("phi")).alias("src"), perm.targets(F.col("phi")).alias("dst"))
    order = F.array_sort(F.arrays_zip("src", "dst"))
    pairs = pairs.select("k", F.transform(order, lambda s: s["src"]).alias("src"), F.transform(order, lambda s: s["dst"]).alias("dst"))
    return pairs.select("k", F.explode(perm.cycles(F.col("src"), F.col("dst"))).alias("c")).select("k", perm.cycle_key(F.col("c")).alias("sigma"), F.size("c").cast("long").alias("members"))


@query("candidate_cells", oracle.with_(f"{_TO_CYCLES}, moves AS (SELECT n, unnest(src) AS u, unnest(dst) AS v FROM matched)", "SELECT bad.n, v AS m, round(x, 6) AS x FROM moves JOIN bad ON bad.n = moves.n AND bad.m = u WHERE u <> v"))
def candidate_cells(spark, sf_dir):
    e = Example(spark, sf_dir)
    fixed = candidates.candidate_panel(e.bad, e.candidates())
    both = panels.to_long(fixed).select("n", "m", "x").join(panels.to_long(e.bad).select("n", "m", F.col("x").alias("was")), ["n", "m"])
    return both.filter("x <> was").select("n", "m", r6("x"))


@query("escalations", oracle.with_(f"{oracle.example()}, {oracle.FLAGS}", "SELECT n, a AS size FROM sets WHERE a > 3"))
def escalations(spark, sf_dir):
    e = Example(spark, sf_dir)
    got = candidates.candidate_schemas(e.bad, e.models, e.cfg.with_(epsilon=3))
    return candidates.escalations(got).select("n", F.col("size").cast("long").alias("size"))


@query("escalation_sink", oracle.with_(f"{oracle.example()}, {oracle.FLAGS}", "SELECT n, a AS size FROM sets WHERE a > 3 UNION ALL SELECT n, a FROM sets WHERE a > 4"))
def escalation_sink(spark, sf_dir):
    """What people must look at, appended to a table by two runs and read back."""
    e, path = Example(spark, sf_dir), scratch_path(spark, "escalations")
    for epsilon in (3, 4):
        write_escalations(candidates.candidate_schemas(e.bad, e.models, e.cfg.with_(epsilon=epsilon)), path)
    return spark.read.parquet(path).select("n", F.col("size").cast("long").alias("size"))


@query("candidates_empirical")
def candidates_empirical(spark, sf_dir):
    """Step A with learned histograms in the place of moments."""
    e = Example(spark, sf_dir)
    got = candidates.candidate_schemas(e.bad, model.fit_hist(e.history), RepairConfig(family="empirical", theta_m=0.02))
    return got.select("n", "status", perm.cycles_key(F.col("cycles")).alias("phi"))


@query("candidates_detector", oracle.with_(f"{oracle.example()}, {_ROBUST}, flags AS (SELECT n, bad.m, x FROM bad JOIN mid USING (m) WHERE NOT x BETWEEN q1 - (q3 - q1) * 1.5 AND q3 + (q3 - q1) * 1.5), sets AS (SELECT n, list(m ORDER BY m) AS ab, count(*) AS a FROM flags GROUP BY n), {oracle.WEIGHTS}, {oracle.MATCH}", "SELECT n, array_to_string(src, '>') AS src, array_to_string(dst, '>') AS dst FROM matched"))
def candidates_detector(spark, sf_dir):
    """Step A with a plug-in detector (fences around the quartiles) in the place of its own test."""
    e = Example(spark, sf_dir)
    got = candidates.candidate_schemas(e.bad, e.models, RepairConfig(detector="iqr"), history=e.history).filter("status = 'repaired'")
    return got.select("n", perm.cycle_key(F.col("src")).alias("src"), perm.cycle_key(F.col("dst")).alias("dst"))


@query("repair_by_regime")
def repair_by_regime(spark, sf_dir):
    """The whole method with a model for each working condition."""
    clean = stored(panels.native_panel(spark, sf_dir), "native")
    bad = stored(inject.inject(clean, inject.plan(inject.extent(clean), 6, 9)), "bad")
    got = methods.repair(bad, stored(model.fit_moments(clean, regime=True), "models"), RepairConfig(regime=True, len1=5, len2=5))
    return got.schemas.select("l", "r", perm.cycles_key(F.col("phi")).alias("phi"))


@query("candidates_calibrated")
def candidates_calibrated(spark, sf_dir):
    b = workloads.Workbench(spark, sf_dir, g=3.0)
    got = candidates.candidate_schemas(b.panel, b.models, RepairConfig())
    return got.filter("status = 'repaired'").select("n", perm.cycles_key(F.col("cycles")).alias("phi"), "size")


# --- units, runs, determination ---------------------------------------------------------------------------------

_TO_UNITS = f"{_TO_CYCLES}, {oracle.UNITS}"


@query("units", oracle.with_(_TO_UNITS, "SELECT * FROM units"))
def units_all(spark, sf_dir):
    return units.build_units(units.ones(Example(spark, sf_dir).candidates())).select("sigma", "size", "first", "last")


@query("units_kept", oracle.with_(_TO_UNITS, "SELECT sigma, size, row_number() OVER (ORDER BY size DESC, sigma) AS \"rank\" FROM units WHERE size >= 20"))
def units_kept(spark, sf_dir):
    got = units.select_units(units.build_units(units.ones(Example(spark, sf_dir).candidates())), 20)
    return got.select("sigma", "size", F.col("rank").cast("long").alias("rank"))


@query("top_units", oracle.with_(_TO_UNITS, "SELECT sigma, size, row_number() OVER (ORDER BY size DESC, sigma) AS \"rank\" FROM units ORDER BY 3 LIMIT 3"))
def top_units(spark, sf_dir):
    return units.top_units(units.build_units(units.ones(Example(spark, sf_dir).candidates())), 3).select("sigma", "size", F.col("rank").cast("long").alias("rank"))


@query(
    "unit_rank",
    oracle.with_(_TO_UNITS, "SELECT sigma, row_number() OVER w AS row_no, rank() OVER (ORDER BY size DESC) AS size_rank, dense_rank() OVER (ORDER BY size DESC) AS dense_no, ntile(4) OVER w AS quarter FROM units WINDOW w AS (ORDER BY size DESC, sigma)"),
)
def unit_rank(spark, sf_dir):
    from pyspark.sql.window import Window

    got = units.build_units(units.ones(Example(spark, sf_dir).candidates()))
    w, s = Window.partitionBy("eq_id").orderBy(F.desc("size"), "sigma"), Window.partitionBy("eq_id").orderBy(F.desc("size"))
    cols = {"row_no": F.row_number().over(w), "size_rank": F.rank().over(s), "dense_no": F.dense_rank().over(s), "quarter": F.ntile(4).over(w)}
    return got.select("sigma", *[c.cast("long").alias(k) for k, c in cols.items()])


@query("unit_distinct", oracle.with_(_TO_CYCLES, "SELECT count(DISTINCT sigma) AS n_sigma, count(DISTINCT n) AS n_points FROM cyc"))
def unit_distinct(spark, sf_dir):
    ones = units.ones(Example(spark, sf_dir).candidates())
    return ones.groupBy("eq_id").agg(F.count_distinct("sigma").alias("n_sigma"), F.count_distinct("n").alias("n_points")).drop("eq_id")


@query("unit_distinct_approx")
def unit_distinct_approx(spark, sf_dir):
    ones = units.ones(Example(spark, sf_dir).candidates())
    return ones.groupBy("eq_id").agg(F.approx_count_distinct("sigma").alias("n_sigma"), F.approx_count_distinct("n").alias("n_points"))


_TO_RUNS = f"{_TO_CYCLES}, ones AS (SELECT sigma, n FROM cyc), {oracle.runs('ones')}"


@query("runs_sigma", oracle.with_(_TO_RUNS, "SELECT sigma, l, r FROM runs"))
def runs_sigma(spark, sf_dir):
    return runs.islands(units.ones(Example(spark, sf_dir).candidates())).select("sigma", "l", "r")


_ALL_RUNS = """every AS (SELECT sigma, 1 AS bit, l, r FROM runs UNION ALL SELECT sigma, 0, coalesce(lag(r) OVER w, 0) + 1, l - 1 FROM runs WINDOW w AS (PARTITION BY sigma ORDER BY l)
  UNION ALL SELECT sigma, 0, max(r) + 1, (SELECT last FROM span) FROM runs GROUP BY sigma),
valid AS (SELECT *, r - l + 1 AS len FROM every WHERE l <= r)"""


@query("tau_sigma", oracle.with_(f"{_TO_RUNS}, {_ALL_RUNS}", "SELECT sigma, bit, l, len, round(len / (lag(len) OVER w + lead(len) OVER w), 6) AS tau FROM valid WINDOW w AS (PARTITION BY sigma ORDER BY l)"))
def tau_sigma(spark, sf_dir):
    e = Example(spark, sf_dir)
    got = runs.with_tau(runs.all_runs(runs.islands(units.ones(e.candidates())), e.last))
    return got.select("sigma", "bit", "l", "len", r6("tau"))


def _bits(table: str, order: str, condition: str) -> str:
    return f"b AS (SELECT row_number() OVER (ORDER BY {order}) AS n, {condition} AS on_ FROM {table}), ones AS (SELECT 'x' AS sigma, n FROM b WHERE on_)"


def _label_ones(spark, sf_dir, column: str) -> tuple[DataFrame, DataFrame]:
    from unscramble.operators.ordinal import with_ordinal

    rows = with_ordinal(read_table(spark, sf_dir, "labels", ["doc_id", column]), ["doc_id"]).withColumn("eq_id", F.lit(0).cast("long"))
    return rows.filter(F.col(column) == 1).select("eq_id", F.lit("x").alias("sigma"), "n"), rows.groupBy("eq_id").agg(F.max("n").alias("last"))


def _natural(column: str) -> str:
    return f"{_bits('labels', 'doc_id', f'{column} = 1')}, {oracle.runs('ones')}"


@query("label_runs", oracle.with_(_natural("quality"), "SELECT l, r FROM runs"))
def label_runs(spark, sf_dir):
    return runs.islands(_label_ones(spark, sf_dir, "quality")[0]).select("l", "r")


@query("role_runs", oracle.with_(f"{_bits('conversations', 'conv_id, turn', chr(39).join(['role = ', 'user', '']))}, {oracle.runs('ones')}", "SELECT l, r FROM runs"))
def role_runs(spark, sf_dir):
    from unscramble.operators.ordinal import with_ordinal

    rows = with_ordinal(read_table(spark, sf_dir, "conversations", ["conv_id", "turn", "role"]), ["conv_id", "turn"])
    ones = rows.filter("role = 'user'").select(F.lit(0).cast("long").alias("eq_id"), F.lit("x").alias("sigma"), "n")
    return runs.islands(ones).select("l", "r")


def _smoothing(name: str, merge: str, mode: str, sql: str | None) -> None:
    @query(name, sql)
    def smoothing(spark, sf_dir):
        ones, last = _label_ones(spark, sf_dir, "quality")
        return runs.smooth(runs.islands(ones), last, 0.3, 5, mode, merge).select("l", "r")


_LAST = "(SELECT max(n) FROM b)"
_smoothing("smooth_two_pass", "two_pass", "guarded", oracle.with_(f"{_natural('quality')}, {oracle.two_pass('runs', _LAST, 0.3, 5)}", "SELECT l, r FROM smooth"))
_smoothing("smooth_symmetric", "two_pass", "symmetric", oracle.with_(f"{_natural('quality')}, {oracle.two_pass('runs', _LAST, 0.3, 5, 'symmetric')}", "SELECT l, r FROM smooth"))
_SNAP = f"""{_ALL_RUNS.replace("(SELECT last FROM span)", _LAST)},
t AS (SELECT *, coalesce(len / (lag(len) OVER w + lead(len) OVER w) < 0.3, false) AND (bit = 0 OR len < 5) AS may FROM valid WINDOW w AS (PARTITION BY sigma ORDER BY l)),
s AS (SELECT *, sum(CASE WHEN may THEN 0 ELSE 1 END) OVER (PARTITION BY sigma ORDER BY l ROWS UNBOUNDED PRECEDING) AS streak FROM t),
p AS (SELECT *, sum(CASE WHEN may THEN 1 ELSE 0 END) OVER (PARTITION BY sigma, streak ORDER BY l ROWS UNBOUNDED PRECEDING) AS place FROM s),
k AS (SELECT sigma, l, r FROM p WHERE CASE WHEN may AND place % 2 = 1 THEN 1 - bit ELSE bit END = 1),
j AS (SELECT *, sum(CASE WHEN coalesce(l - pr = 1, false) THEN 0 ELSE 1 END) OVER (PARTITION BY sigma ORDER BY l ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT *, lag(r) OVER (PARTITION BY sigma ORDER BY l) AS pr FROM k))"""
_smoothing("smooth_snapshot", "snapshot", "guarded", oracle.with_(f"{_natural('quality')}, {_SNAP}", "SELECT min(l) AS l, max(r) AS r FROM j GROUP BY sigma, g"))
_smoothing("smooth_progressive", "progressive", "guarded", None)


@query("intervals_full", oracle.with_(oracle.FULL, "SELECT sigma, l, r FROM intervals"))
def intervals_full(spark, sf_dir):
    """The flagship: from readings to the final intervals of every cycle, in expressions only."""
    e = Example(spark, sf_dir)
    found = stored(e.candidates(), "candidates")
    return determine.determine(found, e.last, e.cfg).intervals.select("sigma", "l", "r")


_OVERLAY = oracle.METHODS["full"]


@query("overlay_final", oracle.with_(_OVERLAY, "SELECT l, r, phi FROM final"))
def overlay_final(spark, sf_dir):
    e = Example(spark, sf_dir)
    got = determine.determine(stored(e.candidates(), "candidates"), e.last, e.cfg).schemas
    return got.select("l", "r", perm.cycles_key(F.col("phi")).alias("phi"))


@query("repaired_cells", oracle.with_(f"{oracle.FULL}, pairs AS (SELECT l, r, CAST(string_split(sigma, '>') AS INTEGER[]) AS c FROM intervals), moves AS (SELECT l, r, unnest(c) AS u, unnest(list_append(c[2:], c[1])) AS v FROM pairs)", "SELECT n, v AS m, round(x, 6) AS x FROM moves JOIN bad ON n BETWEEN l AND r AND m = u"))
def repaired_cells(spark, sf_dir):
    e = Example(spark, sf_dir)
    result = methods.repair(e.bad, e.models, e.cfg)
    both = panels.to_long(result.repaired).select("n", "m", "x").join(panels.to_long(e.bad).select("n", "m", F.col("x").alias("was")), ["n", "m"])
    return both.filter("x <> was").select("n", "m", r6("x"))


# --- whole methods, measures, workloads -------------------------------------------------------------------------


def _method(name: str, cfg: RepairConfig) -> None:
    @query(f"method_{name}")
    def method(spark, sf_dir):
        b = workloads.Workbench(spark, sf_dir)
        got = methods.repair(b.panel, b.models, cfg).schemas
        return got.select("eq_id", "l", "r", perm.cycles_key(F.col("phi")).alias("phi"))


for _name, _cfg in {
    "full": RepairConfig(), "greedy": RepairConfig(method="greedy"), "candidate": RepairConfig(method="candidate"), "block": RepairConfig(method="block"),
    "block_median": RepairConfig(method="block", block_stat="median"), "block_last": RepairConfig(method="block", block_stat="last"), "none": RepairConfig(method="none"),
    "rolling": RepairConfig(mode="rolling"), "feedback": RepairConfig(mode="feedback"), "as_printed": as_printed(),
}.items():
    _method(_name, _cfg)


def _example_method(name: str, cfg: RepairConfig) -> None:
    @query(f"example_{name}", oracle.with_(oracle.METHODS[name], "SELECT l, r, phi FROM final"))
    def method(spark, sf_dir):
        e = Example(spark, sf_dir)
        return methods.repair(e.bad, e.models, cfg).schemas.select("l", "r", perm.cycles_key(F.col("phi")).alias("phi"))


_EXAMPLE = {
    "full": RepairConfig(), "greedy": RepairConfig(method="greedy"), "candidate": RepairConfig(method="candidate"),
    "block": RepairConfig(method="block"), "block_median": RepairConfig(method="block", block_stat="median"),
}
for _name, _cfg in _EXAMPLE.items():
    _example_method(_name, _cfg)


@query("example_scores", " UNION ALL ".join(f"SELECT * FROM {oracle.scores(m)}" for m in _EXAMPLE))
def example_scores(spark, sf_dir):
    """W10 without its seconds: the measures of every method on the example."""
    e = Example(spark, sf_dir)
    out = None
    for name, cfg in _EXAMPLE.items():
        row = methods.evaluated(methods.repair(e.bad, e.models, cfg), e.truth, cfg).select(F.lit(name).alias("method"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query("method_pointwise", oracle.with_(f"{oracle.example()}, {oracle.FLAGS}", "SELECT n, flags.m, round(mu, 6) AS x FROM flags JOIN models USING (m)"))
def method_pointwise(spark, sf_dir):
    e = Example(spark, sf_dir)
    fixed = methods.repair(e.bad, e.models, RepairConfig(method="pointwise")).repaired
    both = panels.to_long(fixed).select("n", "m", "x").join(panels.to_long(e.bad).select("n", "m", F.col("x").alias("was")), ["n", "m"])
    return both.filter("x <> was").select("n", "m", r6("x"))


@query("block_means", oracle.with_(f"{oracle.example()}, len AS (SELECT CAST(ceil(sqrt(last)) AS BIGINT) AS len FROM span)", "SELECT CAST((n - 1) // len + 1 AS BIGINT) AS n, m, round(avg(x), 6) AS x FROM bad, len GROUP BY (n - 1) // len, m"))
def block_means(spark, sf_dir):
    e = Example(spark, sf_dir)
    length = methods.block_length(e.last.first()["last"], 1.0)
    return panels.to_long(methods.blocks(e.bad, length)).select("n", "m", r6("x"))


_HAND = "(0, 1, 10, '0>1'), (0, 21, 30, '2>3'), (0, 41, 50, '4>5'), (0, 61, 70, '6>7'), (0, 81, 90, '8>9')"
_HAND_TRUE = "(0, 1, 10, '0>1'), (0, 21, 29, '2>3'), (0, 43, 50, '4>5'), (0, 61, 70, '6>8'), (0, 120, 130, '8>9')"
#: Intervals found and true for the parts, of which some have no partner, too small a common share or another permutation.
_PARTS_FOUND = "SELECT p_partkey * 100 + p_size % 7 AS l, p_partkey * 100 + p_size % 7 + 10 + p_size % 11 AS r, concat(p_size % 6, '>', p_size % 6 + 1) AS phi FROM {} WHERE p_partkey % 7 <> 0"
_PARTS_TRUE = "SELECT p_partkey * 100 + p_size % 5 AS l, p_partkey * 100 + p_size % 5 + 8 + p_size % 13 AS r, concat(p_size % 6, '>', p_size % 6 + CASE WHEN p_size % 4 = 0 THEN 2 ELSE 1 END) AS phi FROM {} WHERE p_partkey % 5 <> 0"
_HAND_SQL = f"""f AS ({_PARTS_FOUND.format("part")}), t AS ({_PARTS_TRUE.format("part")}),
s AS (SELECT f.phi AS fp, t.phi AS tp, abs(f.l - t.l) AS dl, abs(f.r - t.r) AS dr FROM f JOIN t ON (least(f.r, t.r) - greatest(f.l, t.l) + 1.0) / (greatest(f.r, t.r) - least(f.l, t.l) + 1) >= 0.5 AND f.l <= t.r AND t.l <= f.r),
c AS (SELECT (SELECT count(*) FROM f) AS n_found, (SELECT count(*) FROM t) AS n_true, (SELECT count(*) FROM s) AS n_correct, (SELECT count(*) FROM s WHERE fp = tp) AS n_repaired)"""


def _hand(spark: SparkSession) -> tuple[DataFrame, DataFrame]:
    def rows(values: str) -> DataFrame:
        raw = spark.sql(f"SELECT CAST(eq_id AS LONG) eq_id, CAST(l AS LONG) l, CAST(r AS LONG) r, phi FROM VALUES {values} AS t(eq_id, l, r, phi)")
        return raw.withColumn("phi", perm.parse_cycles(F.col("phi")))

    return rows(_HAND), rows(_HAND_TRUE)


def part_intervals(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    parts = read_table(spark, sf_dir, "part", ["p_partkey", "p_size"])
    both = (spark.sql(text.format("{parts}"), parts=parts) for text in (_PARTS_FOUND, _PARTS_TRUE))
    found, true = (df.select(F.lit(0).cast("long").alias("eq_id"), "l", "r", perm.parse_cycles(F.col("phi")).alias("phi")) for df in both)
    return found, true


@query("scores_hand", oracle.with_(_HAND_SQL, "SELECT n_found, n_true, n_correct, n_repaired, n_correct / n_found AS p_d, n_correct / n_true AS r_d, n_repaired / n_correct AS p_r, n_repaired / n_found AS r_r FROM c"))
def scores_hand(spark, sf_dir):
    return metrics.scores(*part_intervals(spark, sf_dir)).drop("p_r_alt", "r_r_alt")


@query("scores_hand_alt", oracle.with_(_HAND_SQL, "SELECT n_repaired / n_found AS p_r_alt, n_repaired / n_correct AS r_r_alt FROM c"))
def scores_hand_alt(spark, sf_dir):
    return metrics.scores(*part_intervals(spark, sf_dir)).select("p_r_alt", "r_r_alt")


@query("cycle_scores_hand", oracle.with_(_HAND_SQL, "SELECT n_found, n_true, n_repaired AS n_correct, n_repaired / n_found AS \"precision\", n_repaired / n_true AS recall FROM c"))
def cycle_scores_hand(spark, sf_dir):
    return metrics.cycle_scores(*part_intervals(spark, sf_dir))


@query("bound_error_hand", oracle.with_(_HAND_SQL, "SELECT count(*) AS n_pairs, avg(dl) AS start_error, avg(dr) AS end_error FROM s"))
def bound_error_hand(spark, sf_dir):
    return metrics.bound_error(*part_intervals(spark, sf_dir))


_TRUE_RUNS = "true_runs AS (SELECT '0>1' AS sigma, l, r FROM span UNION ALL SELECT '2>4', l, r FROM span)"


def _confusion_sql(found: str) -> str:
    return f"""pts AS (SELECT sigma, unnest(range(l, r + 1)) AS n FROM {found}), want AS (SELECT sigma, unnest(range(l, r + 1)) AS n FROM true_runs)"""


_CONFUSED = "SELECT sigma, count(*) FILTER (WHERE p.n IS NOT NULL AND w.n IS NOT NULL) AS tp, count(*) FILTER (WHERE w.n IS NULL) AS fp, count(*) FILTER (WHERE p.n IS NULL) AS fn FROM pts p FULL JOIN want w USING (sigma, n) GROUP BY sigma"


@query("bit_confusion", oracle.with_(f"{_TO_RUNS}, {_TRUE_RUNS}, {_confusion_sql('runs')}", _CONFUSED.replace("p.n IS", "pn IS").replace("w.n IS", "wn IS").replace("FROM pts p FULL JOIN want w USING (sigma, n)", "FROM (SELECT sigma, n, n AS pn FROM pts) p FULL JOIN (SELECT sigma, n, n AS wn FROM want) w USING (sigma, n)")))
def bit_confusion(spark, sf_dir):
    e = Example(spark, sf_dir)
    return metrics.bit_confusion(runs.islands(units.ones(e.candidates())), metrics.truth_runs(e.truth)).drop("eq_id")


@query("bit_confusion_smoothed", oracle.with_(f"{oracle.FULL}, {_TRUE_RUNS}, {_confusion_sql('intervals')}", _CONFUSED.replace("p.n IS", "pn IS").replace("w.n IS", "wn IS").replace("FROM pts p FULL JOIN want w USING (sigma, n)", "FROM (SELECT sigma, n, n AS pn FROM pts) p FULL JOIN (SELECT sigma, n, n AS wn FROM want) w USING (sigma, n)")))
def bit_confusion_smoothed(spark, sf_dir):
    e = Example(spark, sf_dir)
    got = determine.determine(stored(e.candidates(), "candidates"), e.last, e.cfg).intervals
    return metrics.bit_confusion(got, metrics.truth_runs(e.truth)).drop("eq_id")


@query("escalation_rate", oracle.with_(f"{oracle.example()}, {oracle.FLAGS}", "SELECT count(*) AS n_escalated, any_value(last) AS n_points, count(*) / any_value(last) AS rate FROM sets, span WHERE a > 3"))
def escalation_rate(spark, sf_dir):
    e = Example(spark, sf_dir)
    return metrics.escalation_rate(candidates.candidate_schemas(e.bad, e.models, e.cfg.with_(epsilon=3)), e.last)


_MOVED = f"{oracle.FULL}, pairs AS (SELECT l, r, CAST(string_split(sigma, '>') AS INTEGER[]) AS c FROM intervals), moves AS (SELECT l, r, unnest(c) AS u, unnest(list_append(c[2:], c[1])) AS v FROM pairs)"
_CELLS = f"""{_MOVED}, fixed AS (SELECT n, v AS m, x AS y FROM moves JOIN bad ON n BETWEEN l AND r AND m = u),
cells AS (SELECT c.x AS t, b.x AS d, coalesce(f.y, b.x) AS y FROM clean c JOIN bad b USING (n, m) LEFT JOIN fixed f USING (n, m))"""


@query(
    "cell_scores",
    oracle.with_(_CELLS, "SELECT CAST(count(*) FILTER (WHERE t <> d) AS BIGINT) AS n_misplaced, count(*) FILTER (WHERE t <> d AND t = y) AS n_restored, count(*) FILTER (WHERE t = d AND t <> y) AS n_damaged, round(count(*) FILTER (WHERE t <> d AND t = y) / count(*) FILTER (WHERE t <> d), 9) AS restored_share, round(sqrt(sum((t - y) * (t - y)) / count(*)), 9) AS rmse FROM cells"),
)
def cell_scores(spark, sf_dir):
    e = Example(spark, sf_dir)
    got = metrics.cell_scores(e.clean, e.bad, methods.repair(e.bad, e.models, e.cfg).repaired)
    return got.select("n_misplaced", "n_restored", "n_damaged", *[F.round(c, 9).alias(c) for c in ("restored_share", "rmse")])


@query("measures_full")
def measures_full(spark, sf_dir):
    return workloads.quality_of(workloads.Workbench(spark, sf_dir), RepairConfig())


@query("w3_overall")
def w3_overall(spark, sf_dir):
    return workloads.overall(spark, sf_dir)


@query("w4_volume")
def w4_volume(spark, sf_dir):
    return workloads.by_volume(spark, sf_dir)


@query("w6_attributes")
def w6_attributes(spark, sf_dir):
    return workloads.by_attributes(spark, sf_dir)


@query("w9_block_length")
def w9_block_length(spark, sf_dir):
    return workloads.by_block_length(spark, sf_dir)


@query("w10_example")
def w10_example(spark, sf_dir):
    return workloads.example(spark, sf_dir)


@query("w11_detectors")
def w11_detectors(spark, sf_dir):
    return workloads.detectors(spark, sf_dir)


@query("w12_other_panels")
def w12_other_panels(spark, sf_dir):
    return workloads.other_panels(spark, sf_dir)


@query("w16_ablations")
def w16_ablations(spark, sf_dir):
    return workloads.ablations(spark, sf_dir)
