"""The engine against references that share no code with it."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from tests.ref.step_a import step_a
from unscramble.config import RepairConfig
from unscramble.operators import candidates, detect, model
from unscramble.operators.intervals import asof_join, regularise
from unscramble.operators.ordinal import in_ranges, with_ordinal
from unscramble.plans import methods
from unscramble.plans.queries import Example
from unscramble.sources import panels

THETA = {"chebyshev": 0.12, "kernel": 0.02, "tail": 0.005}


@pytest.fixture(scope="module")
def small(spark, sf):
    e = Example(spark, sf)
    gamma = [(r["mu"], r["sigma"]) for r in e.models.orderBy("m").collect()]
    return e, sorted((r["n"], r["x"]) for r in e.bad.collect()), gamma


def engine(e, cfg):
    rows = candidates.candidate_schemas(e.bad, e.models, cfg).collect()
    return sorted((r["n"], r["abnormal"], r["dst"], r["status"]) for r in rows)


@pytest.mark.parametrize("family", THETA)
@pytest.mark.parametrize("match", ["auto", "enum", "assign", "flow", "greedy"])
def test_frozen_models(small, family, match):
    e, points, gamma = small
    cfg = RepairConfig(family=family, theta_m=THETA[family], match=match, epsilon=4)
    assert engine(e, cfg) == step_a(points, gamma, "frozen", cfg.theta_m, family, 0, 1.0, 4, greedy=match == "greedy")


@pytest.mark.parametrize("family", THETA)
def test_rolling_models(small, family):
    e, points, gamma = small
    cfg = RepairConfig(mode="rolling", family=family, theta_m=THETA[family], window=30, prior_weight=50.0)
    assert engine(e, cfg) == step_a(points, gamma, "rolling", cfg.theta_m, family, 30, 50.0, 24)


@pytest.mark.parametrize("family", THETA)
@pytest.mark.parametrize(("update", "policy"), [("sliding", "paper"), ("sliding", "guarded"), ("cumulative", "paper"), ("cumulative", "guarded")])
def test_models_that_follow_the_repaired_readings(small, family, update, policy):
    e, points, gamma = small
    cfg = RepairConfig(mode="feedback", family=family, theta_m=THETA[family], window=40, update=update, update_policy=policy)
    assert engine(e, cfg) == step_a(points, gamma, "feedback", cfg.theta_m, family, 40, 100.0, 24, update=update, policy=policy)


@pytest.mark.parametrize(("objective", "size_mode", "greedy"), [("log", "matched", False), ("sum", "moved", False), ("sum", "matched", True)])
def test_other_options_of_following_models(small, objective, size_mode, greedy):
    e, points, gamma = small
    cfg = RepairConfig(mode="feedback", method="greedy" if greedy else "full", objective=objective, size_mode=size_mode, epsilon=3, window=40)
    assert engine(e, cfg) == step_a(points, gamma, "feedback", 0.12, "chebyshev", 40, 100.0, 3, objective, greedy, size_mode=size_mode)


def test_histograms_working_conditions_and_detectors_reach_the_matching(spark, small):
    e, points, gamma = small
    got = candidates.candidate_schemas(e.bad, model.fit_hist(e.history), RepairConfig(family="empirical", theta_m=0.02))
    assert got.filter("status = 'repaired'").count() > 0
    halves = e.bad.withColumn("regime", F.when(F.col("n") % 2 == 0, "a").otherwise("b"))
    both = e.models.withColumn("regime", F.explode(F.array(F.lit("a"), F.lit("b"))))
    same = methods.repair(halves, both, RepairConfig(regime=True)).schemas.select("l", "r", "phi").collect()
    assert same == methods.repair(e.bad, e.models, RepairConfig()).schemas.select("l", "r", "phi").collect()
    apart = both.withColumn("mu", F.when(F.col("regime") == "a", F.col("mu")).otherwise(F.col("mu") + 1e6))
    assert {r["n"] % 2 for r in candidates.candidate_schemas(halves, apart, RepairConfig(regime=True)).filter("size(abnormal) = 5").collect()} == {1}
    flags = {}
    for r in detect.DETECTORS["ksigma"](e.bad, e.history).filter("flag").collect():
        flags.setdefault(r["n"], []).append(r["m"])
    got = candidates.candidate_schemas(e.bad, e.models, RepairConfig(detector="ksigma"), history=e.history).collect()
    assert {r["n"]: r["abnormal"] for r in got} == {n: sorted(ms) for n, ms in flags.items()}
    for cfg in (RepairConfig(detector="iqr"), RepairConfig(mode="rolling", regime=True), RepairConfig(mode="rolling", family="empirical"), RepairConfig(mode="feedback", regime=True), RepairConfig(mode="feedback", family="empirical")):
        with pytest.raises(Exception, match="history|frozen|moments|feedback"):
            candidates.candidate_schemas(e.bad, e.models, cfg).count()


@pytest.mark.parametrize("name", ["jump", "ar1", "hampel", "ewma", "features", "distance"])
def test_detectors_in_stretches(small, monkeypatch, name):
    e, _, _ = small
    run = lambda: sorted((r["n"], r["m"]) for r in detect.DETECTORS[name](e.bad, e.history).filter("flag").collect())
    want = run()
    monkeypatch.setattr(panels, "STRETCH", 23)
    assert run() == want


def test_rolling_models_in_stretches(small, monkeypatch):
    e, _, _ = small
    run = lambda: sorted((r["n"], r["abnormal"]) for r in detect.rolling(e.bad, e.models, 30).filter("size(abnormal) > 0").collect())
    want = run()
    monkeypatch.setattr(panels, "STRETCH", 17)
    assert run() == want


def test_ordinals_of_a_hot_time(spark):
    rows = spark.range(4000).select(F.when(F.col("id") % 10 < 9, 5).otherwise(F.col("id")).alias("t"), (F.col("id") * 7919 % 4001).alias("u"), (F.col("id") % 3).alias("g"))
    rows = rows.unionByName(spark.createDataFrame([(None, 1, 0), (None, 2, None)], "t long, u long, g long"))
    laid = in_ranges(rows, [F.col("t").asc_nulls_first(), F.col("u")])
    assert laid.groupBy("_part").count().agg(F.max("count")).first()[0] < 4002 / 2  # nine tenths have one time
    got = [(r["t"], r["u"]) for r in with_ordinal(rows, ["t", "u"]).orderBy("n").collect()]
    assert got == sorted(got, key=lambda k: (k[0] is not None, k[0] or 0, k[1])) and len(got) == 4002
    for r in with_ordinal(rows, ["t", "u"], "k", "g", 0).groupBy("g").agg(F.min("k").alias("lo"), F.max("k").alias("hi"), F.count_distinct("k").alias("n"), F.count("*").alias("c")).collect():
        assert (r["lo"], r["hi"], r["n"]) == (0, r["c"] - 1, r["c"])
    assert with_ordinal(rows.limit(0), ["t"]).count() == 0


def test_alignment_and_filling_across_ranges(spark):
    g = np.random.default_rng(3)
    at = lambda s: pd.Timestamp("2024-01-01") + pd.Timedelta(minutes=int(s))
    r = pd.DataFrame({"ts": [at(x) for x in g.choice(3000, 200, replace=False)], "k": g.integers(0, 2, 200), "v": g.normal(size=200)})
    r.loc[r.index % 7 == 0, "v"] = None
    t = pd.DataFrame({"ts": [at(x) for x in range(0, 3000, 11)]})
    want = pd.merge_asof(t, r.dropna().sort_values("ts"), on="ts")["v"]
    df = spark.createDataFrame([(x.ts.to_pydatetime(), int(x.k), None if pd.isna(x.v) else float(x.v)) for x in r.itertuples()], "ts timestamp, k long, v double")
    ticks = spark.createDataFrame([(x.to_pydatetime(),) for x in t["ts"]], "ts timestamp")
    got = asof_join(ticks, df.select("ts", "v"), "v").orderBy("ts").toPandas()["v"]
    assert np.allclose(got, want, equal_nan=True)
    keyed = asof_join(ticks.crossJoin(spark.range(2).toDF("k")), df, "v", "k").orderBy("k", "ts").toPandas()
    for k in (0, 1):
        want = pd.merge_asof(t, r[r.k == k].dropna().sort_values("ts"), on="ts")["v"]
        assert np.allclose(keyed[keyed.k == k]["v"], want, equal_nan=True)
    grid = pd.date_range(at(0), at(400), freq="1min")
    known = {at(0): 1.0, at(3): 4.0, at(200): -6.0, at(400): 2.0}
    s = pd.Series([known.get(x) for x in grid], index=grid, dtype=float)
    few = spark.createDataFrame([(k.to_pydatetime(), v) for k, v in known.items()], "ts timestamp, v double")
    for fill, want in (("forward", s.ffill()), ("linear", s.interpolate()), ("none", s)):
        out = regularise(few, "1 minute", ["v"], fill).orderBy("ts").toPandas()
        assert np.allclose(out["v"], want, equal_nan=True) and out["filled"].sum() == 397


ODD = 260  # points of each equipment of odd_panel


def odd_panel(spark, seed):
    """Two equipments of three sensors, with NULL and NaN among the readings."""
    rng, rows = np.random.default_rng(seed), []
    for eq in (0, 4):
        x = rng.normal([0.0, 5.0, 9.0], 1.0, (ODD, 3)) + (rng.random((ODD, 3)) < 0.04) * 6
        for n, v in enumerate(x.tolist(), 1):
            odd = [None if rng.random() < 0.05 else float("nan") if rng.random() < 0.004 else u for u in v]
            rows.append((eq, n, None, None, odd))
    return spark.createDataFrame(rows, "eq_id long, n long, ts timestamp, regime string, x array<double>").repartition(3)


@pytest.mark.parametrize("name", ["ewma", "hampel"])
def test_windows_see_what_is_known(spark, monkeypatch, name):
    monkeypatch.setattr(panels, "STRETCH", 40)
    panel, history = odd_panel(spark, 1).cache(), odd_panel(spark, 2).cache()
    fit = {(r["eq_id"], r["m"]): (r["mu"], r["sigma"]) for r in model.fit_moments(history).collect()}
    series = {}
    for r in panel.orderBy("n").collect():
        for m, v in enumerate(r["x"]):
            series.setdefault((r["eq_id"], m), []).append(v)
    want = {}
    above = lambda a, b: (a > b) or (a != a and b == b)
    middle = lambda a: ((s := sorted(a, key=lambda v: (v != v, v)))[(len(s) + 1) // 2 - 1] + s[len(s) // 2]) / 2
    for (eq, m), xs in series.items():
        mu, sigma = fit[eq, m]
        for i, x in enumerate(xs):
            near = [v for v in (xs[max(0, i - 30) : i] if name == "ewma" else xs[max(0, i - 7) : i + 8]) if v is not None]
            if name == "ewma":
                mid, far = mu, 2.5 * sigma
                for v in near:
                    mid = mid + 0.2 * (v - mid)
            else:
                mid = middle(near)
                far = 3.0 * (middle([abs(v - mid) for v in near]) * 1.4826)
            want[eq, i + 1, m] = None if x is None else above(abs(x - mid), far)
    more = {"memory": 30} if name == "ewma" else {}
    got = {(r["eq_id"], r["n"], r["m"]): r["flag"] for r in detect.DETECTORS[name](panel, history, **more).collect()}
    assert got == want and set(want.values()) == {True, False, None}


@pytest.mark.parametrize("name", ["ewma", "hampel", "features", "distance"])
def test_windows_run_over_points_not_readings(spark, name):
    plan = detect.DETECTORS[name](odd_panel(spark, 3), odd_panel(spark, 4))._jdf.queryExecution().optimizedPlan().toString()
    assert "Window [" not in plan and plan.index("Generate posexplode") < plan.index("InArrow")  # cells come last


def test_a_sensor_without_a_model_is_left_out(spark):
    panel = odd_panel(spark, 5)
    history = odd_panel(spark, 6).withColumn("x", F.transform("x", lambda v, m: F.when(m != 1, v))).filter("eq_id = 4")
    for name in ("ewma", "features", "distance"):
        assert {(r["eq_id"], r["m"]) for r in detect.DETECTORS[name](panel, history).select("eq_id", "m").distinct().collect()} == {(4, 0), (4, 2)}


def test_rolling_models_are_columns_not_expressions(spark):
    history = odd_panel(spark, 8).withColumn("x", F.transform("x", lambda v, m: F.when(m != 1, v)))
    rows = detect.rolling(odd_panel(spark, 7), model.fit_moments(history), 30)
    plan = rows._jdf.queryExecution().optimizedPlan().toString()
    assert "arrays_zip" not in plan and "Window [" not in plan
    assert {(len(r["x"]), len(r["mu"]), len(r["sigma"])) for r in rows.collect()} == {(2, 2, 2)}
