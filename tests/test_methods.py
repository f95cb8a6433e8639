import pickle

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from unscramble import catalog
from unscramble.config import RepairConfig, as_printed
from unscramble.functions import support
from unscramble.operators import candidates, detect, matching, metrics, model
from unscramble.plans import methods, workloads
from unscramble.plans.operator_queries import _drain
from unscramble.plans.queries import Example, _hand
from unscramble.plans.workloads import Workbench
from unscramble.scratch import scratch_path
from unscramble.sources import inject, panels
from unscramble.sources.tables import stream_source
from unscramble.streaming.online import Online, stream_repair


@pytest.fixture(scope="module")
def easy(spark, sf):
    return Workbench(spark, "/root/testdata/sf0.01", g=3.0)


def test_injection_moves_values_only_inside_truth(spark, sf, easy):
    both = easy.clean.alias("a").join(easy.panel.alias("b"), ["eq_id", "n"]).select("n", F.col("a.x").alias("a"), F.col("b.x").alias("b")).collect()
    truth = easy.truth.collect()
    for r in both:
        assert sorted(r["a"]) == sorted(r["b"])
        phi = next((t["phi"] for t in truth if t["l"] <= r["n"] <= t["r"]), [])
        assert {m for m in range(48) if r["a"][m] != r["b"][m]} <= {s for c in phi for s in c}


def test_intervals_of_the_plan_never_overlap(spark):
    for last in (12, 157, 500, 1578, 5000, 15789, 50000):
        ends = spark.createDataFrame([(0, last)], "eq_id long, last long")
        rows = sorted((r["l"], r["r"]) for r in inject.plan(ends).collect())
        assert all(1 <= l <= r <= last for l, r in rows) and all(a[1] < b[0] for a, b in zip(rows, rows[1:]))


@pytest.mark.parametrize("method", ["full", "greedy"])
def test_easy_panel_is_restored(spark, easy, method):
    cfg = RepairConfig(method=method)
    got = methods.repair(easy.panel, easy.models, cfg, 1)
    s = methods.evaluated(got, easy.truth, cfg).first()
    assert s["n_correct"] == s["n_true"] == s["n_repaired"]
    cells = metrics.cell_scores(easy.clean, easy.panel, got.repaired).first()
    assert cells["restored_share"] == 1.0 and cells["n_damaged"] == 0


def test_sensors_outside_stay_and_values_only_move(spark, easy):
    got = methods.repair(easy.panel, easy.models, RepairConfig(), 1)
    rows = got.repaired.alias("a").join(easy.panel.alias("b"), ["eq_id", "n"]).select(F.array_sort("a.x").alias("a"), F.array_sort("b.x").alias("b"))
    assert rows.filter("a <> b").count() == 0


def test_trend_full_is_at_least_candidate(spark):
    b = Workbench(spark, "/root/testdata/sf0.01", 12, g=2.0)
    score = {m: methods.evaluated(methods.repair(b.panel, b.models, RepairConfig(method=m), 1), b.truth, RepairConfig()).first() for m in ("full", "candidate")}
    assert score["full"]["p_d"] > score["candidate"]["p_d"] and score["full"]["r_d"] >= score["candidate"]["r_d"]


def test_escalated_points_stay_and_single_ones_are_untouched(spark, sf):
    e = Example(spark, sf)
    got = candidates.candidate_schemas(e.bad, e.models, RepairConfig(epsilon=3, match="enum"), 1)
    rows = got.collect()
    assert {r["status"] for r in rows} >= {"single", "repaired"}
    assert all((r["status"] == "escalated") == (len(r["abnormal"]) > 3) for r in rows)
    assert all(r["cycles"] == [] for r in rows if r["status"] != "repaired")


def test_feedback_in_chunks_is_the_sequential_result(spark, sf):
    e = Example(spark, sf)
    m = {r["m"]: r for r in e.models.collect()}
    mu, sigma = [m[i]["mu"] for i in range(5)], [m[i]["sigma"] for i in range(5)]
    for cfg in (RepairConfig(mode="feedback", window=40), RepairConfig(mode="feedback", window=25, update_policy="guarded")):
        want = candidates.sequential(sorted((r["n"], r["x"]) for r in e.bad.collect()), mu, sigma, cfg)
        for chunk, run_in in ((64, 80), (97, 10)):
            got = candidates.feedback_candidates(e.bad, e.models, cfg, chunk, run_in).select("n", "abnormal", "src", "dst", "size", "status").collect()
            assert sorted(map(tuple, got)) == sorted((n, a, s, d, k, t) for n, a, s, d, k, t in want)


def test_cumulative_update_runs_in_one_chunk(spark, sf):
    e = Example(spark, sf)
    got = candidates.feedback_candidates(e.bad, e.models, RepairConfig(mode="feedback", update="cumulative"))
    assert got.count() > 0


def test_hand_made_scores(spark):
    s = metrics.scores(*_hand(spark)).first()
    assert (s["p_d"], s["r_d"], s["p_r"], s["r_r"]) == (0.8, 0.8, 0.75, 0.6) and s["r_r"] <= s["p_r"]
    empty = _hand(spark)[0].limit(0)
    assert metrics.scores(empty, empty).first()["p_d"] is None


def test_unknown_readings_are_never_abnormal(spark):
    panel = spark.createDataFrame([(0, 1, None, None, [None, float("nan"), 99.0])], panels.PANEL)
    models = spark.createDataFrame([(0, m, 10, 0.0, 1.0, -1.0, 1.0) for m in range(3)], "eq_id long, m int, cnt long, mu double, sigma double, lo double, hi double")
    assert detect.flag(panel, models, equipments=1).first()["abnormal"] == [2]


def test_empty_panel(spark, sf):
    e = Example(spark, sf)
    got = methods.repair(e.bad.limit(0), e.models, RepairConfig(), 1)
    assert got.schemas.count() == 0 and got.repaired.count() == 0


def test_equipments_are_independent(spark, sf):
    p = panels.calibrated_panel(spark, sf, 3.0, equipments=2)
    bad = inject.inject(p, inject.plan(inject.extent(p)))
    models = model.fit_moments(panels.calibrated_panel(spark, sf, 3.0, history=True, equipments=2))
    both = methods.repair(bad, models, RepairConfig(len1=10, len2=10)).schemas.collect()
    one = methods.repair(bad.filter("eq_id = 1"), models.filter("eq_id = 1"), RepairConfig(len1=10, len2=10)).schemas.collect()
    assert sorted((r["l"], r["r"], r["phi"]) for r in both if r["eq_id"] == 1) == sorted((r["l"], r["r"], r["phi"]) for r in one)


def test_as_printed_erases_isolated_intervals(spark, sf):
    e = Example(spark, sf)
    got = methods.repair(e.bad, e.models, as_printed().with_(len1=5, len2=5), 1)
    assert got.schemas.count() == 0


def test_scoring_and_applying_never_shuffle_the_panel(spark, easy):
    flags = detect.flag(easy.panel, easy.models, equipments=1)
    plan = flags._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Cartesian" not in plan
    above = plan.split("BroadcastExchange")[0]
    assert "Exchange hashpartitioning" not in above and "Exchange rangepartitioning" not in above


def test_stream_gives_the_batch_recursion(spark, sf):
    e = Example(spark, sf)
    m = {r["m"]: r for r in e.models.collect()}
    mu, sigma = [m[i]["mu"] for i in range(5)], [m[i]["sigma"] for i in range(5)]
    cfg = RepairConfig(mode="feedback", window=40)
    rows = sorted((r["n"], r["x"]) for r in e.bad.collect())
    want = candidates.sequential(rows, mu, sigma, cfg)
    live = Online(mu, sigma, cfg)
    order = np.random.default_rng(0).permutation(len(rows))
    for i in order:
        live.arrive(rows[i][0], rows[i][1])
    out = live.finish()
    assert sorted({r[1] for r in out if r[0] == "candidate"}) == [w[0] for w in want]
    path = scratch_path(spark, "tuples")
    spaced = e.bad.withColumn("ts", F.timestamp_seconds(F.col("n") * 60)).select("eq_id", "ts", "x")
    for k in range(3):  # files arrive in order of time
        spaced.filter(F.floor(F.unix_seconds("ts") / 60 / 200) == k).coalesce(1).write.mode("append").parquet(path)
    got = _drain(stream_repair(stream_source(spark, path, spaced.schema), mu, sigma, cfg, "1 hour")).filter("kind = 'candidate'").select("n").distinct().collect()
    seen = {r["n"] for r in got}
    assert seen and seen <= {w[0] for w in want}  # the rest waits for the watermark
    two = spaced.unionByName(spaced.withColumn("eq_id", F.lit(1).cast("long")).withColumn("x", F.transform("x", lambda v: v + 1000)))
    other = scratch_path(spark, "tuples")
    for k in range(3):
        two.filter(F.floor(F.unix_seconds("ts") / 60 / 200) == k).coalesce(1).write.mode("append").parquet(other)
    both = e.models.unionByName(e.models.withColumn("eq_id", F.lit(1).cast("long")).withColumn("mu", F.col("mu") + 1000))
    got = _drain(stream_repair(stream_source(spark, other, two.schema), None, None, cfg, "1 hour", models=both)).filter("kind = 'candidate'").select("eq_id", "n").distinct().collect()
    assert all({r["n"] for r in got if r["eq_id"] == k} == seen for k in (0, 1))  # each by its own models


def test_streamed_intervals_wait_for_the_end_or_for_the_longest_run(spark, sf):
    e = Example(spark, sf)
    m = {r["m"]: r for r in e.models.collect()}
    rows = sorted((r["n"], r["x"]) for r in e.bad.collect())
    found = {}
    for most in (None, 10_000, 200):
        live = Online([m[i]["mu"] for i in range(5)], [m[i]["sigma"] for i in range(5)], RepairConfig(mode="feedback", window=40, len2=5), most)
        for n, x in rows:
            live.arrive(n, x)
        found[most] = sorted(r[2:5] for r in live.finish() if r[0] == "interval")
    assert found[None] and found[None] == found[10_000]


NAMES = [
    "panel_calibrated_stats", "inject_truth", "models_moments", "models_robust", "models_hist", "flags_frozen_chebyshev", "flags_frozen_tail", "weights_long", "match_enum", "match_exact", "match_greedy",
    "cycles", "units_kept", "tau_sigma", "smooth_snapshot", "intervals_full", "overlay_final", "repaired_cells", "block_means", "bit_confusion_smoothed", "ordinal_index", "interval_join", "asof_align", "udtf_runs", "sql_match",
]


@pytest.mark.parametrize("name", NAMES)
def test_query_and_sql_agree(spark, sf, name):
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df = catalog.queries()[name](spark, sf)
    cols = sorted(df.columns)
    rel = con.sql(catalog.oracle_sql()[name])
    assert sorted(rel.columns) == cols
    norm = lambda v: round(v, 6) + 0.0 if isinstance(v, float) else v.replace(tzinfo=None) if hasattr(v, "tzinfo") else v
    got = sorted((tuple(norm(r[c]) for c in cols) for r in df.collect()), key=repr)
    want = sorted((tuple(norm(r[rel.columns.index(c)]) for c in cols) for r in rel.fetchall()), key=repr)
    assert got == want


def test_feedback_has_the_families_it_takes(spark):
    z = np.linspace(-9, 9, 37)
    df = spark.createDataFrame([(float(v),) for v in z], "z double")
    for name, f in support.FAMILIES.items():
        want = [r["p"] for r in df.select(f(F.col("z")).alias("p")).collect()]
        assert np.allclose(sorted(candidates._support(z, name)), sorted(want), rtol=1e-9, atol=0)
    with pytest.raises(ValueError, match="empirical"):
        candidates._support(z, "empirical")


def test_auto_matches_exactly_beyond_64_sensors(spark):
    w = np.random.default_rng(5).random((70, 70))
    df = spark.createDataFrame([(w.tolist(),)], "w array<array<double>>")
    to = np.array(df.select(matching.matched(F.col("w")).alias("to")).first()["to"])
    assert (to == matching.assign(w)).all() and matching.total(w, to) > matching.total(w, matching.greedy_numpy(w))
    x = np.random.default_rng(6).normal(5, 40, 70)
    _, dst, _ = candidates.Feedback(np.zeros(70), np.ones(70), RepairConfig(size_mode="moved", theta_m=1.1), np.zeros((0, 70))).step(x)
    assert (dst == matching.assign(candidates._support(np.tile(x[:, None], 70), "chebyshev"))).all()


@pytest.mark.parametrize(("name", "points"), [("w4_volume", (40, 50, 60, 70, 80, 90, 100)), ("w6_attributes", (3, 6, 9, 12, 15, 18))])
def test_registered_sweeps_have_all_points(spark, sf, monkeypatch, name, points):
    class Stub:
        def __init__(self, *args, **options):
            pass

        def run(self, workload, method, x):
            return (workload, method, float(x), 0, 0, 0, 0, *[0.0] * 7)

    monkeypatch.setattr(workloads, "Workbench", Stub)
    got = {(r["method"], r["x"]) for r in catalog.queries()[name](spark, sf).collect()}
    assert got == {(m, float(x)) for m in methods.METHODS for x in points}


def test_every_sql_text_has_its_query():
    assert set(catalog.oracle_sql()) <= set(catalog.queries())


FROM_PARTS = ["bound_error_hand", "cycle_scores_hand", "cycle_text", "interval_overlap", "score_outer", "scores_hand", "scores_hand_alt"]


@pytest.mark.parametrize("name", FROM_PARTS)
def test_queries_of_parts_read_the_table(spark, sf, name):
    df = catalog.queries()[name](spark, sf)
    assert any(f.endswith("/part.parquet") for f in df.inputFiles())
    test_query_and_sql_agree(spark, sf, name)


def test_sweeps_build_their_panel_once(spark, sf, monkeypatch):
    built, real = [], panels.calibrated_panel
    monkeypatch.setattr(panels, "calibrated_panel", lambda *a, **k: built.append(k) or real(*a, **k))
    monkeypatch.setattr(Workbench, "run", lambda self, workload, method, x: (workload, method, float(x), *[0] * 4, *[0.0] * 7))
    workloads.by_volume(spark, sf, ["full"], [40, 100])
    workloads.by_attributes(spark, sf, ["full"], [3, 6])
    assert len(built) == 4  # readings and history of each sweep
    one, two = Workbench(spark, sf, 6, percent=90), Workbench(spark, sf, 6, source=workloads.Source(spark, sf, percent=90))
    for a, b in ((one.panel, two.panel), (one.truth, two.truth), (one.history, two.history)):
        assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def test_waiting_readings_are_taken_in_one_cut():
    class Counted(list):
        def pop(self, *at):
            raise AssertionError("moves all that wait")

    live = Online([0.0, 9.0], [1.0, 1.0], RepairConfig(mode="feedback", len2=1), None)
    live.waiting = Counted([(t, [9.0, 0.0] if t in (3, 4) else [0.0, 9.0]) for t in (5, 3, 1, 2, 4, 6)])
    got = live.advance(5)
    assert [r[1] for r in got if r[0] == "candidate"] == [3, 4] and live.done == 5 and [t for t, _ in live.waiting] == [6]


def test_detectors_are_counted_one_by_one_without_joining_cells(spark, sf, monkeypatch):
    names, stored = [], workloads.stored
    monkeypatch.setattr(workloads, "stored", lambda df, name: names.append(name) or stored(df, name))
    some = ["ksigma", "jump", "features"]
    rows = {r["detector"]: r for r in workloads.detectors(spark, sf, some).collect()}
    assert names.count("detector") == 3 and "cells" not in names
    b = Workbench(spark, sf)
    cells = {(r["n"], m): u != v for r in b.panel.join(b.clean.select("n", F.col("x").alias("t")), "n").collect() for m, (u, v) in enumerate(zip(r["x"], r["t"], strict=True))}
    for name in some:
        flags = [(cells[r["n"], r["m"]], r["flag"]) for r in detect.DETECTORS[name](b.panel, b.history).select("n", "m", "flag").collect()]
        hit, bad, flagged = sum(c and f for c, f in flags), sum(c for c, _ in flags), sum(f for _, f in flags)
        assert bad and tuple(rows[name]) == (name, bad, hit, flagged - hit, hit / bad, hit / flagged if flagged else None)


def test_runs_on_one_workbench_share_candidates(spark, sf, monkeypatch):
    made, make = [], candidates.candidate_schemas
    monkeypatch.setattr(candidates, "candidate_schemas", lambda panel, models, cfg, *a, **k: made.append(cfg) or make(panel, models, cfg, *a, **k))
    b = Workbench(spark, sf)
    few = {"full": RepairConfig(), "greedy": RepairConfig(), "candidate": RepairConfig(), "kernel": RepairConfig(family="kernel", theta_m=0.02), "cut": RepairConfig(len1=0, merge="snapshot", tau_mode="symmetric", len2=1)}
    got = {k: b.run("w", k if k in methods.METHODS else "full", 0, v) for k, v in few.items()}
    assert len(made) == 3
    for k in ("greedy", "cut"):
        cfg = few[k].with_(method=got[k][1])
        assert got[k][3:-1] == tuple(methods.evaluated(methods.repair(b.panel, b.models, cfg), b.truth, cfg).first())


def test_overall_orders_the_items_once(spark, sf, monkeypatch):
    orders, place = [], panels.with_ordinal
    monkeypatch.setattr(panels, "with_ordinal", lambda df, order, *a: orders.append(order) or place(df, order, *a))
    assert [r["x"] for r in workloads.overall(spark, sf, ("block",)).collect()] == [48.0, 150.0]
    assert sorted(orders) == sorted([panels.ROW_ORDER, panels.HISTORY_ORDER])


def _one_by_one(xs, mu, sigma, cfg, window):
    state, want = candidates.Feedback(mu, sigma, cfg, window), []
    for i, x in enumerate(xs):
        ab, dst, status = state.step(x)
        if len(ab):
            want.append((i, ab.tolist(), dst.tolist(), status))
    return state, want


@pytest.mark.parametrize(
    "more",
    [{}, {"update": "cumulative"}, {"update_policy": "guarded"}, {"family": "kernel", "theta_m": 0.02}, {"family": "tail", "theta_m": 0.005}, {"size_mode": "moved", "epsilon": 2}, {"objective": "log"}, {"method": "greedy"}, {"epsilon": 2}, {"window": 3}],
)
def test_blocks_of_feedback_are_steps(more):
    rng = np.random.default_rng(8)
    mu, sigma, cfg = np.arange(6) * 4.0, np.full(6, 1.2), RepairConfig(mode="feedback").with_(**{"window": 40, **more})
    xs = rng.normal(mu, 1.2, (900, 6)) + np.linspace(0, 3, 900)[:, None]
    xs[200:420] = xs[200:420][:, [1, 0, 2, 4, 5, 3]]
    xs[600:640] = xs[600:640, ::-1]
    xs[rng.random(xs.shape) < 0.01] += 9.0
    xs[rng.random(xs.shape) < 0.01] = np.nan
    start = rng.normal(mu, 1.2, (min(25, cfg.window), 6))
    one, want = _one_by_one(xs, mu, sigma, cfg, start)
    many = candidates.Feedback(mu, sigma, cfg, start)
    got = [(i, ab, dst if status == "repaired" or dst else [], status) for i, ab, dst, status in many.steps(xs[:333])]
    got += [(i + 333, *f) for i, *f in many.steps(xs[333:])]
    assert got == want and {f[-1] for f in got} >= {"single", "repaired"}
    assert (np.array(one.rows) == np.array(many.rows)).all() and (one.s == many.s).all() and (one.ss == many.ss).all() and one.k == many.k


def test_feedback_takes_points_in_blocks(monkeypatch):
    calls, real = [], candidates.Feedback._block
    monkeypatch.setattr(candidates.Feedback, "_block", lambda self, x, guess: calls.append(len(x)) or real(self, x, guess))
    mu, sigma, cfg = np.arange(5) * 9.0, np.ones(5), RepairConfig(mode="feedback", theta_m=0.05)
    xs = np.random.default_rng(3).normal(mu, 1.0, (20_000, 5))
    xs[8000:12000] = xs[8000:12000][:, [1, 0, 4, 3, 2]]
    candidates.run_feedback(np.arange(20_000), xs, mu, sigma, cfg, np.zeros((0, 5)))
    assert len(calls) < 1000


def test_state_of_a_stream_keeps_what_waits():
    live = Online([0.0, 9.0], [1.0, 1.0], RepairConfig(), None)
    for t in range(2000):
        live.arrive(t, [0.1 * t, None if t == 5 else 9.0])
    blob = pickle.dumps(live)
    back = pickle.loads(blob)
    assert len(blob) < 2000 * 25 and back.waiting[:5] == live.waiting[:5] and len(back.waiting) == 2000
    assert back.finish() == live.finish()
