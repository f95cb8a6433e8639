import random

import pytest
from pyspark.sql import functions as F

from tests.ref.strict import strict_order
from unscramble.config import RepairConfig
from unscramble.operators import determine, runs
from unscramble.plans.operator_queries import check_runs


def one_runs(spark, bits):
    return sorted((r["l"], r["r"]) for r in check_runs(spark, bits).collect())


@pytest.mark.parametrize("bits", [[1], [0], [1, 0] * 10, [1] * 9, [0] * 9, [0, 1, 1, 0, 0, 1], [1] * 5000 + [0] + [1] * 5000])
def test_islands_are_what_union_find_gives(spark, bits):
    assert one_runs(spark, bits) == [(l, r) for b, l, r in runs.runs_union_find(bits) if b]


def smoothed(spark, bits, **kw):
    last = spark.createDataFrame([(0, len(bits))], "eq_id long, last long")
    got = runs.smooth(check_runs(spark, bits), last, **kw)
    return sorted((r["l"], r["r"]) for r in got.collect())


def test_isolated_run_survives_only_when_guarded(spark):
    bits = [0] * 300 + [1] * 60 + [0] * 300
    for merge in ("two_pass", "snapshot", "progressive"):
        assert smoothed(spark, bits, mode="guarded", merge=merge) == [(301, 360)]
        assert smoothed(spark, bits, mode="symmetric", merge=merge) == []


def test_short_gap_is_filled_and_edge_runs_are_never_middles(spark):
    bits = [1] * 40 + [0] * 5 + [1] * 40 + [0] * 100 + [1] * 3
    for merge in ("two_pass", "snapshot", "progressive"):
        assert smoothed(spark, bits, merge=merge) == [(1, 85), (186, 188)]


def test_alternating_bits_are_not_inverted(spark):
    got = smoothed(spark, [1, 0] * 20, theta=0.6, len2=3)
    assert got == [(1, 39)]


def test_tau_values(spark):
    last = spark.createDataFrame([(0, 12)], "eq_id long, last long")
    got = runs.with_tau(runs.all_runs(check_runs(spark, [0, 0, 1, 1, 1, 1, 0, 1, 0, 0, 0, 0]), last)).orderBy("l").collect()
    assert [(r["bit"], r["len"]) for r in got] == [(0, 2), (1, 4), (0, 1), (1, 1), (0, 4)]
    assert [r["tau"] for r in got] == [None, 4 / 3, 1 / 5, 1 / 5, None]


def test_waves_give_the_strict_order(spark):
    g = random.Random(5)
    cycles = [(0, 1), (1, 2), (0, 2, 3), (3, 4), (4, 5), (5, 6), (2, 6)]
    for trial in range(3):
        last, points = 400, {}
        for c in cycles:
            mine = set()
            for _ in range(g.randint(1, 3)):
                at, n = g.randint(1, 330), g.randint(15, 70)
                mine.update(p for p in range(at, at + n) if g.random() > 0.12)
            points[c] = mine
        rows = [(0, n, [list(c) for c in cycles if n in points[c]]) for n in range(1, last + 1)]
        found = spark.createDataFrame(rows, "eq_id long, n long, cycles array<array<int>>").filter(F.size("cycles") > 0)
        cfg = RepairConfig(len1=10, len2=8, theta_tau=0.3)
        done = determine.determine(found, spark.createDataFrame([(0, last)], "eq_id long, last long"), cfg)
        got = {}
        for r in done.intervals.collect():
            got.setdefault(tuple(map(int, r["sigma"].split(">"))), []).append((r["l"], r["r"]))
        assert {c: sorted(v) for c, v in got.items()} == strict_order(points, last, 10, 8, 0.3), trial
        schemas = sorted((r["l"], r["r"], r["phi"]) for r in done.schemas.collect())
        for (_, r1, p1), (l2, _, p2) in zip(schemas, schemas[1:]):
            assert r1 < l2 and not (r1 + 1 == l2 and p1 == p2)
        for _, _, phi in schemas:
            sensors = [s for c in phi for s in c]
            assert len(sensors) == len(set(sensors))  # no cell is repaired twice


@pytest.mark.parametrize("merge, mode, theta", [("two_pass", "guarded", 0.3), ("snapshot", "guarded", 0.4), ("progressive", "symmetric", 0.4)])
def test_one_task_and_waves_agree_and_one_task_stores_no_wave(spark, monkeypatch, merge, mode, theta):
    g = random.Random(11)
    cycles = [[0, 1], [1, 2], [0, 2, 3], [3, 4], [2, 4]]
    rows = []
    for eq, last in ((0, 300), (1, 260)):
        on = [[False] * (last + 2) for _ in cycles]
        for mine in on:
            for _ in range(3):
                at, n = g.randint(1, last - 50), g.randint(10, 50)
                for p in range(at, at + n):
                    mine[p] = g.random() > 0.15
        rows += [(eq, n, [c for c, mine in zip(cycles, on, strict=True) if mine[n]]) for n in range(1, last + 1)]
    found = spark.createDataFrame(rows, "eq_id long, n long, cycles array<array<int>>").filter(F.size("cycles") > 0).cache()
    last = spark.createDataFrame([(0, 300), (1, 260)], "eq_id long, last long")
    cfg = RepairConfig(len1=10, len2=5, theta_tau=theta, merge=merge, tau_mode=mode)
    by_wave = determine.determine(found, last, cfg, held=0)
    names, stored = [], determine.stored
    monkeypatch.setattr(determine, "stored", lambda df, name: names.append(name) or stored(df, name))
    at_once = determine.determine(found, last, cfg)
    assert by_wave.waves > 1 and at_once.waves == 0 and "wave" not in names
    rows_of = lambda df: sorted(tuple(map(str, r)) for r in df.collect())
    assert rows_of(at_once.intervals) and rows_of(at_once.intervals) == rows_of(by_wave.intervals)
    assert rows_of(at_once.schemas) == rows_of(by_wave.schemas) and rows_of(at_once.units) == rows_of(by_wave.units)


def test_plans_of_waves_do_not_grow(spark, monkeypatch):
    sizes, evaluate = [], determine.evaluate_intervals

    def seen(points, last, cfg, claims=None):
        if claims is not None:
            sizes.append(claims._jdf.queryExecution().analyzed().toString().count("Relation"))
        return evaluate(points, last, cfg, claims)

    monkeypatch.setattr(determine, "evaluate_intervals", seen)
    found = spark.createDataFrame([(0, n, [[k, k + 1]]) for k in range(4) for n in range(1 + k, 100, 1 + k // 2)], "eq_id long, n long, cycles array<array<int>>")
    done = determine.determine(found, spark.createDataFrame([(0, 100)], "eq_id long, last long"), RepairConfig(len1=1, len2=1, merge="progressive"), held=0)
    assert done.waves > 2 and set(sizes) == {1}
