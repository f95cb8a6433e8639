import random
from itertools import permutations

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from unscramble.functions import perm, support
from unscramble.operators import matching, model, quantiles
from unscramble.sources import panels


def test_cycles_of_every_permutation_of_four(spark):
    rows = [(list(range(4)), list(p)) for p in permutations(range(4))]
    df = spark.createDataFrame(rows, "src array<int>, dst array<int>").withColumn("c", perm.cycles(F.col("src"), F.col("dst")))
    df = df.withColumn("back", F.array_sort(F.arrays_zip(perm.sources(F.col("c")).alias("a"), perm.targets(F.col("c")).alias("b"))))
    for r in df.collect():
        moved = [(u, v) for u, v in zip(r["src"], r["dst"], strict=True) if u != v]
        assert [tuple(x) for x in r["back"]] == moved
        assert all(c[0] == min(c) and len(c) > 1 for c in r["c"]) and r["c"] == sorted(r["c"])


def test_notation_and_undo(spark):
    df = spark.sql("SELECT '(1 2)(3 5)' AS s, array(10.0D, 20.0D, 30.0D, 40.0D, 50.0D) AS x")
    phi = perm.parse_notation(F.col("s"))
    bad = perm.gather(F.col("x"), perm.corrupt_places(phi, F.size("x")))
    r = df.select(phi.alias("phi"), bad.alias("bad"), perm.apply_cycles(bad, phi).alias("y"), perm.inverse(phi).alias("inv")).first()
    assert r["phi"] == [[0, 1], [2, 4]] and r["bad"] == [20, 10, 50, 40, 30] and r["y"] == [10, 20, 30, 40, 50] and r["inv"] == [[0, 1], [2, 4]]


def test_three_cycle_and_inverse_differ(spark):
    df = spark.sql("SELECT array(array(0, 1, 2)) AS c, array(1.0D, 2.0D, 3.0D) AS x")
    r = df.select(perm.apply_cycles(F.col("x"), F.col("c")).alias("a"), perm.apply_cycles(F.col("x"), perm.inverse(F.col("c"))).alias("b"), perm.disjoint(F.col("c"), F.lit([[3, 4]])).alias("d")).first()
    assert r["a"] == [3, 1, 2] and r["b"] == [2, 3, 1] and r["d"]


@pytest.mark.parametrize("ties", [False, True])
def test_exact_matchers_agree_with_enumeration(ties):
    g = np.random.default_rng(1)
    for _ in range(150):
        a = int(g.integers(1, 6))
        w = g.integers(0, 3, (a, a)).astype(float) if ties else g.random((a, a))
        best = min(permutations(range(a)), key=lambda p: (-round(matching.total(w, np.array(p)), 12), p))
        for f in (matching.assign, matching.flow):
            assert tuple(f(w)) == best, (w, f)
        assert matching.total(w, matching.greedy_numpy(w)) <= matching.total(w, np.array(best)) + 1e-12


def test_large_exact_matchers_have_equal_totals():
    g = np.random.default_rng(2)
    for a in (12, 24, 40):
        w = g.random((a, a)) ** 4
        one, two = matching.assign(w), matching.flow(w)
        assert sorted(one) == sorted(two) == list(range(a)) and abs(matching.total(w, one) - matching.total(w, two)) < 1e-9


def test_greedy_can_be_worse_and_zero_weights_still_match(spark):
    w = np.array([[0.9, 0.8, 0], [0.8, 0.1, 0], [0, 0, 0.5]])
    assert matching.total(w, matching.greedy_numpy(w)) == pytest.approx(1.5) and matching.total(w, matching.assign(w)) == pytest.approx(2.1)
    zero = np.zeros((3, 3))
    assert list(matching.assign(zero)) == list(matching.flow(zero)) == list(matching.greedy_numpy(zero)) == [0, 1, 2]
    df = spark.createDataFrame([(w.tolist(),), (zero.tolist(),)], "w array<array<double>>")
    got = df.select(matching.matched(F.col("w"), "greedy").alias("g"), matching.matched(F.col("w"), "enum").alias("e"), matching.matched(F.col("w"), "auto").alias("a")).collect()
    assert [list(r) for r in got] == [[[0, 1, 2], [1, 0, 2], [1, 0, 2]], [[0, 1, 2]] * 3]


def test_composition_of_permutations(spark):
    g = random.Random(11)

    def cycles_of(to):
        out, seen = [], set()
        for s in sorted(to):
            walk = [s]
            while s not in seen and to[walk[-1]] != s:
                walk.append(to[walk[-1]])
            if s not in seen and len(walk) > 1:
                out.append(walk)
            seen.update(walk)
        return out

    rows = []
    for _ in range(40):
        a, b = (dict(zip(k, g.sample(k, len(k)), strict=True)) for k in (g.sample(range(9), g.randint(0, 7)) for _ in range(2)))
        both = {u: b.get(a.get(u, u), a.get(u, u)) for u in {*a, *b}}
        rows.append((cycles_of(a), cycles_of(b), cycles_of(both)))
    df = spark.createDataFrame(rows, f"a {perm.CYCLES}, b {perm.CYCLES}, want {perm.CYCLES}")
    got = df.select(perm.compose(F.col("a"), F.col("b")).alias("got"), "want", perm.compose(F.col("a"), perm.inverse(F.col("a"))).alias("none")).collect()
    assert all(r["got"] == r["want"] and r["none"] == [] for r in got)


@pytest.mark.parametrize(("bins", "short"), [(4, 3), (16, 40), (1024, 1 << 15)])
def test_quantiles_are_exact_for_odd_readings(spark, bins, short):
    g = np.random.default_rng(3)
    groups = [g.normal(5, 2, 301), np.full(200, 7.0), np.repeat([1.0, 2.0, 9.0], [5, 90, 6]), np.array([1e308, -1e308, 3.0, 4.0, 1e-300, 5.0]), np.array([42.0])]
    rows = spark.createDataFrame([(0, m, float(x)) for m, xs in enumerate(groups) for x in xs], "eq_id long, m int, x double")
    ends = rows.groupBy("eq_id", "m").agg(F.count("*").alias("cnt"), F.min("x").alias("lo"), F.max("x").alias("hi"))
    wanted = {"q1": 0.25, "mid": 0.5, "q9": 0.9}
    want = rows.groupBy("m").agg(*[F.percentile("x", p).alias(name) for name, p in wanted.items()])
    cols = ["m", *wanted]
    got = quantiles.quantiles(rows, ends, wanted, bins, short).select(*cols)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.select(*cols).collect()))


def test_robust_models_shuffle_counts_and_not_readings(spark, monkeypatch):
    panel = spark.createDataFrame([(0, n, None, None, [float(n * n % 997), None if n % 9 else 1.0, float("nan")]) for n in range(400)], panels.PANEL)
    called = []
    monkeypatch.setattr(model, "quantiles", lambda *args: called.append(args[2]) or quantiles.quantiles(*args, 8, 20))
    got = {r["m"]: r for r in model.fit_robust(panel).collect()}
    xs = np.array([n * n % 997 for n in range(400)], float)
    assert called == [{"q1": 0.25, "mu": 0.5, "q3": 0.75}, {"gap": 0.5}] and set(got) == {0, 1}
    assert (got[0]["q1"], got[0]["mu"], got[0]["q3"]) == tuple(np.quantile(xs, [0.25, 0.5, 0.75])) and got[1]["sigma"] == 0
    assert got[0]["sigma"] == pytest.approx(1.4826 * np.median(np.abs(xs - np.median(xs))))


def test_masses_are_worked_out_once_for_each_model(spark):
    df = spark.sql("SELECT 0L AS eq_id, 0 AS m, 0.0D AS lo, 4.0D AS hi, array(0.4D, 0.1D, 0.2D, 0.3D) AS hist")
    mass = model.packed(df, ("lo", "hi", "mass")).first()["mass"][0]
    assert mass == pytest.approx([1.0, 0.1, 0.3, 0.6])
    xs = spark.createDataFrame([(x,) for x in (0.5, 1.5, 4.0, 4.1, None)], "x double").crossJoin(model.packed(df, ("lo", "hi", "mass")))
    got = [r["p"] for r in xs.select(support.empirical(F.col("x"), F.col("lo")[0], F.col("hi")[0], F.col("mass")[0]).alias("p")).collect()]
    assert got == [pytest.approx(1.0), pytest.approx(0.1), pytest.approx(0.6), support.FLOOR, None]


def test_matchings_of_batches_are_those_of_single_points(spark):
    rng = np.random.default_rng(11)
    clear = lambda a: np.log(np.eye(a)[rng.permutation(a)] * 0.9 + rng.random((a, a)) * 0.02 + 1e-9)
    all_w = [w for a in (1, 2, 3, 5, 8, 12) for _ in range(20) for w in (rng.random((a, a)), np.round(rng.random((a, a)), 1), np.ones((a, a)), clear(a))]
    rng.shuffle(all_w := [w.tolist() for w in all_w])
    rows = pa.array([*all_w, []], pa.list_(pa.list_(pa.float64())))
    for name, one in matching.MATCHERS.items():
        many = matching._batched(name)(rows).to_pylist()
        assert many == [one(np.array(w)).tolist() for w in all_w] + [[]]
    src = [sorted(rng.choice(48, a, replace=False).tolist()) for a in (0, 1, 2, 3, 5, 8, 12) for _ in range(20)]
    df = spark.createDataFrame([(s, rng.permutation(s).tolist()) for s in src], "src array<int>, dst array<int>").repartition(3)
    for r in df.select(perm.cycles(F.col("src"), F.col("dst")).alias("want"), matching.cycles(F.col("src"), F.col("dst")).alias("got")).collect():
        assert r["got"] == r["want"]


def test_only_points_whose_choices_clash_are_matched_one_by_one(monkeypatch):
    w = np.stack([np.eye(6)[::-1] + 0.01 * np.arange(6)] * 50 + [np.ones((6, 6))])
    asked = []
    to = matching.exact_many(w, lambda one: asked.append(one) or matching.assign(one))
    assert len(asked) == 1 and (to[:50] == np.arange(6)[::-1]).all() and (to[50] == np.arange(6)).all()
