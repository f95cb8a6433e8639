"""Behaviour models of sensors, learned from history by distributed aggregation.

A model table has a row for each (eq_id, m): cnt, mu, sigma, lo, hi, and what its family adds. packed() turns it into
one row of arrays for each equipment, which is what scoring joins with.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from unscramble.functions.support import masses
from unscramble.operators.intervals import interval_join
from unscramble.operators.quantiles import quantiles
from unscramble.operators.stretched import Tile, above, long, null, over_stretches, with_last
from unscramble.scratch import few, stored
from unscramble.sources.panels import to_long

KEYS = ("eq_id", "m")


def _known(panel: DataFrame) -> DataFrame:
    return to_long(panel).filter(F.col("x").isNotNull() & ~F.isnan("x"))


def _read_twice(panel: DataFrame) -> DataFrame:
    """Known readings (eq_id, m, x) of a panel that is stored first, as they are read more than once."""
    narrow = stored(panel.select("eq_id", "x"), "readings")
    return narrow.select("eq_id", F.posexplode("x").alias("m", "x")).filter("x IS NOT NULL AND NOT isnan(x)")


def fit_moments(panel: DataFrame, regime: bool = False) -> DataFrame:
    """Mean, standard deviation and range. With regime, one model for each working condition."""
    return _moments(_known(panel), (*KEYS, "regime") if regime else KEYS)


def _moments(known: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    x = F.col("x")
    aggs = [F.count("*").alias("cnt"), F.avg(x).alias("mu"), F.coalesce(F.stddev_samp(x), F.lit(0.0)).alias("sigma"), F.min(x).alias("lo"), F.max(x).alias("hi")]
    return known.groupBy(*keys).agg(*aggs)


def models_from_table(given: DataFrame) -> DataFrame:
    """Models that are known beforehand (eq_id, m, mu, sigma; cnt, lo, hi and hist where there are any)."""
    if missing := {*KEYS, "mu", "sigma"} - set(given.columns):
        raise ValueError(f"given models lack {', '.join(sorted(missing))}")
    more = {"cnt": "long", "lo": "double", "hi": "double"}
    rest = [(F.col(c) if c in given.columns else F.lit(None)).cast(kind).alias(c) for c, kind in more.items()]
    hist = [F.col("hist").cast("array<double>").alias("hist")] if "hist" in given.columns else []
    return given.select(F.col("eq_id").cast("long").alias("eq_id"), F.col("m").cast("int").alias("m"), *[F.col(c).cast("double").alias(c) for c in ("mu", "sigma")], *rest, *hist)


def fit_robust(panel: DataFrame, approximate: bool = False) -> DataFrame:
    """Median and scaled median absolute deviation in the place of mean and deviation; quartiles beside them.

    approximate: percentile sketches, which merge before the shuffle, in the place of exact quantiles.
    """
    x = F.col("x")
    if approximate:
        q = lambda c, p: F.percentile_approx(c, p, 10_000)
        long = _known(panel)
        mid = long.groupBy(*KEYS).agg(q("x", 0.5).alias("mu"), q("x", 0.25).alias("q1"), q("x", 0.75).alias("q3"), F.count("*").alias("cnt"), F.min("x").alias("lo"), F.max("x").alias("hi"))
        mid = few(mid, "medians")
        off = long.join(mid.select(*KEYS, "mu"), list(KEYS)).groupBy(*KEYS).agg((q(F.abs(x - F.col("mu")), 0.5) * 1.4826).alias("sigma"))
    else:
        long = _read_twice(panel)
        ends = few(long.groupBy(*KEYS).agg(F.count("*").alias("cnt"), F.min("x").alias("lo"), F.max("x").alias("hi")), "ends")
        mid = few(ends.join(quantiles(long, ends, {"q1": 0.25, "mu": 0.5, "q3": 0.75}), list(KEYS)), "medians")
        gaps = long.join(mid.select(*KEYS, "mu"), list(KEYS)).select(*KEYS, F.abs(x - F.col("mu")).alias("x"))
        far = F.greatest(F.col("hi") - F.col("mu"), F.col("mu") - F.col("lo"))
        off = quantiles(gaps, mid.select(*KEYS, "cnt", F.lit(0.0).alias("lo"), far.alias("hi")), {"gap": 0.5}).select(*KEYS, (F.col("gap") * 1.4826).alias("sigma"))
    return mid.join(off, list(KEYS)).select(*KEYS, "cnt", "mu", "sigma", "lo", "hi", "q1", "q3")


def fit_hist(panel: DataFrame, bins: int = 20) -> DataFrame:
    """Shares of equal-width bins between least and greatest value, beside the moments."""
    long = _read_twice(panel)
    base = few(_moments(long, KEYS), "moments")
    cell = F.least(F.floor((F.col("x") - F.col("lo")) / F.when(F.col("hi") > F.col("lo"), F.col("hi") - F.col("lo")).otherwise(1.0) * bins).cast("int"), F.lit(bins - 1))
    counted = long.join(base.select(*KEYS, "lo", "hi"), list(KEYS)).groupBy(*KEYS, cell.alias("bin")).agg(F.count("*").alias("c"))
    full = counted.groupBy(*KEYS).agg(F.map_from_entries(F.collect_list(F.struct("bin", "c"))).alias("by_bin"))
    share = F.transform(F.sequence(F.lit(0), F.lit(bins - 1)), lambda b: F.coalesce(F.try_element_at("by_bin", b), F.lit(0)).cast("double") / F.col("cnt"))
    return base.join(full, list(KEYS)).select(*base.columns, share.alias("hist"))


def fit_ar1(panel: DataFrame) -> DataFrame:
    """Slope and intercept of a reading on the one before, and the deviation of what is left."""
    pairs = with_last(panel).filter("p IS NOT NULL AND x IS NOT NULL AND NOT isnan(x) AND NOT isnan(p)")
    fit = pairs.groupBy(*KEYS).agg(F.coalesce(F.regr_slope("x", "p"), F.lit(0.0)).alias("slope"), F.avg("x").alias("mx"), F.avg("p").alias("mp"), F.count("*").alias("cnt"))
    fit = few(fit.select(*KEYS, "cnt", "slope", (F.col("mx") - F.col("slope") * F.col("mp")).alias("intercept")), "lines")
    rest = pairs.join(fit, list(KEYS)).groupBy(*KEYS).agg(F.stddev_samp(F.col("x") - F.col("slope") * F.col("p") - F.col("intercept")).alias("sigma"))
    return fit.join(rest, list(KEYS))


def window_features(panel: DataFrame, q: int, far: DataFrame | None = None, k: float = 0.0) -> DataFrame:
    """Mean, deviation, slope, least and greatest of the last q readings of a sensor, where all q are known.

    far: features of a history (fit_features); a column flag says then whether one is more than k deviations off.
    """

    judged = far is not None

    def compute(t: Tile) -> dict[str, np.ndarray]:
        t.known = t.known & ~np.isnan(t.x)
        t.whole = bool(t.known.all())
        s, n = t.total(1 - q, 0)
        mean, m2 = np.zeros_like(s), np.zeros_like(s)
        lo, hi = np.full_like(s, np.inf), np.full_like(s, -np.inf)
        st, stt, stx = np.zeros_like(s), np.zeros_like(s), np.zeros_like(s)
        for i, step in enumerate(range(1 - q, 1), 1):
            x, _ = t.at(step)
            off = x - mean
            by_n = off / i
            mean = mean + by_n
            m2 = m2 + off * (off - by_n)
            lo, hi = np.fmin(lo, x), np.fmax(hi, x)
            time = (t.n + step)[:, None].astype(float)
            st, stt, stx = st + time, stt + time * time, stx + time * x
        bottom = n * stt - st * st
        out = {"f_mean": s / n, "f_sd": np.sqrt(m2 / (q - 1.0)), "f_slope": null((n * stx - st * s) / bottom, bottom == 0), "f_lo": lo, "f_hi": hi, "_all": n == q}
        if q == 1:
            out["f_sd"] = null(out["f_sd"], True)
        if judged:
            hits = [above(np.abs(np.ma.getdata(out[c]) - t.models[f"{c}_mu"]), k * t.models[f"{c}_sigma"]) & ~np.ma.getmaskarray(out[c]) & ~t.unset(f"{c}_mu") & ~t.unset(f"{c}_sigma") for c in FEATURES]
            out["flag"] = np.logical_or.reduce(hits)
        return out

    fields = dict.fromkeys(FEATURES, "double") | {"_all": "boolean"} | ({"flag": "boolean"} if judged else {})
    return long(over_stretches(panel, q - 1, 0, fields, compute, far)).filter("_all").drop("_all")


def gaps(panel: DataFrame, q: int, levels: DataFrame, known: bool = False) -> DataFrame:
    """Long rows with the root mean square gap of a sensor's last q readings to its level mu. known: NaN counts as unknown."""

    def compute(t: Tile) -> dict[str, np.ndarray]:
        if known:
            t.known = t.known & ~np.isnan(t.x)
            t.whole = bool(t.known.all())
        s, n = t.total(1 - q, 0, lambda x: (x - t.models["mu"]) ** 2)
        return {"gap": null(np.sqrt(s / n), n == 0), "mu": np.broadcast_to(t.models["mu"], s.shape)}

    return long(over_stretches(panel, q - 1, 0, {"gap": "double", "mu": "double"}, compute, levels))


FEATURES = ("f_mean", "f_sd", "f_slope", "f_lo", "f_hi")


def fit_features(panel: DataFrame, q: int = 10) -> DataFrame:
    """Mean and deviation of each window feature over the history."""
    feats = window_features(panel, q)
    return feats.groupBy(*KEYS).agg(*[f(c).alias(f"{c}_{s}") for c in FEATURES for f, s in ((F.avg, "mu"), (F.stddev_samp, "sigma"))])


def fit_profile(panel: DataFrame, q: int = 10) -> DataFrame:
    """Reference for subsequence distances: the mean level, and the usual root mean square gap of q readings to it."""
    base = few(fit_moments(panel).select(*KEYS, "mu"), "levels")
    rows = gaps(panel, q, base, known=True).filter("x IS NOT NULL AND NOT isnan(x)")
    return rows.groupBy(*KEYS).agg(F.first("mu").alias("mu"), F.avg("gap").alias("gap_mu"), F.stddev_samp("gap").alias("gap_sigma"))


def without_intervals(panel: DataFrame, bad: DataFrame) -> DataFrame:
    """History without intervals that are known to be wrong (eq_id, l, r)."""
    return interval_join(panel, bad, how="left_anti")


def sampled(panel: DataFrame, one_in: int) -> DataFrame:
    """The same one_in-th of the history in every run."""
    return panel.filter(F.pmod(F.xxhash64("eq_id", "n"), F.lit(one_in)) == 0)


def merge_moments(a: DataFrame, b: DataFrame) -> DataFrame:
    """Models of two disjoint histories made into the models of both, without reading either again."""
    def m2(df: DataFrame) -> DataFrame:
        return df.select(*KEYS, "cnt", "mu", (F.col("sigma") ** 2 * (F.col("cnt") - 1)).alias("m2"), "lo", "hi")

    both = m2(a).unionByName(m2(b)).groupBy(*KEYS).agg(
        F.sum("cnt").alias("cnt"), (F.sum(F.col("cnt") * F.col("mu")) / F.sum("cnt")).alias("mu"),
        F.sum("m2").alias("m2"), F.sum(F.col("cnt") * F.col("mu") * F.col("mu")).alias("s2"), F.min("lo").alias("lo"), F.max("hi").alias("hi"),
    )
    total = F.col("m2") + F.col("s2") - F.col("cnt") * F.col("mu") * F.col("mu")
    return both.select(*KEYS, "cnt", "mu", F.when(F.col("cnt") > 1, F.sqrt(F.greatest(total, F.lit(0.0)) / (F.col("cnt") - 1))).otherwise(0.0).alias("sigma"), "lo", "hi")


def packed(models: DataFrame, columns: tuple[str, ...] = ("mu", "sigma"), keys: tuple[str, ...] = ("eq_id",)) -> DataFrame:
    """One row for each equipment with an array, in the order of sensors, for each column; mass is that of hist."""
    if "mass" in columns and "mass" not in models.columns:
        models = models.withColumn("mass", masses(F.col("hist")))
    rows = models.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("m", *columns))).alias("_all"))
    return rows.select(*keys, *[F.transform("_all", _field(c)).alias(c) for c in columns])


def _field(name: str):
    return lambda s: s[name]


def distances(models: DataFrame) -> DataFrame:
    """For each pair of sensors how far their models are apart in standard deviations: a check before any repair.

    Below about two, readings of the pair can't be told apart. Pairs grow with sensors squared, not with data.
    """
    a, b = (models.select("eq_id", *[F.col(c).alias(f"{c}_{s}") for c in ("m", "mu", "sigma")]) for s in "ab")
    gap = F.abs(F.col("mu_a") - F.col("mu_b")) / F.sqrt((F.col("sigma_a") ** 2 + F.col("sigma_b") ** 2) / 2)
    return a.join(b, "eq_id").filter("m_a < m_b").select("eq_id", "m_a", "m_b", gap.alias("distance"))


