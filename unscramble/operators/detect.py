"""Which readings don't fit their own sensor: the abnormal set of every time point."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from unscramble.functions.support import empirical, support
from unscramble.operators import model as models_
from unscramble.operators.model import KEYS, packed
from unscramble.operators.stretched import Tile, above, long, null, over_stretches, with_last
from unscramble.scratch import few
from unscramble.sources.panels import to_long

BROADCAST_ROWS = 20_000  # equipments whose packed models may be broadcast; beyond, models and panel are joined by shuffle


def with_models(panel: DataFrame, packed_models: DataFrame, equipments: int | None = None, keys: tuple[str, ...] = ("eq_id",)) -> DataFrame:
    """The panel beside its models. The panel is not shuffled while there are at most BROADCAST_ROWS equipments.

    The number of equipments is looked up unless stated, as a bound on what is broadcast.
    """
    if equipments is None:
        equipments = packed_models.limit(BROADCAST_ROWS + 1).count()
    return panel.join(F.broadcast(packed_models) if equipments <= BROADCAST_ROWS else packed_models, list(keys))


def supports(family: str) -> Column:
    """Support of each reading under its own model, for rows with x, mu and sigma."""
    return F.transform("x", lambda v, m: support(v, F.col("mu")[m], F.col("sigma")[m], family))


def abnormal(p: Column, theta: float) -> Column:
    """Sensors whose support is below theta; unknown readings never are."""
    return F.filter(F.transform(p, lambda v, m: F.when(v < theta, m)), lambda m: m.isNotNull())


def flag(panel: DataFrame, models: DataFrame, theta: float = 0.12, family: str = "chebyshev", equipments: int | None = None, regime: bool = False) -> DataFrame:
    """Frozen models: each point on its own. Adds mu, sigma and abnormal; no shuffle of the panel."""
    keys = ("eq_id", "regime") if regime else ("eq_id",)
    columns = ("mu", "sigma", "lo", "hi", "mass") if family == "empirical" else ("mu", "sigma")
    joined = with_models(panel, packed(models, columns, keys), equipments, keys)
    if family == "empirical":
        p = F.transform("x", lambda v, m: empirical(v, F.col("lo")[m], F.col("hi")[m], F.col("mass")[m]))
    else:
        p = supports(family)
    return joined.withColumn("abnormal", abnormal(p, theta))


def rolling(panel: DataFrame, models: DataFrame, window: int = 100, prior_weight: float = 100.0, theta: float = 0.12, family: str = "chebyshev") -> DataFrame:
    """Models of the last readings as recorded, joined with the learned model, which counts for prior_weight points."""
    if family == "empirical":
        raise ValueError("rolling models are moments; the family empirical has none")

    def compute(t: Tile) -> dict[str, np.ndarray]:
        mu0, sigma0 = t.models["mu"], t.models["sigma"]
        (s, count), (ss, _) = t.total(-window, -1), t.total(-window, -1, lambda x: x * x)
        total = count + prior_weight
        mu = (s + prior_weight * mu0) / total
        second = (ss + prior_weight * (sigma0**2 + mu0**2)) / total
        return {"mu": mu, "sigma": np.sqrt(np.maximum(second - mu**2, 0.0))}

    # arrays as they come: expressions that named parts of a struct would be repeated inside lambdas
    wide = over_stretches(panel.select("eq_id", "n", "ts", "regime", "x"), window, 0, {"mu": "double", "sigma": "double"}, compute, models.select(*KEYS, "mu", "sigma"), plain=True)
    return wide.withColumn("abnormal", abnormal(supports(family), theta))


# --- detectors as plug-ins: long rows (eq_id, n, m, x) and a history to long rows with a flag -------------------

DETECTORS: dict[str, Callable[[DataFrame, DataFrame], DataFrame]] = {}


def register_detector(name: str) -> Callable:
    def put(f: Callable) -> Callable:
        DETECTORS[name] = f
        return f

    return put


def _beside(panel: DataFrame, models: DataFrame) -> DataFrame:
    return to_long(panel).join(few(models, "models"), list(KEYS))


@register_detector("ksigma")
def detect_ksigma(panel: DataFrame, history: DataFrame, k: float = 2.5) -> DataFrame:
    return _beside(panel, models_.fit_moments(history)).withColumn("flag", F.abs(F.col("x") - F.col("mu")) > k * F.col("sigma"))


@register_detector("iqr")
def detect_iqr(panel: DataFrame, history: DataFrame, k: float = 1.5) -> DataFrame:
    iqr = (F.col("q3") - F.col("q1")) * k
    return _beside(panel, models_.fit_robust(history)).withColumn("flag", ~F.col("x").between(F.col("q1") - iqr, F.col("q3") + iqr))


@register_detector("range")
def detect_range(panel: DataFrame, history: DataFrame) -> DataFrame:
    return _beside(panel, models_.fit_moments(history)).withColumn("flag", ~F.col("x").between(F.col("lo"), F.col("hi")))


@register_detector("hampel")
def detect_hampel(panel: DataFrame, history: DataFrame, half: int = 7, k: float = 3.0) -> DataFrame:
    """Distance to the median of a centred window in scaled median absolute deviations of that window."""

    def middle(v: np.ndarray, count: np.ndarray) -> np.ndarray:
        v.sort(-1)  # what is NULL stands behind, as NaN does
        at = lambda i: np.take_along_axis(v, np.maximum(i, 0)[..., None], -1)[..., 0]
        return (at((count + 1) // 2 - 1) + at(np.minimum(count // 2, v.shape[-1] - 1))) / 2

    def compute(t: Tile) -> dict[str, np.ndarray]:
        near = np.stack([t.at(step)[0] for step in range(-half, half + 1)], -1)
        count = np.sum([t.at(step)[1] for step in range(-half, half + 1)], 0)
        mid = middle(near, count)
        mad = middle(np.abs(near - mid[..., None]), count) * 1.4826
        x, known = t.at(0)
        return {"mid": null(mid, count == 0), "mad": null(mad, count == 0), "flag": null(above(np.abs(x - mid), k * mad), ~known)}

    return long(over_stretches(panel, half, half, {"mid": "double", "mad": "double", "flag": "boolean"}, compute))


@register_detector("ewma")
def detect_ewma(panel: DataFrame, history: DataFrame, alpha: float = 0.2, k: float = 2.5, memory: int | None = None) -> DataFrame:
    """Distance to the exponential mean of the readings before.

    Of these the last memory are looked at; by default so many that what is older weighs less than a double can show.
    """
    memory = memory or math.ceil(math.log(2.0**-53) / math.log(1 - alpha))

    def compute(t: Tile) -> dict[str, np.ndarray]:
        past = np.repeat(t.models["mu"][None, :], t.points, 0)
        step_by = np.empty_like(past)
        for step in range(-memory, 0):
            v, known = t.at(step)
            np.subtract(v, past, out=step_by)
            np.multiply(step_by, alpha, out=step_by)
            if t.whole:
                past += step_by
            else:
                np.add(past, step_by, out=past, where=known)
        x, known = t.at(0)
        lacks = np.broadcast_to(t.unset("mu"), x.shape)
        return {"ewma": null(past, lacks), "flag": null(above(np.abs(x - past), k * t.models["sigma"]), ~known | lacks | t.unset("sigma"))}

    return long(over_stretches(panel, memory, 0, {"ewma": "double", "flag": "boolean"}, compute, models_.fit_moments(history).select(*KEYS, "mu", "sigma")))


@register_detector("jump")
def detect_jump(panel: DataFrame, history: DataFrame, k: float = 2.5) -> DataFrame:
    """Step from the reading before in standard deviations of the history's steps."""
    stepped = lambda p: with_last(p).withColumn("d", F.col("x") - F.col("p"))
    steps = stepped(history).groupBy(*KEYS).agg(F.stddev_samp("d").alias("sd"))
    return stepped(panel).join(few(steps, "steps"), list(KEYS)).withColumn("flag", F.coalesce(F.abs("d") > k * F.col("sd"), F.lit(False)))


@register_detector("ar1")
def detect_ar1(panel: DataFrame, history: DataFrame, k: float = 2.5) -> DataFrame:
    rows = with_last(panel).join(few(models_.fit_ar1(history), "lines"), list(KEYS))
    return rows.withColumn("flag", F.coalesce(F.abs(F.col("x") - F.col("slope") * F.col("p") - F.col("intercept")) > k * F.col("sigma"), F.lit(False)))


@register_detector("robust")
def detect_robust(panel: DataFrame, history: DataFrame, k: float = 2.5) -> DataFrame:
    return _beside(panel, models_.fit_robust(history)).withColumn("flag", F.abs(F.col("x") - F.col("mu")) > k * F.col("sigma"))


@register_detector("features")
def detect_features(panel: DataFrame, history: DataFrame, q: int = 10, k: float = 4.0) -> DataFrame:
    """Any feature of the last q readings more than k deviations from its mean."""
    return models_.window_features(panel, q, models_.fit_features(history, q), k)


@register_detector("distance")
def detect_distance(panel: DataFrame, history: DataFrame, q: int = 10, k: float = 4.0) -> DataFrame:
    """Root mean square gap of the last q readings to the reference, against its usual size."""
    profile = models_.fit_profile(history, q)
    rows = models_.gaps(panel, q, few(profile.select(*KEYS, "mu"), "levels")).join(few(profile.select(*KEYS, "gap_mu", "gap_sigma"), "profiles"), list(KEYS))
    return rows.withColumn("flag", F.col("gap") > F.col("gap_mu") + k * F.col("gap_sigma"))


def flagged_panel(long_flags: DataFrame) -> DataFrame:
    """Flags of any detector as the abnormal set (eq_id, n, abnormal) of each point that has one."""
    return long_flags.filter("flag").groupBy("eq_id", "n").agg(F.array_sort(F.collect_list(F.when(F.col("flag"), F.col("m")))).alias("abnormal"))


