"""How well a reading fits a sensor's behaviour model: a support between 0 and 1 as a Column expression."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

FLOOR = 1e-300  # least support that enters logarithms


def z_score(x: Column, mu: Column, sigma: Column) -> Column:
    """Distance in standard deviations; a model without spread takes only its own value."""
    return F.when(sigma > 0, (x - mu) / sigma).when(x == mu, 0.0).otherwise(1e9)


def chebyshev(z: Column) -> Column:
    """Bound on the mass this far out for any distribution."""
    return F.when(F.abs(z) <= 1, 1.0).otherwise(1 / (z * z))


def kernel(z: Column) -> Column:
    return F.greatest(F.exp(-z * z / 2), F.lit(FLOOR))


# fixed values: coefficients of a published approximation with error below 1.2e-7
TAIL = (-1.26551223, 1.00002368, 0.37409196, 0.09678418, -0.18628806, 0.27886807, -1.13520398, 1.48851587, -0.82215223, 0.17087277)


def tail(z: Column) -> Column:
    """Two-sided tail of the normal distribution, by a rational approximation of the complementary error function."""
    a = F.abs(z) / math.sqrt(2)
    t = 1 / (1 + a / 2)
    poly = F.lit(TAIL[-1])
    for k in reversed(TAIL[:-1]):
        poly = poly * t + k
    return F.least(F.greatest(t * F.exp(-a * a + poly), F.lit(FLOOR)), F.lit(1.0))


FAMILIES: dict[str, Callable[[Column], Column]] = {"chebyshev": chebyshev, "kernel": kernel, "tail": tail}


def support(x: Column, mu: Column, sigma: Column, family: str = "chebyshev") -> Column:
    """NULL and NaN readings are unknown and give NULL."""
    known = x.isNotNull() & ~F.isnan(x)
    return F.when(known, FAMILIES[family](z_score(x, mu, sigma)))


def masses(hist: Column) -> Column:
    """For each bin the share of the learned mass in bins no fuller than it."""
    return F.transform(hist, lambda own: F.aggregate(hist, F.lit(0.0), lambda acc, h: acc + F.when(h <= own, h).otherwise(0.0)))


def empirical(x: Column, lo: Column, hi: Column, mass: Column) -> Column:
    """The mass (see masses) of the reading's bin; outside the learned range FLOOR."""
    bins = F.size(mass)
    at = F.least(F.floor((x - lo) / F.when(hi > lo, hi - lo).otherwise(1.0) * bins).cast("int"), bins - 1)
    known = x.isNotNull() & ~F.isnan(x)
    return F.when(known, F.when((x < lo) | (x > hi), FLOOR).otherwise(F.greatest(F.coalesce(F.try_element_at(mass, at + 1), F.lit(0.0)), F.lit(FLOOR))))
