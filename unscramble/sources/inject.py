"""Deterministic misplacement with ground truth."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unscramble.functions import perm
from unscramble.operators.intervals import interval_join

SIZES = (2, 3, 2, 4)  # sizes of the cycles that a set of sensors is cut into, over and over
LENGTHS = (60, 90, 140, 200)


def cycle_cuts(attributes: int) -> list[tuple[int, int]]:
    """(start, size) of the cycles among so many sensors; a last single one joins the cycle before."""
    out, at, k = [], 0, 0
    while at < attributes:
        size = min(SIZES[k % len(SIZES)], attributes - at)
        if attributes - at - size == 1:
            size += 1
        out.append((at, size))
        at, k = at + size, k + 1
    return out


def plan(points: DataFrame, attributes: int = 12, sensors: int = 48) -> DataFrame:
    """Truth (eq_id, k, l, r, phi) for panels of so many points; points: eq_id, last."""
    stride = 7 if sensors == 150 else 5
    last = F.col("last")
    count = F.greatest(F.lit(3), F.floor(last / 500)).cast("long")
    rows = points.withColumn("count", count).filter("last > 0").withColumn("k", F.explode(F.sequence(F.lit(0).cast("long"), F.col("count") - 1)))
    k, c = F.col("k"), F.col("count")
    l = F.floor(k * last / c) + F.floor(last / (3 * c)) + 1  # noqa: E741
    wanted = F.element_at(F.lit(list(LENGTHS)), (k % len(LENGTHS)).cast("int") + 1)
    length = F.greatest(F.least(wanted, F.floor(last / (2 * c))), F.lit(1))
    members = F.transform(F.sequence(F.lit(0), F.lit(attributes - 1)), lambda j: ((7 * k + stride * j) % sensors).cast("int"))
    phi = perm.canonical(F.array(*[F.slice(members, at + 1, size) for at, size in cycle_cuts(attributes)]))
    return rows.select("eq_id", "k", l.cast("long").alias("l"), (l + length - 1).cast("long").alias("r"), phi.alias("phi"))


def example_plan(points: DataFrame) -> DataFrame:
    """One interval in which sensors 1 and 2, and 3 and 5 (counted from 1) stand in each other's columns."""
    phi = perm.parse_notation(F.lit("(1 2)(3 5)"))
    return points.select("eq_id", F.lit(0).cast("long").alias("k"), F.floor(F.col("last") * 3 / 5).cast("long").alias("l"), F.floor(F.col("last") * 4 / 5).cast("long").alias("r"), phi.alias("phi"))


def extent(panel: DataFrame) -> DataFrame:
    return panel.groupBy("eq_id").agg(F.max("n").alias("last"))


def inject(panel: DataFrame, truth: DataFrame) -> DataFrame:
    """The panel with readings misplaced in the intervals of truth."""
    joined = interval_join(panel, truth.select("eq_id", "l", "r", "phi"))
    moved = F.when(F.col("phi").isNotNull(), perm.gather(F.col("x"), perm.corrupt_places(F.col("phi"), F.size("x")))).otherwise(F.col("x"))
    return joined.select("eq_id", "n", "ts", "regime", moved.alias("x"))
