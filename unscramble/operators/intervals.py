"""Joins between points, intervals and each other.

Intervals are cut into stretches of BUCKET positions, which turns containment and overlap into an equality join with a
rest condition. Nothing is compared across stretches, and Spark chooses between broadcast and shuffle by size.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from unscramble.operators.ordinal import carried, in_ranges

BUCKET = 256


def _stretches(df: DataFrame, l: str, n: str, bucket: int) -> DataFrame:  # noqa: E741
    return df.withColumn("_b", F.explode(F.sequence(F.floor(F.col(l) / bucket), F.floor(F.col(n) / bucket))))


def interval_join(points: DataFrame, intervals: DataFrame, how: str = "left", at: str = "n", bucket: int = BUCKET, small: bool = False) -> DataFrame:
    """Points with the interval (l, r) of their eq_id that holds them. Intervals of one eq_id must not overlap.

    small: the intervals are known to be few; they are broadcast then.
    """
    cut = _stretches(intervals, "l", "r", bucket)
    cut = F.broadcast(cut) if small else cut
    left = points.withColumn("_b", F.floor(F.col(at) / bucket))
    inside = (left["eq_id"] == cut["eq_id"]) & (left["_b"] == cut["_b"]) & left[at].between(cut["l"], cut["r"])
    keep = [left[c] for c in points.columns] + ([cut[c] for c in intervals.columns if c != "eq_id"] if how in ("left", "inner") else [])
    return left.join(cut, inside, how).select(*keep)


def overlap_join(a: DataFrame, b: DataFrame, extra: Column | None = None, bucket: int = BUCKET) -> DataFrame:
    """Pairs of intervals (a_*, b_*) of the same eq_id that share a position, once each."""
    left = _stretches(a, "l", "r", bucket).select(*[F.col(c).alias(f"a_{c}") for c in a.columns], F.col("_b").alias("a__b"))
    right = _stretches(b, "l", "r", bucket).select(*[F.col(c).alias(f"b_{c}") for c in b.columns], F.col("_b").alias("b__b"))
    meets = (F.col("a_eq_id") == F.col("b_eq_id")) & (F.col("a__b") == F.col("b__b")) & (F.col("a_l") <= F.col("b_r")) & (F.col("b_l") <= F.col("a_r"))
    first = F.floor(F.greatest("a_l", "b_l") / bucket) == F.col("a__b")  # the stretch where the common part begins
    meets = meets & first if extra is None else meets & first & extra
    return left.join(right, meets).drop("a__b", "b__b")


def asof_join(ticks: DataFrame, readings: DataFrame, value: str, by: str | None = None) -> DataFrame:
    """For each tick (ts) the latest reading at or before it that isn't null, as column value.

    The union of both is dealt to ranges of time; the last value of the ranges before is handed on from range to range.
    """
    group = [by] if by else []
    a = ticks.select(*group, "ts", F.lit(1).alias("_tick"), F.lit(None).cast(dict(readings.dtypes)[value]).alias(value))
    b = readings.select(*group, "ts", F.lit(0).alias("_tick"), value)
    laid = in_ranges(a.unionByName(b), [F.col(c) for c in (*group, "ts", "_tick")])
    return carried(laid, {value: F.col(value)}, group).filter("_tick = 1").select(*group, "ts", value)


def regularise(df: DataFrame, tick: str, values: list[str], fill: str = "forward") -> DataFrame:
    """Rows on a grid of ticks between the first and last ts, with filled marking rows that were missing.

    fill: forward (the last known value), linear (between the neighbours), none.
    """
    ends = df.agg(F.min("ts").alias("lo"), F.max("ts").alias("hi"))
    grid = ends.select(F.explode(F.expr(f"sequence(lo, hi, interval {tick})")).alias("ts"))
    out = grid.join(df, "ts", "left").withColumn("filled", F.coalesce(*[F.col(v).isNull() for v in values[:1]]))
    if fill == "none":
        return out
    laid, columns = in_ranges(out, [F.col("ts")]), out.columns
    if fill == "forward":
        return carried(laid, {v: F.col(v) for v in values}, []).select(*columns)
    t = F.unix_micros("ts").cast("double")
    known = {v: F.when(F.col(v).isNotNull(), F.struct(t.alias("t"), F.col(v).cast("double").alias("v"))) for v in values}
    both = carried(carried(laid, {f"_back_{v}": c for v, c in known.items()}, []), {f"_ahead_{v}": c for v, c in known.items()}, [], ahead=True)
    for v in values:
        back, ahead = F.col(f"_back_{v}"), F.col(f"_ahead_{v}")
        share = F.when(ahead["t"] > back["t"], (t - back["t"]) / (ahead["t"] - back["t"])).otherwise(0.0)
        both = both.withColumn(v, F.coalesce(F.col(v), back["v"] + (ahead["v"] - back["v"]) * share))
    return both.select(*columns)
