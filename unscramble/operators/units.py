"""Repair units: every cycle with the points at which it was a candidate."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from unscramble.functions import perm


def ones(candidates: DataFrame) -> DataFrame:
    """Rows (eq_id, sigma, n): cycle sigma is part of the candidate of point n."""
    return candidates.select("eq_id", F.explode("cycles").alias("c"), "n").select("eq_id", perm.cycle_key(F.col("c")).alias("sigma"), "n")


def build_units(points: DataFrame) -> DataFrame:
    """size (points) and extent of every cycle; counts meet before the shuffle."""
    tally = points.groupBy("eq_id", "sigma").agg(F.count("*").alias("size"), F.min("n").alias("first"), F.max("n").alias("last"))
    cycle = perm.parse_cycle(F.col("sigma"))
    return tally.select("eq_id", "sigma", cycle.alias("cycle"), F.size(cycle).alias("order"), "size", "first", "last")


def select_units(units: DataFrame, len1: int) -> DataFrame:
    """Units of at least len1 points with their rank, the largest first; ties by key."""
    w = Window.partitionBy("eq_id").orderBy(F.desc("size"), "sigma")
    return units.filter(F.col("size") >= len1).withColumn("rank", F.row_number().over(w))


def top_units(units: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("eq_id").orderBy(F.desc("size"), "sigma")
    return units.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)
