"""Final repairs: units in order of size, each on what larger ones left (Step B).

An equipment with at most HELD runs of candidate cycles is determined in one task, unit by unit in strict order; runs, not
points, meet there. Equipments with more runs go in waves. Units touch each other only where they share a sensor at the
same time. Their segments (1-runs with short gaps filled, before anything is claimed) can only shrink later, so two units
are in conflict only if segments with a common sensor overlap. All units without a larger unit in conflict are evaluated
together in one wave, then their intervals are claimed, and the next wave follows. The result is the one of strict order,
in as many waves as the longest chain.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from unscramble.config import RepairConfig
from unscramble.functions import perm
from unscramble.operators import runs as runs_
from unscramble.operators import units as units_
from unscramble.operators.intervals import interval_join, overlap_join
from unscramble.scratch import appended, scratch_path, stored

KEYS = ("eq_id", "sigma")
HELD = 1 << 21  # so many runs of an equipment are held in one task
INTERVALS = "eq_id long, sigma string, l long, r long"


@dataclass
class Determined:
    schemas: DataFrame  # eq_id, l, r, phi: maximal disjoint intervals of constant phi
    units: DataFrame  # eq_id, sigma, cycle, order, size, first, last, rank, intervals, points
    intervals: DataFrame  # eq_id, sigma, l, r
    waves: int  # that large equipments took


def by_sensor(rows: DataFrame) -> DataFrame:
    return rows.withColumn("sensor", F.explode(perm.parse_cycle(F.col("sigma"))))


def free_ones(points: DataFrame, claims: DataFrame) -> DataFrame:
    """Points of cycles none of whose sensors is claimed there."""
    each = by_sensor(points)
    cut = claims.withColumn("_b", F.explode(F.sequence(F.floor(F.col("l") / 256), F.floor(F.col("r") / 256))))
    left = each.withColumn("_b", F.floor(F.col("n") / 256))
    taken = left.join(cut, ["eq_id", "sensor", "_b"]).filter(F.col("n").between(F.col("l"), F.col("r"))).select(*KEYS, "n").distinct()
    return points.join(taken, [*KEYS, "n"], "left_anti")


def hard_gaps(runs: DataFrame, claims: DataFrame) -> DataFrame:
    """Runs (eq_id, sigma, l) before which some point is claimed for a sensor of the cycle."""
    w = Window.partitionBy(*KEYS).orderBy("l")
    gaps = runs.withColumn("g", F.lag("r").over(w) + 1).filter("g IS NOT NULL AND g < l")
    gaps = by_sensor(gaps).select("eq_id", "sigma", "sensor", F.col("l").alias("run"), F.col("g").alias("l"), (F.col("l") - 1).alias("r"))
    hit = overlap_join(gaps, claims, F.col("a_sensor") == F.col("b_sensor"))
    return hit.select(F.col("a_eq_id").alias("eq_id"), F.col("a_sigma").alias("sigma"), F.col("a_run").alias("l")).distinct()


def evaluate_intervals(points: DataFrame, last: DataFrame, cfg: RepairConfig, claims: DataFrame | None = None) -> DataFrame:
    """Intervals (eq_id, sigma, l, r) of all cycles in points at once, on what claims (eq_id, sensor, l, r) leave."""
    runs = runs_.islands(points if claims is None else free_ones(points, claims))
    blocked = None if claims is None else hard_gaps(runs, claims)
    smooth = runs if cfg.theta_tau <= 0 else runs_.smooth(runs, last, cfg.theta_tau, cfg.len2, cfg.tau_mode, cfg.merge, blocked)
    return runs_.long_enough(smooth, cfg.len2)


def conflicts(units: DataFrame, points: DataFrame, cfg: RepairConfig) -> DataFrame:
    """Pairs (eq_id, sigma, over): over is larger and may take points from sigma."""
    w = Window.partitionBy(*KEYS).orderBy("l")
    runs = runs_.islands(points)
    length = F.col("r") - F.col("l") + 1
    gap = F.col("l") - F.lag("r").over(w) - 1
    if cfg.merge == "two_pass":
        segments = runs_.joined_runs(runs, KEYS, gap <= cfg.theta_tau * (length + F.lag(length).over(w)))
    else:  # lengths may grow while runs merge: the whole extent is the safe bound
        segments = runs.groupBy(*KEYS).agg(F.min("l").alias("l"), F.max("r").alias("r"))
    ranked = by_sensor(segments.join(units.select(*KEYS, "rank"), list(KEYS)))
    both = overlap_join(ranked, ranked, (F.col("a_sensor") == F.col("b_sensor")) & (F.col("a_rank") > F.col("b_rank")))
    return both.select(F.col("a_eq_id").alias("eq_id"), F.col("a_sigma").alias("sigma"), F.col("b_sigma").alias("over")).distinct()


def determine(candidates: DataFrame, last: DataFrame, cfg: RepairConfig, held: int = HELD) -> Determined:
    """last: eq_id, last point. candidates are read several times: give a stored table."""
    all_ones = units_.ones(candidates)
    units = stored(units_.select_units(units_.build_units(all_ones), cfg.len1), "units")
    ones = all_ones.join(units.select(*KEYS, "rank"), list(KEYS))
    runs = stored(runs_.islands(ones, ("eq_id", "rank")), "runs")
    large = stored(runs.groupBy("eq_id").agg(F.count("*").alias("c")).filter(F.col("c") > held).select("eq_id"), "large")
    if large.isEmpty():
        found, waves = stored(in_order(runs, units, last, cfg), "intervals"), 0
    else:
        small = stored(in_order(runs.join(large, "eq_id", "left_anti"), units, last, cfg), "intervals")
        mine, points = units.join(large, "eq_id", "left_semi"), stored(ones.join(large, "eq_id", "left_semi").select(*KEYS, "n"), "ones")
        found, waves = in_waves(mine, points, last, cfg)
        found = small.unionByName(found)
    totals = found.groupBy(*KEYS).agg(F.count("*").alias("intervals"), F.sum(F.col("r") - F.col("l") + 1).alias("points"))
    done = units.join(totals, list(KEYS), "left").fillna(0, ["intervals", "points"])
    return Determined(overlay(found), done, found, waves)


def in_order(runs: DataFrame, units: DataFrame, last: DataFrame, cfg: RepairConfig) -> DataFrame:
    """Intervals of all units, one task for each equipment. runs: eq_id, rank, l, r."""

    def evaluate(mine: pd.DataFrame, names: pd.DataFrame) -> pd.DataFrame:
        got = []
        if len(mine) and len(names):
            mine = mine.sort_values(["rank", "l"])
            rank, l, r = (mine[c].to_numpy(np.int64) for c in ("rank", "l", "r"))  # noqa: E741
            bounds = dict(zip(*np.unique(rank, return_index=True), strict=True))
            end, claims = int(names["last"].iloc[0]), Claims()
            names = names.sort_values("rank")
            for k, sigma in zip(names["rank"], names["sigma"], strict=True):
                at = bounds[k]
                to = at + np.searchsorted(rank[at:], k, "right")
                sensors = [int(s) for s in sigma.split(">")]
                left, right = claims.rest(sensors, l[at:to], r[at:to])
                if cfg.theta_tau > 0:
                    left, right = runs_.smoothed(left, right, claims.hard(sensors, left, right), end, cfg.theta_tau, cfg.len2, cfg.tau_mode, cfg.merge)
                enough = right - left + 1 >= cfg.len2
                left, right = left[enough], right[enough]
                claims.put(sensors, left, right)
                got.append(pd.DataFrame({"sigma": sigma, "l": left, "r": right}))
        out = pd.concat(got) if got else pd.DataFrame({"sigma": [], "l": [], "r": []})
        out.insert(0, "eq_id", int(names["eq_id"].iloc[0]) if len(names) else 0)
        return out.astype({"eq_id": "int64", "sigma": "str", "l": "int64", "r": "int64"})

    known = units.select("eq_id", "rank", "sigma").join(last, "eq_id")
    return runs.groupBy("eq_id").cogroup(known.groupBy("eq_id")).applyInPandas(evaluate, INTERVALS)


class Claims:
    """Intervals claimed for each sensor of an equipment so far; those of one sensor never overlap."""

    def __init__(self) -> None:
        self.of: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def put(self, sensors: list[int], l: np.ndarray, r: np.ndarray) -> None:  # noqa: E741
        for s in sensors if len(l) else ():
            a, b = self.of.get(s, (l[:0], r[:0]))
            at = np.searchsorted(a, l)
            self.of[s] = np.insert(a, at, l), np.insert(b, at, r)

    def united(self, sensors: list[int], low: int, high: int) -> tuple[np.ndarray, np.ndarray]:
        """Disjoint intervals claimed for any of the sensors that reach into low..high, in order."""
        parts = []
        for a, b in (self.of[s] for s in sensors if s in self.of):
            at = slice(np.searchsorted(b, low), np.searchsorted(a, high, "right"))
            parts.append((a[at], b[at]))
        if not parts:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        a, b = (np.concatenate(p) for p in zip(*parts, strict=True))
        at = np.argsort(a, kind="stable")
        a, b = a[at], np.maximum.accumulate(b[at])
        first = np.flatnonzero(np.concatenate([[True], a[1:] > b[:-1]])) if len(a) else np.zeros(0, int)
        return a[first], b[np.concatenate([first[1:] - 1, [len(b) - 1]])] if len(a) else b

    def rest(self, sensors: list[int], l: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:  # noqa: E741
        """What runs in order keep beside the claims."""
        a, b = self.united(sensors, l[0], r[-1])
        if not len(a):
            return l, r
        free_l, free_r = np.concatenate([[l[0]], b + 1]), np.concatenate([a - 1, [r[-1]]])
        begin, stop = np.searchsorted(r, free_l), np.searchsorted(l, free_r, "right")  # runs that each free stretch meets
        many = np.maximum(stop - begin, 0)
        stretch = np.repeat(np.arange(len(many)), many)
        run = np.arange(many.sum()) - np.repeat(many.cumsum() - many, many) + begin[stretch]
        left, right = np.maximum(l[run], free_l[stretch]), np.minimum(r[run], free_r[stretch])
        return left[left <= right], right[left <= right]

    def hard(self, sensors: list[int], l: np.ndarray, r: np.ndarray) -> np.ndarray:  # noqa: E741
        """Whether some point of the gap before each run is claimed."""
        out = np.zeros(len(l), bool)
        if len(l) > 1:
            a, b = self.united(sensors, r[0] + 1, l[-1] - 1)
            if len(a):
                at = np.searchsorted(b, r[:-1] + 1)
                out[1:] = (at < len(a)) & (a[np.minimum(at, len(a) - 1)] <= l[1:] - 1)
        return out


def in_waves(units: DataFrame, points: DataFrame, last: DataFrame, cfg: RepairConfig) -> tuple[DataFrame, int]:
    """Intervals of all units, and how many waves they took. What waves leave behind is appended to one table, so that
    plans don't grow with them."""
    spark, path = units.sparkSession, scratch_path(units.sparkSession, "intervals")
    over = stored(conflicts(units, points, cfg), "conflicts")
    waiting = stored(units.select(*KEYS), "waiting")
    found, waves = appended(spark.createDataFrame([], INTERVALS), path), 0
    while True:
        # a larger unit that still waits holds back those below it
        held = over.join(waiting.withColumnRenamed("sigma", "over"), ["eq_id", "over"], "left_semi").select(*KEYS).distinct()
        ready = stored(waiting.join(held, list(KEYS), "left_anti"), "wave")
        if ready.isEmpty():
            return found, waves
        mine = points.join(ready, list(KEYS), "left_semi")
        claims = by_sensor(found).select("eq_id", "sensor", "l", "r") if waves else None
        found = appended(stored(evaluate_intervals(mine, last, cfg, claims), "intervals"), path)
        waiting = stored(waiting.join(ready, list(KEYS), "left_anti"), "waiting")
        waves += 1


def overlay(intervals: DataFrame) -> DataFrame:
    """Intervals of single cycles (eq_id, sigma, l, r) to maximal disjoint intervals (eq_id, l, r, phi)."""
    borders = intervals.select("eq_id", F.explode(F.array("l", F.col("r") + 1)).alias("l")).distinct()
    w = Window.partitionBy("eq_id").orderBy("l")
    pieces = borders.withColumn("r", F.lead("l").over(w) - 1).filter("r IS NOT NULL")
    both = overlap_join(pieces, intervals)
    cover = both.groupBy(F.col("a_eq_id").alias("eq_id"), F.col("a_l").alias("l"), F.col("a_r").alias("r"))
    sets = cover.agg(F.array_sort(F.collect_set(perm.parse_cycle(F.col("b_sigma")))).alias("phi"))
    same = (F.lag("r").over(w) + 1 == F.col("l")) & (F.lag("phi").over(w) == F.col("phi"))
    groups = sets.withColumn("_new", F.when(F.coalesce(same, F.lit(False)), 0).otherwise(1)).withColumn("_g", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return groups.groupBy("eq_id", "_g").agg(F.min("l").alias("l"), F.max("r").alias("r"), F.first("phi").alias("phi")).drop("_g")


def merged(schemas: DataFrame) -> DataFrame:
    """Touching intervals as one detection, with all their cycles."""
    w = Window.partitionBy("eq_id").orderBy("l")
    joins = F.coalesce(F.lag("r").over(w) + 1 == F.col("l"), F.lit(False))
    groups = schemas.withColumn("_g", F.sum(F.when(joins, 0).otherwise(1)).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return groups.groupBy("eq_id", "_g").agg(F.min("l").alias("l"), F.max("r").alias("r"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("phi")))).alias("phi")).drop("_g")


def apply_schemas(panel: DataFrame, schemas: DataFrame) -> DataFrame:
    """All data with the final intervals undone: one projection over the panel, which is not shuffled while the
    intervals are few enough for Spark to broadcast."""
    joined = interval_join(panel, schemas.select("eq_id", "l", "r", "phi"))
    y = F.when(F.col("phi").isNotNull(), perm.apply_cycles(F.col("x"), F.col("phi"))).otherwise(F.col("x"))
    return joined.select("eq_id", "n", "ts", "regime", y.alias("x"))
