"""Runs of a cycle over time and their smoothing (Step C).

A bit sequence over points 1..last is kept as its 1-runs (eq_id, sigma, l, r); 0-runs are what lies between and are never
stored. ones: rows (eq_id, sigma, n).

Smoothing looks at three neighbouring runs: tau is the middle one's length over the sum of its neighbours'. A middle run
with tau below the limit takes its neighbours' value. In guarded mode 1-runs are only dropped if they are also shorter
than the least length that counts. Runs at the edges have one neighbour and are never in the middle. Points that a
larger unit has repaired are zeros for good: a gap that holds one is never filled.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

KEYS = ("eq_id", "sigma")
STRETCH = 4096


def islands(ones: DataFrame, keys: Iterable[str] = KEYS, stretch: int = STRETCH) -> DataFrame:
    """1-runs of sparse ones. First inside stretches of time, so that a frequent cycle is spread over many tasks, then
    runs that touch across a border are joined; only runs, not points, meet in one task."""
    keys = list(keys)
    part = F.floor(F.col("n") / stretch)
    w = Window.partitionBy(*keys, "_s").orderBy("n")
    marked = ones.select(*keys, "n").distinct().withColumn("_s", part).withColumn("_g", F.col("n") - F.row_number().over(w))
    local = marked.groupBy(*keys, "_s", "_g").agg(F.min("n").alias("l"), F.max("n").alias("r")).select(*keys, "l", "r")
    return joined_runs(local, keys)


def joined_runs(runs: DataFrame, keys: Iterable[str] = KEYS, gap_ok: Column | None = None) -> DataFrame:
    """Runs made one where nothing lies between them, or where gap_ok (over the gap before a run) says so."""
    keys = list(keys)
    w = Window.partitionBy(*keys).orderBy("l")
    gap = F.col("l") - F.lag("r").over(w) - 1
    join = F.coalesce(gap == 0, F.lit(False)) if gap_ok is None else F.coalesce(gap_ok, F.lit(False))
    return (
        runs.withColumn("_new", F.when(join, 0).otherwise(1))
        .withColumn("_g", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
        .groupBy(*keys, "_g")
        .agg(F.min("l").alias("l"), F.max("r").alias("r"))
        .drop("_g")
    )


def all_runs(runs: DataFrame, last: DataFrame) -> DataFrame:
    """1-runs and 0-runs with bit and len, for inspection; last: eq_id, last."""
    w = Window.partitionBy(*KEYS).orderBy("l")
    ends = runs.join(last, "eq_id")
    before = ends.select(*KEYS, F.lit(0).alias("bit"), (F.coalesce(F.lag("r").over(w), F.lit(0)) + 1).alias("l"), (F.col("l") - 1).alias("r"))
    after = ends.groupBy(*KEYS).agg(F.max("r").alias("r"), F.max("last").alias("last")).select(*KEYS, F.lit(0).alias("bit"), (F.col("r") + 1).alias("l"), F.col("last").alias("r"))
    out = runs.select(*KEYS, F.lit(1).alias("bit"), "l", "r").unionByName(before).unionByName(after)
    return out.filter("l <= r").withColumn("len", F.col("r") - F.col("l") + 1)


def with_tau(runs: DataFrame) -> DataFrame:
    """tau of every run that has two neighbours (else NULL), for rows of all_runs."""
    w = Window.partitionBy(*KEYS).orderBy("l")
    return runs.withColumn("tau", F.col("len") / (F.lag("len").over(w) + F.lead("len").over(w)))


def smooth(runs: DataFrame, last: DataFrame, theta: float = 0.3, len2: int = 20, mode: str = "guarded", merge: str = "two_pass", blocked: DataFrame | None = None) -> DataFrame:
    """Smoothed 1-runs. blocked: rows (eq_id, sigma, l) of runs before which the gap must stay."""
    marked = runs.select(*KEYS, "l", "r")
    marked = marked.withColumn("_hard", F.lit(False)) if blocked is None else marked.join(blocked.select(*KEYS, "l").distinct().withColumn("_hard", F.lit(True)), [*KEYS, "l"], "left").withColumn("_hard", F.coalesce("_hard", F.lit(False)))
    if merge == "two_pass":
        w = Window.partitionBy(*KEYS).orderBy("l")
        length = F.col("r") - F.col("l") + 1
        gap = F.col("l") - F.lag("r").over(w) - 1
        short = (gap < theta * (length + F.lag(length).over(w))) & ~F.col("_hard")
        return dropped(joined_runs(marked, KEYS, short), last, theta, len2, mode)
    if merge == "snapshot":
        return _snapshot(marked, last, theta, len2, mode)
    if merge == "progressive":
        return _progressive(marked, last, theta, len2, mode)
    raise ValueError(f"unknown merge {merge}")


def dropped(runs: DataFrame, last: DataFrame, theta: float, len2: int, mode: str) -> DataFrame:
    """Without 1-runs that are short beside the gaps on both sides."""
    w = Window.partitionBy(*KEYS).orderBy("l")
    length = F.col("r") - F.col("l") + 1
    before = F.col("l") - F.coalesce(F.lag("r").over(w), F.lit(0)) - 1
    after = F.coalesce(F.lead("l").over(w), F.col("last") + 1) - F.col("r") - 1
    short = (before > 0) & (after > 0) & (length < theta * (before + after))
    if mode == "guarded":
        short = short & (length < len2)
    return runs.join(last, "eq_id").withColumn("_short", short).filter(~F.col("_short")).select(*KEYS, "l", "r")


def _snapshot(marked: DataFrame, last: DataFrame, theta: float, len2: int, mode: str) -> DataFrame:
    """All middles are judged by the lengths as they were; of middles next to each other only the first is turned."""
    w = Window.partitionBy(*KEYS).orderBy("l")
    rows = with_tau(all_runs(marked.select(*KEYS, "l", "r"), last)).join(marked.select(*KEYS, "l", "_hard"), [*KEYS, "l"], "left")
    hard_gap = F.coalesce(F.lead("_hard").over(w), F.lit(False)) & (F.col("bit") == 0)
    may = F.coalesce(F.col("tau") < theta, F.lit(False)) & ~hard_gap
    if mode == "guarded":
        may = may & ((F.col("bit") == 0) | (F.col("len") < len2))
    rows = rows.withColumn("_may", may)
    streak = F.sum(F.when(F.col("_may"), 0).otherwise(1)).over(w.rowsBetween(Window.unboundedPreceding, 0))
    rows = rows.withColumn("_streak", streak)
    place = F.sum(F.col("_may").cast("int")).over(Window.partitionBy(*KEYS, "_streak").orderBy("l").rowsBetween(Window.unboundedPreceding, 0))
    turned = F.col("_may") & (place % 2 == 1)
    kept = rows.withColumn("_bit", F.when(turned, 1 - F.col("bit")).otherwise(F.col("bit"))).filter("_bit = 1").select(*KEYS, "l", "r")
    return joined_runs(kept)


def fold_runs(runs: list[tuple[int, int, bool]], last: int, theta: float, len2: int, mode: str) -> list[tuple[int, int]]:
    """Left to right over (bit, length) triples; a run that was absorbed counts with its new length from then on."""
    seq: list[list] = []  # [bit, length, hard]
    at = 1
    for l, r, hard in runs:  # noqa: E741
        if l > at:
            seq.append([0, l - at, hard])
        seq.append([1, r - l + 1, False])
        at = r + 1
    if at <= last:
        seq.append([0, last - at + 1, False])
    kept, i = seq[:1], 1  # what is settled; its last run is the left neighbour of the middle one, seq[i]
    while i + 1 < len(seq):
        (b0, n0, h0), (bit, n, hard), (_, n2, h2) = kept[-1], seq[i], seq[i + 1]
        may = n < theta * (n0 + n2) and not (bit == 0 and hard)
        if bit == 1 and mode == "guarded":
            may = may and n < len2
        if may:
            kept[-1] = [b0, n0 + n + n2, h0 or h2]
            i += 2
        else:
            kept.append(seq[i])
            i += 1
    seq = kept + seq[i:]
    out, at = [], 1
    for bit, n, _ in seq:
        if bit:
            out.append((at, at + n - 1))
        at += n
    return out


def _progressive(marked: DataFrame, last: DataFrame, theta: float, len2: int, mode: str) -> DataFrame:
    def fold(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("l")
        got = fold_runs(list(zip(pdf["l"], pdf["r"], pdf["_hard"], strict=True)), int(pdf["last"].iloc[0]), theta, len2, mode)
        return pd.DataFrame({"eq_id": pdf["eq_id"].iloc[0], "sigma": pdf["sigma"].iloc[0], "l": [a for a, _ in got], "r": [b for _, b in got]}, columns=["eq_id", "sigma", "l", "r"])

    return marked.join(last, "eq_id").groupBy(*KEYS).applyInPandas(fold, "eq_id long, sigma string, l long, r long")


def smoothed(l: np.ndarray, r: np.ndarray, hard: np.ndarray, last: int, theta: float, len2: int, mode: str, merge: str) -> tuple[np.ndarray, np.ndarray]:  # noqa: E741
    """What smooth() gives for one cycle, without Spark. l, r: its 1-runs in order; hard: whether the gap before must stay."""
    if not len(l):
        return l, r
    if merge == "progressive":
        got = np.array(fold_runs(list(zip(l.tolist(), r.tolist(), hard.tolist(), strict=True)), last, theta, len2, mode), np.int64).reshape(-1, 2)
        return got[:, 0], got[:, 1]
    if merge == "two_pass":
        length = r - l + 1
        short = (l[1:] - r[:-1] - 1 < theta * (length[1:] + length[:-1])) & ~hard[1:]
        l, r = _joined(l, r, short)  # noqa: E741
        before = l - np.concatenate([[0], r[:-1]]) - 1
        after = np.concatenate([l[1:], [last + 1]]) - r - 1
        short = (before > 0) & (after > 0) & (r - l + 1 < theta * (before + after))
        if mode == "guarded":
            short &= r - l + 1 < len2
        return l[~short], r[~short]
    if merge != "snapshot":
        raise ValueError(f"unknown merge {merge}")
    starts = np.concatenate([l, [1], r + 1])
    ends = np.concatenate([r, l[:1] - 1, l[1:] - 1, [last]])
    bit = np.repeat([1, 0], [len(l), len(l) + 1])
    stay = np.concatenate([np.zeros(len(l), bool), hard, [False]])
    at = np.argsort(starts, kind="stable")
    at = at[starts[at] <= ends[at]]
    starts, ends, bit, stay = starts[at], ends[at], bit[at], stay[at]
    length, may = ends - starts + 1, np.zeros(len(at), bool)
    may[1:-1] = (length[1:-1] / (length[:-2] + length[2:]) < theta) & ~stay[1:-1]
    if mode == "guarded":
        may &= (bit == 0) | (length < len2)
    place = np.arange(len(at)) - np.maximum.accumulate(np.where(may, -1, np.arange(len(at))))
    ones = np.where(may & (place % 2 == 1), 1 - bit, bit) == 1
    l, r = starts[ones], ends[ones]  # noqa: E741
    return _joined(l, r, l[1:] == r[:-1] + 1)


def _joined(l: np.ndarray, r: np.ndarray, with_next: np.ndarray) -> tuple[np.ndarray, np.ndarray]:  # noqa: E741
    """Runs made one with the next where with_next says so."""
    if not len(l):
        return l, r
    return l[np.concatenate([[True], ~with_next])], r[np.concatenate([~with_next, [True]])]


def long_enough(runs: DataFrame, len2: int) -> DataFrame:
    return runs.filter(F.col("r") - F.col("l") + 1 >= len2)


def runs_union_find(bits: list[int]) -> list[tuple[int, int, int]]:
    """(bit, first, last) of a dense sequence by a disjoint set over positions; the reference for islands."""
    parent = list(range(len(bits)))

    def find(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    for i in range(1, len(bits)):
        if bits[i] == bits[i - 1]:
            parent[find(i)] = find(i - 1)
    groups: dict[int, list[int]] = {}
    for i in range(len(bits)):
        groups.setdefault(find(i), []).append(i + 1)
    return sorted((bits[g[0] - 1], g[0], g[-1]) for g in groups.values())
