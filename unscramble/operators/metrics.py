"""Accuracy of detection and repair, interval by interval, cell by cell and bit by bit.

found and truth: rows (eq_id, l, r, phi). Counts are one row; a measure without denominator is NULL.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from unscramble.functions import perm
from unscramble.operators.intervals import overlap_join


def pairs(found: DataFrame, truth: DataFrame, rule: str = "iou", iou: float = 0.5, tolerance: int = 5) -> DataFrame:
    """One-to-one pairs of found and true intervals that count as the same; the largest overlap share first."""
    rows = overlap_join(found.select("eq_id", "l", "r", "phi"), truth.select("eq_id", "l", "r", "phi"))
    both = F.least("a_r", "b_r") - F.greatest("a_l", "b_l") + 1
    share = both / (F.greatest("a_r", "b_r") - F.least("a_l", "b_l") + 1)
    shift = F.greatest(F.abs(F.col("a_l") - F.col("b_l")), F.abs(F.col("a_r") - F.col("b_r")))
    ok: Column = {"iou": share >= iou, "exact": shift == 0, "tolerance": shift <= tolerance, "overlap": both > 0}[rule]
    rows = rows.withColumn("iou", share).filter(ok)
    best = lambda side: Window.partitionBy(f"{side}_eq_id", f"{side}_l").orderBy(F.desc("iou"), "a_l", "b_l")
    rows = rows.withColumn("_a", F.row_number().over(best("a"))).withColumn("_b", F.row_number().over(best("b")))
    return rows.filter("_a = 1 AND _b = 1").drop("_a", "_b")


def right_phi(found: Column, true: Column, rule: str = "equal") -> Column:
    return found == true if rule == "equal" else F.size(F.array_except(true, found)) == 0


def scores(found: DataFrame, truth: DataFrame, rule: str = "iou", phi_rule: str = "equal", iou: float = 0.5, tolerance: int = 5) -> DataFrame:
    """Counts, p_d, r_d, and the repair measures as printed (p_r over correct detections, r_r over detections) and with
    their denominators exchanged (p_r_alt, r_r_alt)."""
    same = pairs(found, truth, rule, iou, tolerance)
    hit = same.agg(F.count("*").alias("n_correct"), F.count_if(right_phi(F.col("a_phi"), F.col("b_phi"), phi_rule)).alias("n_repaired"))
    counts = hit.crossJoin(found.agg(F.count("*").alias("n_found"))).crossJoin(truth.agg(F.count("*").alias("n_true")))  # one row each
    over = lambda a, b: F.try_divide(F.col(a).cast("double"), F.col(b).cast("double"))
    return counts.select(
        "n_found", "n_true", "n_correct", "n_repaired",
        over("n_correct", "n_found").alias("p_d"), over("n_correct", "n_true").alias("r_d"),
        over("n_repaired", "n_correct").alias("p_r"), over("n_repaired", "n_found").alias("r_r"),
        over("n_repaired", "n_found").alias("p_r_alt"), over("n_repaired", "n_correct").alias("r_r_alt"),
    )


def cycle_scores(found: DataFrame, truth: DataFrame, rule: str = "iou") -> DataFrame:
    """Precision and recall of single cycles within paired intervals, against all cycles found and true."""
    size = lambda df: df.agg(F.coalesce(F.sum(F.size("phi")), F.lit(0)))
    same = pairs(found, truth, rule).agg(F.coalesce(F.sum(F.size(F.array_intersect("a_phi", "b_phi"))), F.lit(0)).alias("n_correct"))
    counts = same.crossJoin(size(found).toDF("n_found")).crossJoin(size(truth).toDF("n_true"))
    over = lambda a, b: F.try_divide(F.col(a).cast("double"), F.col(b).cast("double"))
    return counts.select("n_found", "n_true", "n_correct", over("n_correct", "n_found").alias("precision"), over("n_correct", "n_true").alias("recall"))


def bound_error(found: DataFrame, truth: DataFrame, rule: str = "iou") -> DataFrame:
    same = pairs(found, truth, rule)
    return same.agg(F.count("*").alias("n_pairs"), F.avg(F.abs(F.col("a_l") - F.col("b_l"))).alias("start_error"), F.avg(F.abs(F.col("a_r") - F.col("b_r"))).alias("end_error"))


def cell_scores(clean: DataFrame, corrupt: DataFrame, repaired: DataFrame) -> DataFrame:
    """How many misplaced cells were restored, how many right ones were damaged, and the root mean square error."""
    a, b, c = (df.select("eq_id", "n", F.col("x").alias(k)) for df, k in ((clean, "t"), (corrupt, "d"), (repaired, "y")))
    rows = a.join(b, ["eq_id", "n"]).join(c, ["eq_id", "n"])
    cells = F.transform(F.arrays_zip("t", "d", "y"), lambda s: F.struct((s["t"] != s["d"]).alias("bad"), (s["t"] == s["y"]).alias("good"), F.pow(s["t"] - s["y"], 2).alias("sq")))
    count = lambda cond: F.size(F.filter("cells", cond))
    sums = rows.select(cells.alias("cells")).select(
        F.size("cells").alias("n"), count(lambda s: s["bad"]).alias("bad"), count(lambda s: s["bad"] & s["good"]).alias("restored"),
        count(lambda s: ~s["bad"] & ~s["good"]).alias("damaged"), F.aggregate("cells", F.lit(0.0), lambda acc, s: acc + F.coalesce(s["sq"], F.lit(0.0))).alias("sq"),
    )
    total = sums.agg(*[F.sum(c).alias(c) for c in ("n", "bad", "restored", "damaged")], F.sqrt(F.sum("sq") / F.sum("n")).alias("rmse"))
    return total.select(F.col("bad").alias("n_misplaced"), F.col("restored").alias("n_restored"), F.col("damaged").alias("n_damaged"), F.try_divide(F.col("restored").cast("double"), F.col("bad").cast("double")).alias("restored_share"), "rmse")


def bit_confusion(runs: DataFrame, truth_runs: DataFrame) -> DataFrame:
    """Points of each cycle that are false and missing, from runs (eq_id, sigma, l, r) on both sides."""
    length = lambda df, name: df.groupBy("eq_id", "sigma").agg(F.sum(F.col("r") - F.col("l") + 1).alias(name))
    both = overlap_join(runs, truth_runs, F.col("a_sigma") == F.col("b_sigma"))
    common = both.groupBy(F.col("a_eq_id").alias("eq_id"), F.col("a_sigma").alias("sigma")).agg(F.sum(F.least("a_r", "b_r") - F.greatest("a_l", "b_l") + 1).alias("tp"))
    rows = length(runs, "have").join(length(truth_runs, "want"), ["eq_id", "sigma"], "full").join(common, ["eq_id", "sigma"], "left").fillna(0, ["have", "want", "tp"])
    return rows.select("eq_id", "sigma", "tp", (F.col("have") - F.col("tp")).alias("fp"), (F.col("want") - F.col("tp")).alias("fn"))


def truth_runs(truth: DataFrame) -> DataFrame:
    return truth.select("eq_id", F.explode("phi").alias("c"), "l", "r").select("eq_id", perm.cycle_key(F.col("c")).alias("sigma"), "l", "r")


def escalation_rate(candidates: DataFrame, last: DataFrame) -> DataFrame:
    points = last.agg(F.sum("last").alias("n_points"))
    return candidates.agg(F.count_if(F.col("status") == "escalated").alias("n_escalated")).crossJoin(points).select("n_escalated", "n_points", F.try_divide(F.col("n_escalated").cast("double"), F.col("n_points").cast("double")).alias("rate"))
