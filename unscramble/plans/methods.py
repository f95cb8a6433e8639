"""Whole methods: the complete one and those it is compared with."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from unscramble.config import RepairConfig
from unscramble.functions import perm
from unscramble.operators import candidates as candidates_
from unscramble.operators import determine as determine_
from unscramble.operators import metrics
from unscramble.scratch import stored
from unscramble.sources.inject import extent

METHODS = ("full", "greedy", "candidate", "block")


@dataclass
class RepairResult:
    repaired: DataFrame  # a panel
    schemas: DataFrame  # eq_id, l, r, phi
    units: DataFrame | None
    candidates: DataFrame | None
    escalations: DataFrame | None
    intervals: DataFrame | None = None
    waves: int = 0


def repair(panel: DataFrame, models: DataFrame, cfg: RepairConfig | None = None, equipments: int | None = None, history: DataFrame | None = None, found: DataFrame | None = None) -> RepairResult:
    """equipments: a bound, if one is known, for what is broadcast (else looked up). history: what a detector learns from.
    found: stored candidates, if the panel's with the basis of cfg are there already."""
    cfg = cfg or RepairConfig()
    if cfg.method == "none":
        return RepairResult(panel, panel.sparkSession.createDataFrame([], f"eq_id long, l long, r long, phi {perm.CYCLES}"), None, None, None)
    if cfg.method == "pointwise":
        return RepairResult(candidates_.pointwise(panel, models, cfg), panel.sparkSession.createDataFrame([], f"eq_id long, l long, r long, phi {perm.CYCLES}"), None, None, None)
    if cfg.method == "block":
        return block_repair(panel, models, cfg, equipments)
    if found is None:
        found = stored(candidates_.candidate_schemas(panel, models, cfg, equipments, history), "candidates")
    if cfg.method == "candidate":
        return RepairResult(candidates_.candidate_panel(panel, found), candidate_intervals(found), None, found, candidates_.escalations(found))
    done = determine_.determine(found, extent(panel), cfg)
    schemas = stored(done.schemas, "schemas")
    unit = schemas if cfg.detection_unit == "constant" else determine_.merged(schemas)
    return RepairResult(determine_.apply_schemas(panel, schemas), unit, done.units, found, candidates_.escalations(found), done.intervals, done.waves)


def candidate_intervals(found: DataFrame) -> DataFrame:
    """Candidates taken as they are: maximal intervals of one and the same candidate."""
    rows = found.filter("size(cycles) > 0").select("eq_id", "n", "cycles")
    w = Window.partitionBy("eq_id").orderBy("n")
    same = F.coalesce((F.lag("n").over(w) + 1 == F.col("n")) & (F.lag("cycles").over(w) == F.col("cycles")), F.lit(False))
    groups = rows.withColumn("_g", F.sum(F.when(same, 0).otherwise(1)).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return groups.groupBy("eq_id", "_g").agg(F.min("n").alias("l"), F.max("n").alias("r"), F.first("cycles").alias("phi")).drop("_g")


def block_length(points: int, lam: float) -> int:
    return max(1, -(-int(lam * points**0.5 * 1000) // 1000))


def blocks(panel: DataFrame, length: int, stat: str = "mean") -> DataFrame:
    """One tuple for each block of so many points; a last shorter block is kept."""
    long = panel.select("eq_id", F.floor((F.col("n") - 1) / length).alias("b"), "n", F.posexplode("x").alias("m", "x"))
    value = {"mean": F.avg("x"), "median": F.percentile("x", 0.5), "last": F.max_by("x", "n")}[stat]
    cells = long.groupBy("eq_id", "b", "m").agg(value.alias("x"))
    wide = cells.groupBy("eq_id", "b").agg(F.transform(F.array_sort(F.collect_list(F.struct("m", "x"))), lambda s: s["x"]).alias("x"))
    return wide.select("eq_id", (F.col("b") + 1).cast("long").alias("n"), F.lit(None).cast("timestamp").alias("ts"), F.lit(None).cast("string").alias("regime"), "x")


def block_repair(panel: DataFrame, models: DataFrame, cfg: RepairConfig, equipments: int | None = None) -> RepairResult:
    """Blocks are judged and repaired as wholes; bounds snap to blocks."""
    last = extent(panel)
    most = last.agg(F.max("last")).first()[0] or 1
    length = block_length(most, cfg.lam)
    inner = cfg.with_(method="full", len1=max(1, -(-cfg.len1 // length)), len2=max(1, -(-cfg.len2 // length)))
    got = repair(stored(blocks(panel, length, cfg.block_stat), "blocks"), models, inner, equipments)
    wide = got.schemas.join(last, "eq_id").select("eq_id", ((F.col("l") - 1) * length + 1).alias("l"), F.least(F.col("r") * length, "last").alias("r"), "phi")
    return RepairResult(determine_.apply_schemas(panel, wide), wide, got.units, got.candidates, got.escalations, got.intervals, got.waves)


def evaluated(result: RepairResult, truth: DataFrame, cfg: RepairConfig) -> DataFrame:
    return metrics.scores(result.schemas, truth, cfg.match_rule, cfg.phi_rule, cfg.iou, cfg.tolerance)
