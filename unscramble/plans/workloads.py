"""The experiment workloads on panels made from the given tables.

Errors are injected deterministically; where an experiment was made on real errors this differs, and so may levels.
"""

from __future__ import annotations

import time
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.config import RepairConfig
from unscramble.operators import candidates, detect, metrics
from unscramble.operators.model import fit_moments
from unscramble.plans.methods import METHODS, evaluated, repair
from unscramble.scratch import stored
from unscramble.sources import inject, panels

RESULT = "workload string, method string, x double, n_found long, n_true long, n_correct long, n_repaired long, p_d double, r_d double, p_r double, r_r double, p_r_alt double, r_r_alt double, seconds double"


class Source:
    """A clean calibrated panel with its history and models, stored once for several workbenches."""

    def __init__(self, spark: SparkSession, sf_dir: str, g: float = 2.0, sensors: int = 48, percent: int = 100):
        clean = panels.calibrated_panel(spark, sf_dir, g, sensors)
        self.clean = stored(panels.prefix(clean, percent) if percent < 100 else clean, "clean")
        self.history = stored(panels.calibrated_panel(spark, sf_dir, g, sensors, history=True), "history")
        self.models = stored(fit_moments(self.history), "models")


class Workbench:
    """A corrupted panel with its truth and models, stored once for all methods."""

    def __init__(self, spark: SparkSession, sf_dir: str, attributes: int = 12, sensors: int = 48, g: float = 2.0, percent: int = 100, drift: float = 0.0, name: str = "calibrated", source: Source | None = None, ranked: dict[bool, DataFrame] | None = None):
        """ranked: items in the order of the calibrated panel (False) and of its history (True), where they are there already."""
        history, ranked = None, ranked or {}
        self.found: dict[RepairConfig, tuple[DataFrame, float]] = {}
        if source:
            clean = source.clean
        elif name == "calibrated":
            clean = panels.calibrated_panel(spark, sf_dir, g, sensors, drift=drift, ranked=ranked.get(False))
            history = panels.calibrated_panel(spark, sf_dir, g, sensors, history=True, ranked=ranked.get(True))
        elif name == "example":
            clean = panels.example_panel(spark, sf_dir, g)
            history = panels.example_panel(spark, sf_dir, g, history=True)
        else:
            clean = {"native": panels.native_panel, "ticks": panels.event_ticks, "ordinals": panels.event_ordinals, "embeddings": panels.embedding_panel}[name](spark, sf_dir)
        whole = percent >= 100
        self.clean = clean if source and whole else stored(clean if whole else panels.prefix(clean, percent), "clean")
        ends = inject.extent(self.clean)
        truth = inject.example_plan(ends) if name == "example" else inject.plan(ends, attributes, sensors)
        self.truth = stored(truth, "truth")
        self.panel = stored(inject.inject(self.clean, self.truth), "panel")
        if source:
            self.history, self.models = source.history, source.models
        else:
            self.history = self.clean if history is None else stored(history, "history")
            self.models = stored(fit_moments(self.history), "models")

    def run(self, workload: str, method: str, x: float, cfg: RepairConfig | None = None) -> tuple:
        """One run and its measures. Candidates that an earlier run has made are taken from there, and the seconds that
        they took there count in this run as well."""
        cfg = (cfg or RepairConfig()).with_(method=method)
        found, seconds = (None, 0.0) if method in ("block", "none", "pointwise") else self.candidates(cfg)
        began = time.time() - seconds
        result = repair(self.panel, self.models, cfg, history=self.history, found=found)
        row = evaluated(result, self.truth, cfg).first()
        result.repaired.write.format("noop").mode("overwrite").save()
        return (workload, method, float(x), *row, time.time() - began)


    def candidates(self, cfg: RepairConfig) -> tuple[DataFrame, float]:
        """Stored candidates, made once for each basis, and the seconds that took."""
        key = candidates.basis(cfg)
        if key not in self.found:
            began = time.time()
            self.found[key] = stored(candidates.candidate_schemas(self.panel, self.models, key, history=self.history), "candidates"), time.time() - began
        return self.found[key]


def _rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, RESULT)


def overall(spark: SparkSession, sf_dir: str, methods: Iterable[str] = METHODS) -> DataFrame:
    """W3: all methods on 90 % of the 48-sensor panel and 80 % of the 150-sensor panel, with frozen models and with models
    that follow the repaired readings."""
    out, ranked = [], {history: panels.ranked_items(spark, sf_dir, history) for history in (False, True)}
    for sensors, percent in ((48, 90), (150, 80)):
        bench = Workbench(spark, sf_dir, 12, sensors, percent=percent, ranked=ranked)
        out += [bench.run("overall", m, sensors) for m in methods]
        out += [bench.run("overall, models follow", m, sensors, RepairConfig(mode="feedback")) for m in methods if m != "block"]
    return _rows(spark, out)


def by_volume(spark: SparkSession, sf_dir: str, methods: Iterable[str] = METHODS, percents: Iterable[int] = (40, 50, 60, 70, 80, 90, 100)) -> DataFrame:
    """W4, W5, W8a: prefixes of the 48-sensor panel with 12 attributes."""
    source = Source(spark, sf_dir)
    return _rows(spark, [b.run("volume", m, p) for p in percents for b in (Workbench(spark, sf_dir, percent=p, source=source),) for m in methods])


def by_attributes(spark: SparkSession, sf_dir: str, methods: Iterable[str] = METHODS, counts: Iterable[int] = (3, 6, 9, 12, 15, 18)) -> DataFrame:
    """W6, W7, W8b: 3 to 18 attributes on 90 % of the panel."""
    source = Source(spark, sf_dir, percent=90)
    return _rows(spark, [b.run("attributes", m, a) for a in counts for b in (Workbench(spark, sf_dir, a, source=source),) for m in methods])


def by_block_length(spark: SparkSession, sf_dir: str, lambdas: Iterable[float] = (0.25, 0.5, 1, 2, 4)) -> DataFrame:
    """W9."""
    b = Workbench(spark, sf_dir)
    return _rows(spark, [b.run("block length", "block", lam, RepairConfig(lam=lam)) for lam in lambdas])


def example(spark: SparkSession, sf_dir: str, methods: Iterable[str] = METHODS) -> DataFrame:
    """W10: five sensors, two swaps, one sensor untouched."""
    b = Workbench(spark, sf_dir, name="example", g=3.0)
    return _rows(spark, [b.run("example", m, 5) for m in methods])


def detectors(spark: SparkSession, sf_dir: str, names: Iterable[str] | None = None) -> DataFrame:
    """W11: share of misplaced cells that each detector flags, and of right cells that it flags wrongly."""
    b = Workbench(spark, sf_dir)
    bad = F.filter(F.transform(F.zip_with("d", "t", lambda a, t: a != t), lambda v, m: F.when(v, m)), lambda m: m.isNotNull())
    marked = b.panel.withColumnRenamed("x", "d").join(b.clean.select("eq_id", "n", F.col("x").alias("t")), ["eq_id", "n"])
    panel = stored(marked.select("eq_id", "n", "ts", "regime", F.col("d").alias("x"), bad.alias("bad")), "marked")
    return one_by_one(panel, b.history, names or detect.DETECTORS)


def one_by_one(panel: DataFrame, history: DataFrame, names: Iterable[str]) -> DataFrame:
    """Counts of each detector's flags on a panel with its misplaced sensors (bad). The marks go through a detector with
    its rows, so that cells aren't joined; each detector's counts are stored before the next one starts."""
    out = None
    for name in names:
        cells = detect.DETECTORS[name](panel, history).select("flag", F.array_contains("bad", F.col("m")).alias("bad"))
        row = cells.agg(
            F.lit(name).alias("detector"), F.count_if(F.col("bad")).alias("n_bad"), F.count_if(F.col("bad") & F.col("flag")).alias("n_hit"), F.count_if(~F.col("bad") & F.col("flag")).alias("n_false"),
            F.try_divide(F.count_if(F.col("bad") & F.col("flag")).cast("double"), F.count_if(F.col("bad")).cast("double")).alias("recall"),
            F.try_divide(F.count_if(F.col("bad") & F.col("flag")).cast("double"), F.count_if(F.col("flag")).cast("double")).alias("precision"),
        )
        row = stored(row, "detector")
        out = row if out is None else out.unionByName(row)
    return out


def other_panels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W12, W14 and event ordinals: panels with sensors that are hard to tell apart."""
    out = []
    for name, sensors, attributes in (("native", 9, 6), ("ordinals", 5, 4), ("embeddings", 64, 12)):
        b = Workbench(spark, sf_dir, attributes, sensors, name=name)
        out += [b.run(name, m, sensors, RepairConfig(len1=5, len2=5)) for m in ("full", "candidate")]
    return _rows(spark, out)


def ablations(spark: SparkSession, sf_dir: str, drift: float = 0.0) -> DataFrame:
    """W16: without what the complete method consists of, one part at a time."""
    b = Workbench(spark, sf_dir, drift=drift)
    base = RepairConfig()
    variants = {
        "full": base, "rolling": base.with_(mode="rolling"), "feedback": base.with_(mode="feedback"), "no frequency cut": base.with_(len1=0), "no smoothing": base.with_(theta_tau=0.0),
        "symmetric smoothing": base.with_(tau_mode="symmetric"), "no least length": base.with_(len2=1), "log objective": base.with_(objective="log"),
        "snapshot": base.with_(merge="snapshot"), "progressive": base.with_(merge="progressive"), "merged detections": base.with_(detection_unit="merged"), "kernel": base.with_(family="kernel", theta_m=0.02),
    }
    return _rows(spark, [(f"ablation {k}", *b.run(k, "full", i, v)[1:]) for i, (k, v) in enumerate(variants.items())])


def quality_of(workbench: Workbench, cfg: RepairConfig) -> DataFrame:
    """All measures of one run in long form: measure, value."""
    result = repair(workbench.panel, workbench.models, cfg)
    schemas = stored(result.schemas, "found")
    parts = [evaluated(result, workbench.truth, cfg), metrics.bound_error(schemas, workbench.truth), metrics.cell_scores(workbench.clean, workbench.panel, result.repaired)]
    if result.candidates is not None:
        parts.append(metrics.escalation_rate(result.candidates, inject.extent(workbench.panel)))
    rows = [p.select(F.explode(F.array(*[F.struct(F.lit(c).alias("measure"), F.col(c).cast("double").alias("value")) for c in p.columns])).alias("s")).select("s.*") for p in parts]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out
