"""Candidate repairs point by point (Step A).

Rows (eq_id, n, ts, abnormal, src, dst, size, status, cycles): src and dst say where each abnormal reading belongs,
status is repaired, escalated (too many sensors: a person decides) or single (one abnormal sensor: nothing to match).
Only points with an abnormal sensor have a row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unscramble.config import RepairConfig
from unscramble.functions import perm
from unscramble.functions.support import FLOOR, TAIL
from unscramble.operators import detect, matching
from unscramble.operators.model import packed
from unscramble.scratch import few, stored

CANDIDATE = "eq_id long, n long, ts timestamp, abnormal array<int>, src array<int>, dst array<int>, size int, status string"


def flagged(panel: DataFrame, models: DataFrame, cfg: RepairConfig, equipments: int | None = None, history: DataFrame | None = None) -> DataFrame:
    """Points with their models and their abnormal sensors; with a detector only points that have some."""
    if cfg.detector:
        if cfg.mode != "frozen" or history is None:
            raise ValueError("a detector takes frozen models for the matching, and the history that it learns from")
        found = detect.flagged_panel(detect.DETECTORS[cfg.detector](panel, history))
        columns = ("mu", "sigma", "lo", "hi", "mass") if cfg.family == "empirical" else ("mu", "sigma")
        keys = ("eq_id", "regime") if cfg.regime else ("eq_id",)
        return detect.with_models(panel, packed(models, columns, keys), equipments, keys).join(found, ["eq_id", "n"])
    if cfg.mode == "frozen":
        return detect.flag(panel, models, cfg.theta_m, cfg.family, equipments, cfg.regime)
    if cfg.regime:
        raise ValueError("working conditions need frozen models")
    if cfg.mode == "rolling":
        return detect.rolling(panel, models, cfg.window, cfg.prior_weight, cfg.theta_m, cfg.family)
    raise ValueError(f"mode {cfg.mode} has no flags apart from its candidates")


def gate(flags: DataFrame, least: int = 2) -> DataFrame:
    """Points worth a matching. Nearly all rows of a clean panel end here, before any weight is computed."""
    return flags.filter(F.size("abnormal") >= least)


def basis(cfg: RepairConfig) -> RepairConfig:
    """cfg with only what candidates depend on: those with the same basis have the same candidates."""
    kept = ("mode", "family", "regime", "detector", "theta_m", "window", "prior_weight", "epsilon", "size_mode", "objective", "match", "update", "update_policy")
    return RepairConfig(method="greedy" if cfg.method == "greedy" else "full", **{name: getattr(cfg, name) for name in kept})


def candidate_schemas(panel: DataFrame, models: DataFrame, cfg: RepairConfig, equipments: int | None = None, history: DataFrame | None = None) -> DataFrame:
    if cfg.mode == "feedback":
        if cfg.detector or cfg.regime:
            raise ValueError("feedback has neither detectors nor working conditions")
        return with_cycles(feedback_candidates(panel, models, cfg))
    flags = gate(flagged(panel, models, cfg, equipments, history), 1)
    how = "greedy" if cfg.method == "greedy" else cfg.match
    a = F.size("abnormal")
    early = F.lit(False) if cfg.size_mode == "moved" else a > cfg.epsilon  # the size is known before matching
    none = F.expr("cast(array() as array<array<double>>)")
    w = F.when((a >= 2) & ~early, matching.weights(cfg.family, cfg.objective)).otherwise(none)
    rows = flags.select("eq_id", "n", "ts", "abnormal", w.alias("w")).withColumn("to", matching.matched(F.col("w"), how))
    none = F.expr("cast(array() as array<int>)")
    placed = perm.let(F.struct("to", "abnormal"), lambda p: F.struct(F.when(F.size(p["to"]) > 0, p["abnormal"]).otherwise(none).alias("src"), F.transform(p["to"], lambda j: p["abnormal"][j]).alias("dst")))
    rows = rows.select("eq_id", "n", "ts", "abnormal", placed.alias("placed")).select("eq_id", "n", "ts", "abnormal", "placed.src", "placed.dst")
    moved = F.size(F.filter(F.zip_with("src", "dst", lambda u, v: u != v), lambda b: b))
    size = F.size("abnormal") if cfg.size_mode == "matched" else moved
    status = F.when(F.size("abnormal") < 2, "single").when(size > cfg.epsilon, "escalated").otherwise("repaired")
    return with_cycles(rows.withColumn("size", size).withColumn("status", status))


def with_cycles(rows: DataFrame) -> DataFrame:
    none = F.expr("cast(array() as array<int>)")
    sides = [F.when(F.col("status") == "repaired", F.col(c)).otherwise(none) for c in ("src", "dst")]
    return rows.withColumn("cycles", matching.cycles(*sides))


def candidate_panel(panel: DataFrame, candidates: DataFrame) -> DataFrame:
    """The panel with each point's own candidate undone."""
    moved = candidates.filter("status = 'repaired' AND size(cycles) > 0").select("eq_id", "n", "cycles")
    joined = panel.join(moved, ["eq_id", "n"], "left")
    return joined.select("eq_id", "n", "ts", "regime", F.when(F.col("cycles").isNotNull(), perm.apply_cycles(F.col("x"), F.col("cycles"))).otherwise(F.col("x")).alias("x"))


def pointwise(panel: DataFrame, models: DataFrame, cfg: RepairConfig) -> DataFrame:
    """Cleaning of single points for comparison: abnormal readings become their model's mean."""
    flags = flagged(panel, models, cfg)
    y = F.transform("x", lambda v, m: F.when(F.array_contains("abnormal", m), F.col("mu")[m]).otherwise(v))
    return flags.select("eq_id", "n", "ts", "regime", y.alias("x"))


def escalations(candidates: DataFrame) -> DataFrame:
    return candidates.filter("status = 'escalated'")


# --- feedback: models that follow the repaired readings ----------------------------------------------------------


def _support(z: np.ndarray, family: str) -> np.ndarray:
    z = np.abs(z)
    if family == "kernel":
        return np.maximum(np.exp(-z * z / 2), FLOOR)
    if family == "tail":
        a = z / np.sqrt(2)
        t = 1 / (1 + a / 2)
        return np.clip(t * np.exp(-a * a + np.polyval(TAIL[::-1], t)), FLOOR, 1.0)
    if family != "chebyshev":
        raise ValueError(f"feedback and streams have no family {family}: their models are moments")
    with np.errstate(divide="ignore"):
        return np.where(z <= 1, 1.0, 1 / (z * z))


class Feedback:
    """The recursion over one equipment: score against the learned model joined with the last repaired readings,
    match, repair, and let the result into the window."""

    def __init__(self, mu: np.ndarray, sigma: np.ndarray, cfg: RepairConfig, window: np.ndarray):
        self.cfg, self.mu, self.sigma = cfg, mu, sigma
        self.rows = list(window)
        self.k, self.s, self.ss = len(window), window.sum(0), (window**2).sum(0)

    def step(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, str]:
        """(abnormal sensors, where their readings belong, status) of the next point."""
        cfg, pw = self.cfg, self.cfg.prior_weight
        total = pw + self.k
        mu = (pw * self.mu + self.s) / total
        var = np.maximum((pw * (self.sigma**2 + self.mu**2) + self.ss) / total - mu**2, 1e-18)
        sd = np.sqrt(var)
        known = ~np.isnan(x)
        p = np.where(known, _support((x - mu) / sd, cfg.family), 1.0)
        ab = np.flatnonzero(p < cfg.theta_m)
        dst, status, y = np.zeros(0, int), "ok" if not len(ab) else "single", x
        if len(ab) >= 2:
            status = "escalated"
            if cfg.size_mode == "moved" or len(ab) <= cfg.epsilon:
                w = _support((x[ab][:, None] - mu[ab][None, :]) / sd[ab][None, :], cfg.family)
                w = np.log(np.maximum(w, FLOOR)) if cfg.objective == "log" else w
                exact = cfg.method != "greedy" and cfg.match != "greedy"
                to = (matching.assign if exact else matching.greedy_numpy)(w)
                dst = ab[to]
                if cfg.size_mode == "matched" or (dst != ab).sum() <= cfg.epsilon:
                    status, y = "repaired", x.copy()
                    y[dst] = x[ab]
        push = np.where(known, y, mu)
        if cfg.update_policy == "guarded":
            still = _support((push - mu) / sd, cfg.family) < cfg.theta_m
            push = np.where(still, mu, push)
        self.rows.append(push)
        self.k, self.s, self.ss = self.k + 1, self.s + push, self.ss + push**2
        if cfg.update == "sliding" and self.k > cfg.window:
            old = self.rows.pop(0)
            self.k, self.s, self.ss = self.k - 1, self.s - old, self.ss - old**2
        return ab, dst, status

    def steps(self, xs: np.ndarray) -> list[tuple[int, list[int], list[int], str]]:
        """(place, abnormal sensors, where their readings belong, status) of those of the next points that have some.

        The result is that of step() for one point after the other. What each point lets into the window is first
        guessed, and a block of points scored on the guess; a point is settled when all before it were guessed right.
        The rest of the block starts again, on what it has let in so far as the next guess.
        """
        out, at, block, guess, missed = [], 0, 64, xs[:0], 0
        while at < len(xs):
            guess = guess[:block] if len(guess) else xs[at : at + block]
            x = xs[at : at + len(guess)]
            settled, push, found = self._block(x, guess)
            out += [(at + i, *f) for i, *f in found if i < settled]
            at, guess = at + settled, push[settled:]
            missed = 0 if settled == len(x) else missed + 1
            block = min(2 * block, 1024) if not missed else max(16, block // 2) if missed > 3 else block
        return out

    def _block(self, x: np.ndarray, guess: np.ndarray) -> tuple[int, np.ndarray, list[tuple]]:
        """How many of the points are settled, what all let into the window, and results of all; the state moves behind
        those that are settled."""
        cfg, pw, many = self.cfg, self.cfg.prior_weight, len(x)
        drops = np.zeros(many, bool) if cfg.update != "sliding" else self.k + np.arange(1, many + 1) > cfg.window
        k = self.k + np.arange(many) - np.concatenate([[0], drops.cumsum()[:-1]])
        leaves = drops.cumsum()
        old = np.array(self.rows[: leaves[-1]]).reshape(-1, x.shape[1])
        old = np.concatenate([old, guess[: leaves[-1] - len(old)]])[leaves[drops] - 1]

        def sums(start: np.ndarray, enter: np.ndarray, leave: np.ndarray) -> np.ndarray:
            each = np.full((2 * many + 1, x.shape[1]), -0.0)  # adding it changes nothing
            each[0], each[1::2] = start, enter
            each[2::2][drops] = -leave
            return np.add.accumulate(each)[::2]

        s, ss = sums(self.s, guess, old), sums(self.ss, guess**2, old**2)
        total = (pw + k)[:, None]
        mu = (pw * self.mu + s[:-1]) / total
        sd = np.sqrt(np.maximum((pw * (self.sigma**2 + self.mu**2) + ss[:-1]) / total - mu**2, 1e-18))
        known = ~np.isnan(x)
        below = np.where(known, _support((x - mu) / sd, cfg.family), 1.0) < cfg.theta_m
        y, found, sizes = x.copy(), [], below.sum(1)
        for a in np.unique(sizes[sizes > 0]):
            rows = np.flatnonzero(sizes == a)
            ab = np.nonzero(below[rows])[1].reshape(-1, a)
            if a < 2 or (cfg.size_mode != "moved" and a > cfg.epsilon):
                found += [(i, u, [], "single" if a < 2 else "escalated") for i, u in zip(rows.tolist(), ab.tolist(), strict=True)]
                continue
            at = rows[:, None]
            w = _support((x[at, ab][:, :, None] - mu[at, ab][:, None, :]) / sd[at, ab][:, None, :], cfg.family)
            w = np.log(np.maximum(w, FLOOR)) if cfg.objective == "log" else w
            exact = cfg.method != "greedy" and cfg.match != "greedy"
            dst = np.take_along_axis(ab, (matching.exact_many if exact else matching.greedy_many)(w), 1)
            fine = np.full(len(rows), True) if cfg.size_mode == "matched" else (dst != ab).sum(1) <= cfg.epsilon
            y[at[fine], dst[fine]] = x[at[fine], ab[fine]]
            found += [(i, u, v, "repaired" if ok else "escalated") for i, u, v, ok in zip(rows.tolist(), ab.tolist(), dst.tolist(), fine.tolist(), strict=True)]
        push = np.where(known, y, mu)
        if cfg.update_policy == "guarded":
            push = np.where(_support((push - mu) / sd, cfg.family) < cfg.theta_m, mu, push)
        wrong = np.flatnonzero(~((push == guess) | (np.isnan(push) & np.isnan(guess))).all(1))
        settled = int(wrong[0]) + 1 if len(wrong) else many
        last = settled - 1  # the one point among them that may have been guessed wrong
        self.s, self.ss = s[last] + push[last], ss[last] + push[last] ** 2
        if drops[last]:
            gone = old[leaves[last] - 1]
            self.s, self.ss = self.s - gone, self.ss - gone**2
        self.rows += list(push[:settled])
        del self.rows[: leaves[last]]
        self.k = len(self.rows)
        return settled, push, sorted(found)


def run_feedback(ns: np.ndarray, xs: np.ndarray, mu: np.ndarray, sigma: np.ndarray, cfg: RepairConfig, window: np.ndarray) -> tuple[list[tuple], np.ndarray]:
    """Rows (n, abnormal, src, dst, size, status) of the points with an abnormal sensor, and the window after the last."""
    state, out = Feedback(mu, sigma, cfg, window), []
    for i, ab, dst, status in state.steps(xs):
        size = len(ab) if cfg.size_mode == "matched" else sum(u != v for u, v in zip(ab, dst, strict=False))
        out.append((int(ns[i]), ab, ab if dst else [], dst, size, status))
    return out, np.array(state.rows).reshape(-1, len(mu))


CHUNK = "eq_id long, chunk long, entry binary, leave binary, found array<struct<n: long, abnormal: array<int>, src: array<int>, dst: array<int>, size: int, status: string>>"


def feedback_candidates(panel: DataFrame, models: DataFrame, cfg: RepairConfig, chunk: int = 2048, run_in: int | None = None) -> DataFrame:
    """Feedback over all points of all equipments, in chunks that run side by side.

    Each chunk first runs over the points before it from an empty window, which gives the window it assumes at entry.
    Chunks whose assumption is not what the chunk before left are run again from the true window, until all agree; that
    is the sequential result. A cumulative update never forgets, so it takes one chunk for each equipment.
    """
    run_in = 2 * cfg.window if run_in is None else run_in
    if cfg.update == "cumulative":
        chunk, run_in = 1 << 40, 0
    gamma = few(packed(models), "gamma")
    keyed = panel.select("eq_id", "n", "x").withColumn("own", F.floor((F.col("n") - 1) / chunk))
    ahead = F.floor((F.col("n") - 1 + run_in) / chunk)
    spread = keyed.withColumn("chunk", F.explode(F.sequence("own", ahead))).withColumn("lead", F.col("chunk") > F.col("own"))
    spread = spread.filter((F.col("chunk") == F.col("own")) | (F.col("chunk") == F.col("own") + 1))
    rows = stored(spread.join(gamma, "eq_id").select("eq_id", "chunk", "lead", "n", "x", "mu", "sigma"), "chunks")

    def run(pdf: pd.DataFrame, entry: bytes | None) -> pd.DataFrame:
        pdf = pdf.sort_values("n")
        mu, sigma = np.asarray(pdf["mu"].iloc[0], float), np.asarray(pdf["sigma"].iloc[0], float)
        xs, lead = np.array([np.asarray(v, float) for v in pdf["x"]]), pdf["lead"].to_numpy()
        window = np.zeros((0, len(mu)))
        if entry is not None:
            window = np.frombuffer(entry).reshape(-1, len(mu))
        elif lead.any():
            _, window = run_feedback(pdf["n"].to_numpy()[lead], xs[lead], mu, sigma, cfg, window)
        found, leave = run_feedback(pdf["n"].to_numpy()[~lead], xs[~lead], mu, sigma, cfg, window) if (~lead).any() else ([], window)
        names = ("n", "abnormal", "src", "dst", "size", "status")
        one = {"eq_id": int(pdf["eq_id"].iloc[0]), "chunk": int(pdf["chunk"].iloc[0]), "entry": window.tobytes(), "leave": leave.tobytes(), "found": [dict(zip(names, f, strict=True)) for f in found]}
        return pd.DataFrame([one])

    def first(pdf: pd.DataFrame) -> pd.DataFrame:
        return run(pdf, None) if (~pdf["lead"]).any() else pd.DataFrame(columns=[c.split()[0] for c in ("eq_id", "chunk", "entry", "leave", "found")])

    def again(points: pd.DataFrame, entries: pd.DataFrame) -> pd.DataFrame:
        if not len(entries) or not len(points):
            return pd.DataFrame(columns=["eq_id", "chunk", "entry", "leave", "found"])
        return run(points, bytes(entries["leave"].iloc[0]))

    done = stored(rows.groupBy("eq_id", "chunk").applyInPandas(first, CHUNK), "feedback")
    while True:
        left = done.select("eq_id", (F.col("chunk") + 1).alias("chunk"), F.col("leave").alias("given"))
        wrong = done.join(left, ["eq_id", "chunk"]).filter("entry <> given").select("eq_id", "chunk", F.col("given").alias("leave"))
        wrong = stored(wrong, "entries")
        if wrong.isEmpty():
            break
        at_fault = rows.join(wrong.select("eq_id", "chunk"), ["eq_id", "chunk"], "left_semi")
        fixed = at_fault.groupBy("eq_id", "chunk").cogroup(wrong.groupBy("eq_id", "chunk")).applyInPandas(again, CHUNK)
        # only chunks that were wrong are written again; each pass makes the next chunk of every equipment right for good
        done = done.join(wrong.select("eq_id", "chunk"), ["eq_id", "chunk"], "left_anti").unionByName(stored(fixed, "feedback"))
    found = done.select("eq_id", F.explode("found").alias("f")).select("eq_id", "f.*")
    return found.join(panel.select("eq_id", "n", "ts"), ["eq_id", "n"]).select("eq_id", "n", "ts", "abnormal", "src", "dst", "size", "status")


def sequential(rows: Iterator[tuple[int, list[float]]], mu: list[float], sigma: list[float], cfg: RepairConfig) -> list[tuple]:
    """The same recursion without Spark, for tests and for streams of one equipment."""
    rows = list(rows)
    return run_feedback(np.array([n for n, _ in rows]), np.array([x for _, x in rows], float), np.asarray(mu, float), np.asarray(sigma, float), cfg, np.zeros((0, len(mu))))[0]
