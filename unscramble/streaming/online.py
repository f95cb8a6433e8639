"""The repair of live readings: candidates at once, intervals when later runs can't change them any more.

A gap is filled when it is short beside the runs on both sides, and how long the next run will be is not known while
readings arrive. So without max_run an interval comes out when its equipment is finished; with max_run it comes out
sooner, under the promise that no run of a cycle is longer, and differs from the batch result where one is.

State of an equipment: readings that wait for the watermark (so that they are scored in order of time), the window of
the last repaired tuples, and the open runs of every cycle. Readings behind the watermark are dropped and counted.
"""

from __future__ import annotations

import pickle
from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from unscramble.config import RepairConfig
from unscramble.operators.candidates import Feedback
from unscramble.operators.model import packed
from unscramble.scratch import few

OUTPUT = "eq_id long, kind string, n long, l long, r long, sigma string, status string, n_late long"
STATE = "blob binary"


def _cycles(ab: list[int], dst: list[int]) -> list[str]:
    nxt, out, seen = dict(zip(ab, dst, strict=True)), [], set()
    for s in ab:
        if s in seen or nxt[s] == s:
            continue
        walk = [s]
        while nxt[walk[-1]] != s:
            walk.append(nxt[walk[-1]])
        seen.update(walk)
        out.append(">".join(map(str, walk)))
    return out


class Online:
    """One equipment's recursion with the open runs of its cycles."""

    def __init__(self, mu: list[float], sigma: list[float], cfg: RepairConfig, max_run: int | None = None):
        self.cfg, self.max_run = cfg, max_run
        self.feedback = Feedback(np.asarray(mu, float), np.asarray(sigma, float), cfg, np.zeros((0, len(mu))))
        self.waiting: list[tuple[int, list[float]]] = []
        self.n, self.late, self.done = 0, 0, -1
        self.open: dict[str, list[int]] = {}  # cycle -> [first, last] of its run, short gaps filled

    def __getstate__(self) -> dict:
        """Readings that wait go along as two arrays, not one by one."""
        ts = np.array([t for t, _ in self.waiting], np.int64)
        return self.__dict__ | {"waiting": (ts, np.array([x for _, x in self.waiting], float))}

    def __setstate__(self, kept: dict) -> None:
        ts, xs = kept["waiting"]
        self.__dict__.update(kept, waiting=list(zip(ts.tolist(), xs.tolist(), strict=True)))

    def arrive(self, ts: int, x: list[float]) -> None:
        if ts <= self.done:
            self.late += 1
        else:
            self.waiting.append((ts, x))

    def advance(self, watermark: int) -> list[tuple]:
        """Score what can't be preceded by anything any more; closed intervals come out with the candidates."""
        out = []
        self.waiting.sort()
        due = bisect_right(self.waiting, watermark, key=lambda w: w[0])
        ready, self.waiting = self.waiting[:due], self.waiting[due:]
        xs = np.array([x for _, x in ready], float).reshape(len(ready), len(self.feedback.mu))  # None becomes NaN
        scored = {i: rest for i, *rest in self.feedback.steps(xs)}
        for i, (self.done, _) in enumerate(ready):
            self.n += 1
            if i in scored:
                ab, dst, status = scored[i]
                found = _cycles(ab, dst) if status == "repaired" else []
                out += [("candidate", self.n, None, None, c, status) for c in found] or [("candidate", self.n, None, None, None, status)]
                for c in found:
                    run = self.open.get(c)
                    if run and self.n - run[1] - 1 < self.cfg.theta_tau * (run[1] - run[0] + 2):
                        run[1] = self.n
                    else:
                        out += self.close(c)
                        self.open[c] = [self.n, self.n]
            for c, (first, last) in list(self.open.items()) if self.max_run else ():
                if self.n - last >= self.cfg.theta_tau * (last - first + 1 + self.max_run):
                    out += self.close(c)
        return out

    def close(self, c: str) -> list[tuple]:
        run = self.open.pop(c, None)
        if run and run[1] - run[0] + 1 >= self.cfg.len2:
            return [("interval", None, run[0], run[1], c, "repaired")]
        return []

    def finish(self) -> list[tuple]:
        return self.advance(1 << 62) + [row for c in list(self.open) for row in self.close(c)]


def stream_repair(
    panel: DataFrame, mu: list[float] | None, sigma: list[float] | None, cfg: RepairConfig, late: str = "1 day", idle: str | None = None, max_run: int | None = 200, models: DataFrame | None = None
) -> DataFrame:
    """Candidates and intervals of a stream of tuples (eq_id, ts, x). All tuples are scored in order of ts.

    models: a model table, for equipments with models of their own; without it mu and sigma hold for all equipments.
    An equipment is finished when the watermark passes its last reading by the time idle, in milliseconds. max_run: the
    longest run that intervals may wait for (see above); None waits for the end. How often a cycle occurs in all isn't
    known while readings arrive, so the stream has neither the frequency cut nor claims of larger units on smaller ones.
    """
    wait = int(idle or 86_400_000)

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        live: Online | None = pickle.loads(state.get[0]) if state.exists else None
        if state.hasTimedOut:
            out = live.finish()
            state.remove()
        else:
            for pdf in batches:
                if live is None and len(pdf):
                    live = Online(list(pdf["mu"].iloc[0]), list(pdf["sigma"].iloc[0]), cfg, max_run)
                for ts, x in zip(pdf["us"].tolist(), pdf["x"], strict=True):
                    live.arrive(ts, x.tolist())
            out = live.advance(state.getCurrentWatermarkMs() * 1000)
            state.update((pickle.dumps(live),))
            latest = max([t for t, _ in live.waiting], default=live.done)
            state.setTimeoutTimestamp(max(latest // 1000 + wait, state.getCurrentWatermarkMs() + 1))
        rows = [(key[0], *row, live.late) for row in out]
        frame = pd.DataFrame(rows, columns=[c.split()[0] for c in OUTPUT.split(", ")])
        yield frame.astype({c: "Int64" for c in ("n", "l", "r", "n_late")})

    if models is None:
        fitted = panel.withColumn("mu", F.lit(list(map(float, mu)))).withColumn("sigma", F.lit(list(map(float, sigma))))
    else:
        fitted = panel.join(few(packed(models), "models"), "eq_id")
    timed = fitted.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).withColumn("us", F.unix_micros("ts"))
    return timed.select("eq_id", "ts", "us", "x", "mu", "sigma").groupBy("eq_id").applyInPandasWithState(step, OUTPUT, STATE, "append", GroupStateTimeout.EventTimeTimeout)
