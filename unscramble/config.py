"""All options of a repair."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class RepairConfig:
    """Defaults are ours where the method leaves a value open; as_printed() takes its listing literally."""

    method: str = "full"  # full, greedy, candidate, block, none, pointwise
    mode: str = "frozen"  # frozen, rolling, feedback
    family: str = "chebyshev"  # chebyshev, kernel, tail, empirical
    regime: bool = False  # models and panel have a working condition each, and models hold in theirs
    detector: str | None = None  # name of a registered detector that decides what is abnormal, in the place of theta_m
    theta_m: float = 0.12  # a reading is abnormal below this support
    window: int = 100
    prior_weight: float = 100.0  # how many points the learned model counts for beside the window
    epsilon: int = 24  # more matched sensors than this: a person decides
    size_mode: str = "matched"  # matched, moved
    objective: str = "sum"  # sum, log
    match: str = "auto"  # auto, flow, assign, enum, greedy
    update: str = "sliding"  # sliding, cumulative
    update_policy: str = "paper"  # paper, guarded
    len1: int = 20
    len2: int = 20
    theta_tau: float = 0.3
    tau_mode: str = "guarded"  # guarded, symmetric
    merge: str = "two_pass"  # two_pass, snapshot, progressive
    lam: float = 1.0
    block_stat: str = "mean"  # mean, median, last
    match_rule: str = "iou"  # iou, exact, tolerance, overlap
    iou: float = 0.5
    tolerance: int = 5
    detection_unit: str = "constant"  # constant, merged
    phi_rule: str = "equal"  # equal, covers

    def with_(self, **changes) -> RepairConfig:
        return replace(self, **changes)


def as_printed() -> RepairConfig:
    return RepairConfig(tau_mode="symmetric", merge="progressive", update_policy="paper", mode="feedback", objective="sum")
