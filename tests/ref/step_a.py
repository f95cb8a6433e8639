"""Step A point by point in plain Python, written from the method's description and not from the engine's code.

Sums run over the window anew at every point, supports come from the math library, matchings from trying them all.
"""

from __future__ import annotations

import itertools
import math


def support(z: float, family: str) -> float:
    z = abs(z)
    if family == "chebyshev":
        return 1.0 if z <= 1 else z**-2
    if family == "kernel":
        return max(math.exp(-z * z / 2), 1e-300)
    return max(math.erfc(z / math.sqrt(2)), 1e-300)


def best_matching(w: list[list[float]]) -> tuple[int, ...]:
    return min(itertools.permutations(range(len(w))), key=lambda p: (-round(sum(w[i][j] for i, j in enumerate(p)), 12), p))


def greedy_matching(w: list[list[float]]) -> tuple[int, ...]:
    left = {(i, j) for i in range(len(w)) for j in range(len(w))}
    to = {}
    while left:
        i, j = min(left, key=lambda e: (-w[e[0]][e[1]], e))
        to[i] = j
        left = {e for e in left if e[0] != i and e[1] != j}
    return tuple(to[i] for i in range(len(w)))


def step_a(points, gamma, mode, theta, family, window, prior, epsilon, objective="sum", greedy=False, update="sliding", policy="paper", size_mode="matched"):
    """points: (n, readings); gamma: (mean, deviation) of each sensor. Rows (n, abnormal, dst, status)."""
    held, out = [], []
    for n, x in points:
        now = []
        for m, (mean, dev) in enumerate(gamma):
            seen = [h[m] for h in held]
            total = prior + len(seen)
            mu = (prior * mean + math.fsum(seen)) / total
            second = (prior * (dev**2 + mean**2) + math.fsum(v * v for v in seen)) / total
            now.append((mean, dev) if mode == "frozen" else (mu, math.sqrt(max(second - mu * mu, 1e-18))))
        fit = lambda v, m, now=now: support((v - now[m][0]) / now[m][1], family)
        odd = [m for m, v in enumerate(x) if fit(v, m) < theta]
        y, dst, status = list(x), [], "single" if odd else None
        if len(odd) >= 2:
            status = "escalated"
            if size_mode == "moved" or len(odd) <= epsilon:
                w = [[fit(x[u], v) for v in odd] for u in odd]
                if objective == "log":
                    w = [[math.log(max(v, 1e-300)) for v in row] for row in w]
                dst = [odd[j] for j in (greedy_matching if greedy else best_matching)(w)]
                if size_mode == "matched" or sum(a != b for a, b in zip(odd, dst, strict=True)) <= epsilon:
                    status = "repaired"
                    for u, v in zip(odd, dst, strict=True):
                        y[v] = x[u]
        if status:
            out.append((n, odd, dst, status))
        if mode == "feedback" and policy == "guarded":
            y = [now[m][0] if fit(v, m) < theta else v for m, v in enumerate(y)]
        held.append(list(x) if mode == "rolling" else y)
        if update == "sliding":
            held = held[-window:]
    return out
