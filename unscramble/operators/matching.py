"""Readings matched to models: which column each abnormal reading belongs to.

W[i][j] is the support of the i-th abnormal reading under the j-th abnormal sensor's model. A matching is an array to:
reading i goes to the to[i]-th model. All matchers are perfect (every reading gets a model) and break ties alike, by the
smallest array. greedy and enumeration are built-in expressions; the exact matchers run on Arrow batches, and so does greedy
there.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import permutations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from unscramble.functions.perm import let
from unscramble.functions.support import FLOOR, empirical, support

ENUM_LIMIT = 6


def weights(family: str = "chebyshev", objective: str = "sum") -> Column:
    """W for rows with x, abnormal and the models (mu, sigma; empirical: lo, hi, mass): a by a, never all by all sensors."""

    fields = ("lo", "hi", "mass") if family == "empirical" else ("mu", "sigma")

    def of(row: Column) -> Column:
        def cell(u: Column, v: Column) -> Column:
            model = [row[f][v] for f in fields]
            p = empirical(row["x"][u], *model) if family == "empirical" else support(row["x"][u], *model, family)
            return F.log(F.greatest(p, F.lit(FLOOR))) if objective == "log" else p

        return F.transform(row["abnormal"], lambda u: F.transform(row["abnormal"], lambda v: cell(u, v)))

    return let(F.struct("x", *fields, "abnormal"), of)


def edges(df: DataFrame) -> DataFrame:
    """Rows (eq_id, n, u, v, w) of the bipartite graph of each point, from rows with abnormal and w."""
    rows = df.select("eq_id", "n", "abnormal", F.posexplode("w").alias("i", "row"))
    rows = rows.select("eq_id", "n", "abnormal", F.col("abnormal")[F.col("i")].alias("u"), F.posexplode("row").alias("j", "w"))
    return rows.select("eq_id", "n", "u", F.col("abnormal")[F.col("j")].alias("v"), "w")


# --- in expressions ---------------------------------------------------------------------------------------------


def greedy(w: Column) -> Column:
    """Largest remaining weight first; ties to the smaller reading, then the smaller model."""
    return let(w, _greedy)


def _greedy(w: Column) -> Column:
    flat = F.flatten(F.transform(w, lambda row, i: F.transform(row, lambda v, j: F.struct((-v).alias("cost"), i.alias("i"), j.alias("j")))))

    def take(acc: Column, e: Column) -> Column:
        free = (acc[e["i"]] < 0) & ~F.array_contains(acc, e["j"])
        return F.when(free, F.transform(acc, lambda old, k: F.when(k == e["i"], e["j"]).otherwise(old))).otherwise(acc)

    return F.aggregate(F.array_sort(flat), F.transform(w, lambda _: F.lit(-1)), take)


def enumerated(w: Column, limit: int = ENUM_LIMIT) -> Column:
    """The best of all matchings, for at most limit readings (else NULL; matched() hands those to the exact matcher)."""
    return let(w, lambda v: _enumerated(v, limit))


def _enumerated(w: Column, limit: int) -> Column:
    out = F.lit(None).cast("array<int>")
    for a in range(limit, 0, -1):
        every = F.lit([list(p) for p in permutations(range(a))])
        total = lambda p: F.aggregate(F.zip_with(w, p, lambda row, j: row[j]), F.lit(0.0), lambda s, v: s + v)
        best = F.array_min(F.transform(every, lambda p: F.struct(F.round(-total(p), 12).alias("cost"), p.alias("to"))))["to"]  # noqa: B023
        out = F.when(F.size(w) == a, best).otherwise(out)
    return out


# --- exact matchers in numpy ------------------------------------------------------------------------------------


def assign(w: np.ndarray) -> np.ndarray:
    """Maximum-weight perfect matching by shortest augmenting rows with dual prices."""
    a = len(w)
    cost = w.max(initial=0.0) - w
    u, v = np.zeros(a + 1), np.zeros(a + 1)
    owner = np.full(a + 1, -1)  # of each column; the last column stands for the row that is being placed
    for i in range(a):
        owner[a] = i
        j = a
        slack, came, done = np.full(a, np.inf), np.full(a, a), np.zeros(a + 1, bool)
        while owner[j] >= 0:
            done[j] = True
            row = owner[j]
            gap = cost[row] - u[row] - v[:a]
            better = ~done[:a] & (gap < slack)
            slack[better], came[better] = gap[better], j
            open_ = np.where(done[:a], np.inf, slack)
            nxt = int(open_.argmin())
            step = open_[nxt]
            u[owner[done]] += step
            v[done] -= step
            slack[~done[:a]] -= step
            j = nxt
        while j != a:
            owner[j] = owner[came[j]]
            j = came[j]
    to = np.empty(a, int)
    to[owner[:a]] = np.arange(a)
    return least_tied(cost - u[:a, None] - v[None, :a], to)


def flow(w: np.ndarray) -> np.ndarray:
    """The same optimum as a flow: each round sends one unit along the most profitable augmenting path from a free
    reading to a free model, found by relaxing all edges of the residual graph."""
    a = len(w)
    of_row, of_col = np.full(a, -1), np.full(a, -1)
    for _ in range(a):
        gain_row = np.where(of_row < 0, 0.0, -np.inf)
        gain_col, from_row = np.full(a, -np.inf), np.full(a, -1)
        for _ in range(a + 1):
            reach = gain_row[:, None] + w
            taken = of_row >= 0
            reach[np.flatnonzero(taken), of_row[taken]] = -np.inf
            best = reach.argmax(0)
            value = reach[best, np.arange(a)]
            up = value > gain_col + 1e-15
            if not up.any():
                break
            gain_col[up], from_row[up] = value[up], best[up]
            held = np.flatnonzero(of_col >= 0)
            gain_row[of_col[held]] = gain_col[held] - w[of_col[held], held]
        free = np.flatnonzero(of_col < 0)
        j = int(free[gain_col[free].argmax()])
        while j >= 0:
            i = from_row[j]
            before = of_row[i]
            of_row[i], of_col[j] = j, i
            j = before
    u, v = duals(w, of_row)
    return least_tied(u[:, None] + v[None, :] - w, of_row)


def duals(w: np.ndarray, to: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Prices u + v >= w with equality on an optimal matching, by relaxing until nothing changes."""
    a = len(w)
    v = np.zeros(a)
    own = w[np.arange(a), to]
    for _ in range(a + 1):
        need = (w - (own - v[to])[:, None]).max(0)
        if (need <= v + 1e-14).all():
            break
        v = np.maximum(v, need)
    return own - v[to], v


def least_tied(reduced: np.ndarray, to: np.ndarray, eps: float = 1e-12) -> np.ndarray:
    """Among matchings with the same total (all of whose pairs have reduced cost 0) the smallest array."""
    a = len(to)
    tight = np.abs(reduced) <= eps * max(1.0, float(np.abs(reduced).max(initial=0)))
    tight[np.arange(a), to] = True
    if tight.sum() == a:
        return to
    to, fixed = to.copy(), np.zeros(a, bool)

    def place(i: int, banned: set[int]) -> bool:
        """Move row i to another tight column, pushing rows that aren't fixed."""
        for j in np.flatnonzero(tight[i]):
            if j in banned:
                continue
            banned.add(j)
            holder = np.flatnonzero((to == j) & (np.arange(a) != i))
            if not len(holder) or (not fixed[holder[0]] and place(int(holder[0]), banned)):
                to[i] = j
                return True
        return False

    for i in range(a):
        for j in np.flatnonzero(tight[i]):
            if j >= to[i]:
                break
            holder = int(np.flatnonzero(to == j)[0])
            if fixed[holder]:
                continue
            saved = to.copy()
            to[i], fixed[i] = j, True
            if place(holder, {int(j)}):
                break
            to[:], fixed[i] = saved, False
        fixed[i] = True
    return to


def greedy_numpy(w: np.ndarray) -> np.ndarray:
    a = len(w)
    w, to = w.copy(), np.full(a, -1)
    for _ in range(a):
        i, j = divmod(int(w.argmax()), a)
        to[i] = j
        w[i, :], w[:, j] = -np.inf, -np.inf
    return to


def total(w: np.ndarray, to: np.ndarray) -> float:
    return float(w[np.arange(len(to)), to].sum())


MATCHERS: dict[str, Callable[[np.ndarray], np.ndarray]] = {"assign": assign, "flow": flow, "greedy": greedy_numpy}


# --- many matchings of one size at once: w has a matrix for each point -------------------------------------------


CLEAR = 1e-9  # far above what rounding and least_tied call a tie


def plain(w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(to, sure): where every reading goes to the model that takes it best. Sure are points at which these are all
    different, and every other choice of a reading clearly worse: then that is the only best matching."""
    k, a, _ = w.shape
    to = w.argmax(2)
    if a == 1:
        return to, np.ones(k, bool)
    top = np.partition(w, a - 2, axis=2)[:, :, a - 2 :]
    apart = top[:, :, 1] - top[:, :, 0] > CLEAR * np.maximum(1.0, np.abs(w).max((1, 2)))[:, None]
    return to, apart.all(1) & (np.sort(to, 1) == np.arange(a)).all(1)


def exact_many(w: np.ndarray, one: Callable[[np.ndarray], np.ndarray] = assign) -> np.ndarray:
    """one() of every point; only points at which the best choices of readings, and those of models, clash or are close
    are searched one by one."""
    to, sure = plain(w)
    rest = np.flatnonzero(~sure)
    if len(rest):
        of, also = plain(w[rest].swapaxes(1, 2))
        to[rest[also]] = of[also].argsort(1)
        for k in rest[~also]:
            to[k] = one(w[k])
    return to


def greedy_many(w: np.ndarray) -> np.ndarray:
    """greedy_numpy() of every point."""
    k, a, _ = w.shape
    w, to, at = w.copy(), np.full((k, a), -1), np.arange(k)
    for _ in range(a):
        i, j = np.divmod(w.reshape(k, -1).argmax(1), a)
        to[at, i] = j
        w[at, i, :] = -np.inf
        w[at, :, j] = -np.inf
    return to


def by_size(w: pa.Array, f: Callable[[np.ndarray], np.ndarray]) -> pa.Array:
    """f over all matrices of an Arrow array, those of one size at a time."""
    a = w.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    cells = w.flatten().flatten().to_numpy(zero_copy_only=False)
    begin, ends = np.cumsum(a * a) - a * a, np.concatenate([[0], np.cumsum(a)])
    out = np.zeros(ends[-1], np.int32)
    for size in np.unique(a[a > 0]):
        mine = np.flatnonzero(a == size)
        many = cells[begin[mine][:, None] + np.arange(size * size)].reshape(-1, size, size)
        out[ends[mine][:, None] + np.arange(size)] = f(many)
    return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(out))


def _batched(name: str) -> Callable[[pa.Array], pa.Array]:
    def run(w: pa.Array) -> pa.Array:
        return by_size(w, greedy_many if name == "greedy" else lambda many: exact_many(many, MATCHERS[name]))

    return run


def cycles_many(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cycles of many permutations of one size: the row and the length of each cycle, and all their members in order.

    src is in order and dst holds the same sensors. Cycles come as perm.cycles gives them: the least member first, in
    the order of that member."""
    k, a = src.shape
    to = dst.argsort(1).argsort(1)
    at, least = to, np.minimum(np.arange(a), to)
    for _ in range(a - 2):
        at = np.take_along_axis(to, at, 1)
        least = np.minimum(least, at)
    row, lead = np.nonzero((least == np.arange(a)) & (to != np.arange(a)))
    walk, own = np.full((len(row), a), -1), lead
    open_ = np.ones(len(row), bool)
    for step in range(a):
        walk[open_, step] = own[open_]
        own = to[row, own]
        open_ &= own != lead
    known = walk >= 0
    members = src[np.broadcast_to(row[:, None], walk.shape)[known], walk[known]]
    return row, known.sum(1), members


def _cycles(src: pa.Array, dst: pa.Array) -> pa.Array:
    """perm.cycles on Arrow batches, for permutations as matchings give them: src in order, dst of the same sensors."""
    size = src.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    begin, a, b = np.cumsum(size) - size, *(v.flatten().to_numpy(zero_copy_only=False) for v in (src, dst))
    rows, lengths, members = [], [], []
    for n in np.unique(size[size > 1]):
        mine = np.flatnonzero(size == n)
        places = begin[mine][:, None] + np.arange(n)
        row, length, member = cycles_many(a[places], b[places])
        rows.append(mine[row])
        lengths.append(length)
        members += np.split(member, np.cumsum(length)[:-1]) if len(length) else []
    row, length = (np.concatenate(v) if v else np.zeros(0, np.int64) for v in (rows, lengths))
    order = np.argsort(row, kind="stable")
    flat = np.concatenate([members[i] for i in order]) if len(order) else np.zeros(0)
    inner = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(length[order])]).astype(np.int32)), pa.array(flat.astype(np.int32)))
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(np.bincount(row, minlength=len(size)))]).astype(np.int32)), inner)


def cycles(src: Column, dst: Column) -> Column:
    """perm.cycles of matchings."""
    return F.arrow_udf(_cycles, "array<array<int>>").asNondeterministic()(src, dst)


EASY = 4  # so many readings auto matches by enumeration, in expressions


def matched(w: Column, how: str = "auto") -> Column:
    """Matching of W by name. auto is exact at every size; its cost is cubic in at most the number of sensors.

    Matchings of few readings are enumerated in expressions; larger ones (and with enum those beyond ENUM_LIMIT) go to
    the exact matcher on Arrow batches, which sees only these.
    """
    limit = {"enum": ENUM_LIMIT, "auto": EASY}.get(how, -1)
    # declared nondeterministic only so that the plan never folds the call into later expressions and repeats it
    udf = F.arrow_udf(_batched("assign" if how in ("auto", "enum") else how), "array<int>").asNondeterministic()
    if limit < 0:
        return F.when(F.size(w) >= 0, udf(w))  # named twice, w stays a column of its own, as the call's arguments must be
    none = F.expr("cast(array() as array<array<double>>)")
    large = udf(F.when(F.size(w) > limit, w).otherwise(none))
    return F.when(F.size(w) > limit, large).when(F.size(w) > 0, enumerated(w, limit)).otherwise(F.expr("cast(array() as array<int>)"))
