"""Permutations of sensors as Column expressions.

A permutation over a set of sensors is a pair of arrays of equal length: ``src`` and ``dst``; the reading recorded in
src[i] belongs to dst[i]. A cycle is an array of sensors, the smallest first, each one's reading belonging to the next.
Sets of cycles are arrays sorted by first element, so they can be grouped and compared.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

CYCLES = "array<array<int>>"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body of a value that is computed once for each row, however often (and however deep in lambdas) body names it."""
    return F.transform(F.array(value), body)[0]


def follow(src: Column, dst: Column, sensor: Column) -> Column:
    """Where the reading recorded in sensor belongs; itself if it isn't in src."""
    at = F.array_position(src, sensor)
    return F.when(at > 0, F.try_element_at(dst, at.cast("int"))).otherwise(sensor)


def cycles(src: Column, dst: Column) -> Column:
    """The disjoint cycles of order two or more. Every orbit is walked from each member; the walk from its least one stays."""

    def of(pair: Column) -> Column:
        a, b = pair["a"], pair["b"]

        def step(walk: Column, _: Column) -> Column:
            nxt = follow(a, b, F.element_at(walk, -1))
            return F.when(nxt == walk[0], walk).otherwise(F.array_append(walk, nxt))

        walks = F.transform(a, lambda u: F.aggregate(a, F.array(u), step))
        return F.array_sort(F.filter(walks, lambda c: (F.size(c) > 1) & (c[0] == F.array_min(c))))

    return let(F.struct(src.alias("a"), dst.alias("b")), of)


def rotate_least_first(cycle: Column) -> Column:
    at = F.array_position(cycle, F.array_min(cycle)).cast("int")
    return F.concat(F.slice(cycle, at, F.size(cycle)), F.slice(cycle, 1, at - 1))


def canonical(cs: Column) -> Column:
    return F.array_sort(F.transform(cs, rotate_least_first))


def sources(cs: Column) -> Column:
    """All members of cycles, in order."""
    return F.flatten(cs)


def targets(cs: Column) -> Column:
    """For each member in the order of sources, the sensor that its reading belongs to."""
    return F.flatten(F.transform(cs, lambda c: F.concat(F.slice(c, 2, F.size(c)), F.slice(c, 1, 1))))


def inverse(cs: Column) -> Column:
    return canonical(F.transform(cs, F.reverse))


def compose(first: Column, then: Column) -> Column:
    """The cycles of following first and then the other; both are sets of cycles."""

    def of(p: Column) -> Column:
        move = lambda u: follow(p["c"], p["d"], follow(p["a"], p["b"], u))
        return let(F.struct(p["m"].alias("m"), F.transform(p["m"], move).alias("to")), lambda q: cycles(q["m"], q["to"]))

    members = F.array_distinct(F.concat(F.flatten(first), F.flatten(then)))
    pairs = F.struct(members.alias("m"), sources(first).alias("a"), targets(first).alias("b"), sources(then).alias("c"), targets(then).alias("d"))
    return let(pairs, of)


def disjoint(a: Column, b: Column) -> Column:
    return ~F.arrays_overlap(F.flatten(a), F.flatten(b))


def gather(x: Column, take: Column) -> Column:
    """x read at the places that take lists, one for each sensor."""
    return let(x, lambda v: F.transform(take, lambda i: v[i]))


def undo_places(cs: Column, width: Column) -> Column:
    """For each sensor the column where its reading was recorded: y[v] = x[u] when u's reading belongs to v."""
    pair = F.struct(sources(cs).alias("a"), targets(cs).alias("b"))
    return let(pair, lambda p: F.transform(F.sequence(F.lit(0), width - 1), lambda v: follow(p["b"], p["a"], v)))


def corrupt_places(cs: Column, width: Column) -> Column:
    """For each sensor whose value it gets when cycles are injected: member i gets the value of member i + 1."""
    pair = F.struct(sources(cs).alias("a"), targets(cs).alias("b"))
    return let(pair, lambda p: F.transform(F.sequence(F.lit(0), width - 1), lambda u: follow(p["a"], p["b"], u)))


def apply_cycles(x: Column, cs: Column) -> Column:
    """Undo the misplacement that cs describes."""
    return gather(x, undo_places(cs, F.size(x)))


def cycle_key(cycle: Column) -> Column:
    return F.array_join(F.transform(cycle, lambda s: s.cast("string")), ">")


def cycles_key(cs: Column) -> Column:
    return F.array_join(F.transform(cs, cycle_key), "|")


def parse_cycle(key: Column) -> Column:
    return F.transform(F.split(key, ">"), lambda s: s.cast("int"))


def parse_cycles(key: Column) -> Column:
    """Inverse of cycles_key; the empty text has no cycles."""
    return F.when(key == "", F.expr(f"cast(array() as {CYCLES})")).otherwise(F.transform(F.split(key, "\\|"), parse_cycle))


def parse_notation(text: Column, base: int = 1) -> Column:
    """Cycles from "(1 2)(3,5)", counted from base."""
    groups = F.regexp_extract_all(text, F.lit(r"\(([^)]*)\)"), F.lit(1))
    one = lambda g: F.transform(F.split(F.trim(g), r"[ ,]+"), lambda s: s.cast("int") - base)
    return canonical(F.transform(groups, one))
