"""Exact quantiles of many groups without a group's values in one task.

The places wanted in the order of a group are narrowed down: readings of the span that holds a place are counted in
BINS equal bins, and the bin with the place is the next span, until a span has few readings or a single value.
Only counts of bins, and at last the different values of short spans, are shuffled.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from unscramble.scratch import few, stored

BINS = 1024
SHORT = 1 << 15  # a span of so many readings is sorted
MOST = 1.7976931348623157e308
KEYS = ("eq_id", "m")
SPAN = (*KEYS, "a", "b")


def _inside(rows: DataFrame, spans: DataFrame) -> DataFrame:
    """Readings with each span (a, b) of their group that holds them."""
    return rows.join(few(spans.select(*SPAN).distinct(), "spans"), list(KEYS)).filter(F.col("x").between(F.col("a"), F.col("b")))


def _counted(groups: DataFrame, order: str) -> DataFrame:
    """groups with the number of readings of the span that lie before them."""
    w = Window.partitionBy(*SPAN).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    return groups.withColumn("ahead", F.coalesce(F.sum("c").over(w), F.lit(0)))


def quantiles(rows: DataFrame, ends: DataFrame, wanted: dict[str, float], bins: int = BINS, short: int = SHORT) -> DataFrame:
    """For each group (eq_id, m) of rows (eq_id, m, x; no NULL, no NaN) the quantiles by name, between two values by line.

    ends: eq_id, m, cnt, and lo and hi that no reading is beyond. rows are read once for each narrowing and once more:
    give a table that is cheap to read.
    """
    at = {name: F.lit(p) * (F.col("cnt") - 1) for name, p in wanted.items()}
    places = F.array_distinct(F.flatten(F.array(*[F.array(F.floor(v), F.ceil(v)) for v in at.values()])))
    todo = stored(ends.select(*KEYS, F.col("lo").alias("a"), F.col("hi").alias("b"), F.explode(places).alias("place"), F.lit(0).cast("long").alias("skip"), F.col("cnt").alias("size")), "places")
    wide = (F.col("size") > short) & (F.col("a") < F.col("b"))
    ready = todo.filter(~wide)
    todo = todo.filter(wide)
    # halves, and the largest numbers in the place of infinite ones, keep the width of every span finite
    finite = lambda c: F.greatest(F.least(F.col(c), F.lit(MOST)), F.lit(-MOST)) / 2
    spread = finite("b") - finite("a")
    cell = F.least(F.floor((finite("x") - finite("a")) / F.when(spread > 0, spread).otherwise(1.0) * bins), F.lit(bins - 1))
    while not todo.isEmpty():
        cells = _inside(rows, todo).groupBy(*SPAN, cell.alias("cell")).agg(F.count("*").alias("c"), F.min("x").alias("least"), F.max("x").alias("most"))
        found = todo.join(_counted(cells, "cell"), list(SPAN)).filter((F.col("place") - F.col("skip")).between(F.col("ahead"), F.col("ahead") + F.col("c") - 1))
        next_ = stored(found.select(*KEYS, F.col("least").alias("a"), F.col("most").alias("b"), "place", (F.col("skip") + F.col("ahead")).alias("skip"), F.col("c").alias("size")), "places")
        ready, todo = ready.unionByName(next_.filter(~wide)), next_.filter(wide)
    ready = few(ready, "places")
    open_ = ready.filter("a < b")
    values = _inside(rows, open_).groupBy(*SPAN, "x").agg(F.count("*").alias("c"))
    found = open_.join(_counted(values, "x"), list(SPAN)).filter((F.col("place") - F.col("skip")).between(F.col("ahead"), F.col("ahead") + F.col("c") - 1))
    known = found.select(*KEYS, "place", "x").unionByName(ready.filter("a >= b").select(*KEYS, "place", F.col("a").alias("x")))
    by_place = known.groupBy(*KEYS).agg(F.map_from_entries(F.collect_list(F.struct("place", "x"))).alias("_at"))

    def value(v):
        low, high = F.col("_at")[F.floor(v)], F.col("_at")[F.ceil(v)]
        return F.when(low == high, low).otherwise((F.ceil(v) - v) * low + (v - F.floor(v)) * high)

    return few(ends.select(*KEYS, "cnt").join(by_place, list(KEYS)).select(*KEYS, *[value(v).alias(name) for name, v in at.items()]), "quantiles")
