"""Order over whole tables without a window over all rows.

Rows are dealt to ranges of their full order (so that many rows with one time are split by the columns behind it),
sorted inside, numbered and stored; what lies in the ranges before comes from a table with a row for each range.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from unscramble.scratch import few, stored

_INSIDE = (1 << 33) - 1  # the part of monotonically_increasing_id that counts rows inside a partition


def in_ranges(df: DataFrame, keys: list[Column]) -> DataFrame:
    """df with _part (number of the range) and _at (place inside, from 0), in the order of keys. Ties are in any order."""
    many = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    laid = df.repartitionByRange(many, *keys).sortWithinPartitions(*keys).withColumn("_id", F.monotonically_increasing_id())
    return stored(laid, "ordered").select(*df.columns, F.shiftright("_id", 33).alias("_part"), F.col("_id").bitwiseAND(F.lit(_INSIDE)).alias("_at"))


def _before() -> Window:
    return Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # over ranges, of which there are few


def with_ordinal(df: DataFrame, order: Iterable[str], name: str = "n", by: str | None = None, start: int = 1) -> DataFrame:
    """Adds the position of each row in the order of some columns, in each group of by. Nulls come first."""
    order = list(order)
    laid = in_ranges(df, [F.col(c).asc_nulls_first() for c in ([by] if by else []) + order])
    ahead = laid.groupBy("_part").agg(F.count("*").alias("_size")).withColumn("_ahead", F.coalesce(F.sum("_size").over(_before()), F.lit(0)))
    placed = laid.join(F.broadcast(ahead.drop("_size")), "_part").withColumn("_n", F.col("_at") + F.col("_ahead"))
    if by:
        first = few(placed.groupBy(F.col(by).alias("_by")).agg(F.min("_n").alias("_first")), "firsts")
        placed = placed.join(first, F.col(by).eqNullSafe(F.col("_by")))
    else:
        placed = placed.withColumn("_first", F.lit(0))
    return placed.select(*df.columns, (F.col("_n") - F.col("_first") + start).cast("long").alias(name))


def carried(laid: DataFrame, values: dict[str, Column], by: list[str], ahead: bool = False) -> DataFrame:
    """laid (of in_ranges) with each of values as the last one known so far, or with ahead the next one known.

    Values of the ranges before come from a row for each range and group.
    """
    step = F.col("_at") if not ahead else -F.col("_at")
    part = F.col("_part") if not ahead else -F.col("_part")
    inside = Window.partitionBy("_part", *by).orderBy(step).rowsBetween(Window.unboundedPreceding, 0)
    before = Window.partitionBy(*by).orderBy(part).rowsBetween(Window.unboundedPreceding, -1)
    rows = laid.withColumns({f"_in_{c}": F.last(v, ignorenulls=True).over(inside) for c, v in values.items()})
    ends = laid.groupBy("_part", *by).agg(*[F.max_by(v, F.when(v.isNotNull(), step)).alias(f"_end_{c}") for c, v in values.items()])
    ends = ends.select("_part", *by, *[F.last(f"_end_{c}", ignorenulls=True).over(before).alias(f"_end_{c}") for c in values])
    same = rows["_part"] == ends["_part"]
    for c in by:
        same = same & rows[c].eqNullSafe(ends[c])
    out = rows.join(ends, same, "left")
    return out.select(*[rows[c] for c in laid.columns if c not in values], *[F.coalesce(f"_in_{c}", f"_end_{c}").alias(c) for c in values])
