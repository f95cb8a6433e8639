"""Panels: one row for each time point of an equipment, all sensors in one array.

Schema: eq_id long, n long (from 1), ts timestamp, regime string, x array<double>.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.operators.ordinal import with_ordinal
from unscramble.scratch import few
from unscramble.sources.tables import read_table

PANEL = "eq_id long, n long, ts timestamp, regime string, x array<double>"
ROW_ORDER = ("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
HISTORY_ORDER = ("l_partkey", "l_suppkey", "l_orderkey", "l_linenumber", "l_shipdate")
#: Centre and spread of the four measures that are standardised.
MEASURES = {"l_quantity": (25.5, 14.43), "l_extendedprice": (53000.0, 30100.0), "l_discount": (0.05, 0.02905), "l_tax": (0.04, 0.02348)}
CLICKS = ("click", "error", "purchase", "signup", "view")


def to_panel(long: DataFrame, keys: tuple[str, ...] = ("eq_id", "n")) -> DataFrame:
    """Long rows (keys, m, x) to one row for each key with an array in the order of m."""
    return long.groupBy(*keys).agg(F.transform(F.array_sort(F.collect_list(F.struct("m", "x"))), lambda s: s["x"]).alias("x"))


def to_long(panel: DataFrame) -> DataFrame:
    """One row for each reading. What a panel has beside its own columns stays on all rows of a point."""
    more = [c for c in panel.columns if c not in ("eq_id", "n", "ts", "regime", "x")]
    return panel.select("eq_id", "n", "ts", "regime", *more, F.posexplode("x").alias("m", "x"))


STRETCH = 1 << 16


def stretches(long: DataFrame, before: int, after: int = 0, length: int | None = None) -> DataFrame:
    """Long rows cut in stretches of time (_s) that also hold so many points before and after them (_lead is true there).

    A window over (eq_id, m, _s) then sees what one over the whole series sees, and no task holds a series. Ordinals of
    a series are dense, as those of a panel are.
    """
    length = length or STRETCH
    own = F.floor(F.col("n") / length)
    held = F.sequence(F.floor((F.col("n") - after) / length), F.floor((F.col("n") + before) / length))
    return long.withColumn("_s", F.explode(held)).withColumn("_lead", F.col("_s") != own)


def ranked_items(spark: SparkSession, sf_dir: str, history: bool = False, equipments: int = 1) -> DataFrame:
    """lineitem with each row's place r in the order of a panel, or of a history. It is the same for any number of sensors."""
    cols = list(dict.fromkeys([*ROW_ORDER, *MEASURES]))
    items = read_table(spark, sf_dir, "lineitem", cols)
    items = items.withColumn("eq_id", (F.col("l_suppkey") % equipments).cast("long"))
    return with_ordinal(items, HISTORY_ORDER if history else ROW_ORDER, "r", "eq_id" if equipments > 1 else None, 0)


def calibrated_panel(spark: SparkSession, sf_dir: str, g: float = 2.0, sensors: int = 48, history: bool = False, equipments: int = 1, drift: float = 0.0, keep: int | None = None, ranked: DataFrame | None = None) -> DataFrame:
    """lineitem as readings of many sensors, whose means are g standard deviations apart and swing slowly.

    history: the same rows in another order at ordinals up to 0, to learn models from. keep: so many sensors only.
    ranked: what ranked_items gives for the same equipments and order, if it is there already.
    """
    rows = -(-sensors // 4)
    ranked = ranked_items(spark, sf_dir, history, equipments) if ranked is None else ranked
    # ordinals are dense: how many whole tuples there are is known before they are put together
    ends = few(ranked.groupBy("eq_id").agg(F.floor((F.max("r") + 1) / rows).alias("last")), "ends")
    width = keep or sensors
    z = F.array(*[(F.col(c) - mid) / spread for c, (mid, spread) in MEASURES.items()])
    tuples = (
        ranked.select("eq_id", F.floor(F.col("r") / rows).cast("long").alias("t"), (F.col("r") % rows).cast("int").alias("k"), z.alias("z"))
        .filter(F.col("k") < -(-width // 4))
        .join(ends, "eq_id")
        .filter("t < last")
        .groupBy("eq_id", F.col("t") + 1 - (F.col("last") if history else 0))
        .agg(F.array_sort(F.collect_list(F.struct("k", "z"))).alias("all"))
        .toDF("eq_id", "n", "all")
        .select("eq_id", "n", F.slice(F.flatten(F.transform("all", lambda s: s["z"])), 1, width).alias("z"))
    )
    step = 8.0 if sensors > 48 else 8.64
    x = F.transform("z", lambda v, m: v + g * m + 1.5 * F.sin(2 * F.pi() * F.col("n") / (200 + 17 * m)) + drift * F.col("n") * m / sensors)
    ts = F.timestamp_micros((F.unix_micros(F.lit("2024-01-01").cast("timestamp")) + F.col("n") * int(step * 1e6)).cast("long"))
    return tuples.select("eq_id", "n", ts.alias("ts"), F.lit(None).cast("string").alias("regime"), x.alias("x"))


def native_panel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One tuple for each lineitem with measures of the tables around it, uncalibrated; regime is the return flag."""
    items = read_table(spark, sf_dir, "lineitem", [*ROW_ORDER, "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag"])
    orders = read_table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_totalprice"])
    part = read_table(spark, sf_dir, "part", ["p_partkey", "p_retailprice", "p_size"])
    supplier = read_table(spark, sf_dir, "supplier", ["s_suppkey", "s_acctbal"])
    customer = read_table(spark, sf_dir, "customer", ["c_custkey", "c_acctbal"])
    wide = (
        with_ordinal(items, ROW_ORDER)
        .join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
        .join(part, F.col("l_partkey") == F.col("p_partkey"))
        .join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
        .join(customer, F.col("o_custkey") == F.col("c_custkey"))
    )
    x = F.array(*[F.col(c).cast("double") for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "o_totalprice", "p_retailprice", "p_size", "s_acctbal", "c_acctbal")])
    return wide.select(F.lit(0).cast("long").alias("eq_id"), "n", F.col("l_shipdate").alias("ts"), F.col("l_returnflag").alias("regime"), x.alias("x"))


def event_ticks(spark: SparkSession, sf_dir: str, tick: str = "6 hours", g: float = 40.0) -> DataFrame:
    """events as five channels on a common tick; a tick without all channels holds NULL for what is missing."""
    events = read_table(spark, sf_dir, "events", ["ts", "event_type", "value"])
    cells = events.groupBy(F.window("ts", tick)["start"].alias("ts"), "event_type").agg(F.avg("value").alias("v"))
    x = F.array(*[F.max(F.when(F.col("event_type") == c, F.col("v") + g * m)) for m, c in enumerate(CLICKS)])
    wide = cells.groupBy("ts").agg(x.alias("x"))
    return with_ordinal(wide, ["ts"]).select(F.lit(0).cast("long").alias("eq_id"), "n", "ts", F.lit(None).cast("string").alias("regime"), "x")


def event_ordinals(spark: SparkSession, sf_dir: str, g: float = 150.0) -> DataFrame:
    """The i-th event of each type as one tuple."""
    events = read_table(spark, sf_dir, "events", ["event_id", "ts", "event_type", "value"]).withColumn("m", F.array_position(F.lit(list(CLICKS)), F.col("event_type")).cast("int") - 1)
    ranked = with_ordinal(events, ["ts", "event_id"], by="m")
    x = F.transform(F.array_sort(F.collect_list(F.struct("m", "value"))), lambda s: s["value"] + s["m"] * g)
    wide = ranked.groupBy("n").agg(F.max("ts").alias("ts"), x.alias("x")).filter(F.size("x") == len(CLICKS))
    return wide.select(F.lit(0).cast("long").alias("eq_id"), "n", "ts", F.lit(None).cast("string").alias("regime"), "x")


def embedding_panel(spark: SparkSession, sf_dir: str, g: float = 1.0) -> DataFrame:
    """Vectors as 64 sensors, slightly shifted against each other; regime is the label."""
    rows = with_ordinal(read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding", "label"]), ["vec_id"])
    x = F.transform("embedding", lambda v, m: v.cast("double") + 0.125 * g * m)
    ts = F.timestamp_seconds(F.col("n"))
    return rows.select(F.lit(0).cast("long").alias("eq_id"), "n", ts.alias("ts"), F.col("label").cast("string").alias("regime"), x.alias("x"))


def daily_panel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily count and averages of lineitem: ts, x1..x5."""
    items = read_table(spark, sf_dir, "lineitem", ["l_shipdate", *MEASURES])
    return items.groupBy(F.date_trunc("day", "l_shipdate").alias("ts")).agg(F.count("*").cast("double").alias("x1"), *[F.avg(c).alias(f"x{i}") for i, c in enumerate(MEASURES, 2)])


def example_panel(spark: SparkSession, sf_dir: str, g: float = 3.0, history: bool = False) -> DataFrame:
    """The first five sensors of the calibrated panel."""
    return calibrated_panel(spark, sf_dir, g, history=history, keep=5)


def prefix(panel: DataFrame, percent: int) -> DataFrame:
    """The first percent of each equipment's points."""
    last = panel.groupBy("eq_id").agg(F.max("n").alias("last"))
    return panel.join(last, "eq_id").filter(F.col("n") * 100 <= F.col("last") * percent).drop("last")
