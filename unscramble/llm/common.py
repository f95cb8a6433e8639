"""Helpers that the training-data operators share."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.scratch import scratch_path, ship_package

__all__ = ["drop_scratch", "materialize", "may_hold", "partitions", "scratch_path", "ship_package", "table", "whole_text"]

#: At most so many bits are shipped to executors as a bit map: 64 MB.
FILTER_BITS = 1 << 29
_ROW_BITS = 1 << 15  # of a row of the bit map, as Spark's bitmap functions have them


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship_package(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write to the shared folder as Parquet and read back."""
    spark, path = df.sparkSession, scratch_path(df.sparkSession, name)
    ship_package(spark)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def drop_scratch(*tables: DataFrame) -> None:
    """Delete tables that materialize wrote and nothing reads any more, through Spark's own file systems."""
    for df in tables:
        if path := vars(df).get("_scratch"):
            spark = df.sparkSession
            p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def may_hold(keys: DataFrame, key: str, rows: DataFrame, row_key: Column, most: int = FILTER_BITS) -> DataFrame:
    """rows with a column _may: true wherever row_key is among keys, and seldom elsewhere. rows are not shuffled.

    A bit map with 32 bits or more for each key is broadcast, of most bits at the most; with more keys than fit more
    rows have true, down to all of them, so what uses it stays right at any size.
    """
    n = keys.count()
    bits = min(most, max(_ROW_BITS, 1 << (32 * n).bit_length()))
    at = keys.select(F.pmod(F.col(key), F.lit(bits)).alias("p"))
    maps = at.groupBy(F.expr(f"p div {_ROW_BITS}").alias("_row")).agg(F.bitmap_construct_agg(F.col("p") % _ROW_BITS).alias("_bits"))
    asked = rows.withColumn("_p", F.pmod(row_key, F.lit(bits))).withColumn("_row", F.expr(f"_p div {_ROW_BITS}"))
    byte = F.conv(F.hex(F.expr(f"substring(_bits, cast((_p % {_ROW_BITS}) div 8 as int) + 1, 1)")), 16, 10).cast("int")
    bit = F.expr("cast(shiftleft(1, cast(_p % 8 as int)) as int)")
    found = asked.join(F.broadcast(maps), "_row", "left").withColumn("_may", F.coalesce(byte.bitwiseAND(bit) > 0, F.lit(False)))
    return found.select(*rows.columns, "_may")


def partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def whole_text(col: str = "text"):
    return F.coalesce(F.col(col).cast("string"), F.lit(""))
