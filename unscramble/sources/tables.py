"""Readers and sinks."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from unscramble.scratch import ship_package


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: Iterable[str] | None = None, where: Column | str | None = None) -> DataFrame:
    """A Parquet table; columns and filters reach the scan. Timestamps without zone are taken as session time."""
    ship_package(spark)
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where is not None:
        df = df.filter(where)
    if columns is not None:
        df = df.select(*columns)
    for field in df.schema:
        if field.dataType.typeName() == "timestamp_ntz":
            df = df.withColumn(field.name, F.col(field.name).cast("timestamp"))
    return df


def read_any(spark: SparkSession, fmt: str, path: str, schema: StructType | str, **options: str) -> DataFrame:
    """CSV, JSON, ORC, text or Parquet with the schema stated, so that nothing is scanned to infer it."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def stream_source(spark: SparkSession, path: str, schema: StructType | str, max_files: int = 1, fmt: str = "parquet") -> DataFrame:
    """Files of a folder as a stream, so many in a batch."""
    return spark.readStream.format(fmt).schema(schema).option("maxFilesPerTrigger", max_files).load(path)


def write_result(df: DataFrame, path: str, by: Iterable[str] = ("eq_id",), mode: str = "overwrite") -> None:
    """Parquet, partitioned; one task writes one partition value's rows, hot values are split by AQE."""
    by = list(by)
    (df.hint("rebalance", *[F.col(c) for c in by]) if by else df).write.mode(mode).partitionBy(*by).parquet(path)


def write_escalations(candidates: DataFrame, path: str) -> None:
    """Points that a person must look at, appended to what is there."""
    candidates.filter("status = 'escalated'").write.mode("append").parquet(path)
