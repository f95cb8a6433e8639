"""Tables between the steps of iterative plans."""

from __future__ import annotations

import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_shipped: set[str] = set()


def ship_package(spark: SparkSession) -> None:
    """Send this package to the executors, once for each application, so that their Python can import it."""
    if spark.sparkContext.applicationId not in _shipped:
        top = Path(__file__).resolve().parents[1]
        with zipfile.ZipFile(name := f"{tempfile.mkdtemp()}/unscramble.zip", "w") as z:
            for p in sorted((top / "unscramble").rglob("*.py")):
                z.write(p, p.relative_to(top))
        spark.sparkContext.addPyFile(name)
        _shipped.add(spark.sparkContext.applicationId)


_local: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a folder of this machine only in local mode without that setting."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _local:
        _local[app] = f"file://{tempfile.mkdtemp(prefix='unscramble-')}"
    return _local[app]


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/unscramble/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Written as Parquet and read back, so that lost executors cost a read and not the plan behind it."""
    ship_package(df.sparkSession)
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def appended(df: DataFrame, path: str) -> DataFrame:
    """df added to the Parquet table at path, and all of that table as it is then."""
    ship_package(df.sparkSession)
    df.write.mode("append").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: A table of models and the like is broadcast up to so many rows; beyond, it is joined by shuffle.
FEW_ROWS = 200_000


def few(df: DataFrame, name: str) -> DataFrame:
    """df, stored and counted, and marked for broadcast if it has FEW_ROWS rows at most."""
    kept = stored(df, name)
    return F.broadcast(kept) if kept.limit(FEW_ROWS + 1).count() <= FEW_ROWS else kept
