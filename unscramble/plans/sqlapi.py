"""The engine in SQL: views, functions, an aggregate and a table function."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.operators.matching import assign, greedy_numpy
from unscramble.operators.runs import fold_runs, runs_union_find
from unscramble.scratch import ship_package


def _matrix(rows) -> np.ndarray:
    return np.stack([np.asarray(r, float) for r in rows])


def _cycle_text(sensors, to) -> str:
    nxt, out = {int(s): int(sensors[j]) for s, j in zip(sensors, to, strict=True)}, []
    for s in sorted(nxt):
        walk = [s]
        while nxt[walk[-1]] != s:
            walk.append(nxt[walk[-1]])
        if len(walk) > 1 and min(walk) == s:
            out.append(">".join(map(str, walk)))
    return "|".join(out)


class BitRuns:
    """Rows (bit, l, r) of the runs of an array of bits."""

    def eval(self, bits: list[int]) -> Iterator[tuple[int, int, int]]:
        yield from runs_union_find([int(b) for b in bits or []])


def register_functions(spark: SparkSession) -> None:
    """match_exact(W), match_greedy(W), cycle_text(sensors, to), smooth_bits(n, bit), bit_runs(bits), chebyshev_support(x, mu, sigma)."""
    ship_package(spark)

    def exact(w: pd.Series) -> pd.Series:
        return pd.Series([assign(_matrix(x)).tolist() if x is not None and len(x) else [] for x in w])

    def greedy(w: pd.Series) -> pd.Series:
        return pd.Series([greedy_numpy(_matrix(x)).tolist() if x is not None and len(x) else [] for x in w])

    def cycle_text(sensors: pd.Series, to: pd.Series) -> pd.Series:
        return pd.Series([_cycle_text(a, b) for a, b in zip(sensors, to, strict=True)])

    def smooth_bits(n: pd.Series, bit: pd.Series) -> str:
        order = np.argsort(n.to_numpy(), kind="stable")
        runs = [(lo, hi, False) for b, lo, hi in runs_union_find(bit.to_numpy()[order].astype(int).tolist()) if b]
        return ",".join(f"{lo}-{hi}" for lo, hi in fold_runs(runs, len(n), 0.3, 20, "guarded"))

    spark.udf.register("match_exact", F.pandas_udf(exact, "array<int>"))
    spark.udf.register("match_greedy", F.pandas_udf(greedy, "array<int>"))
    spark.udf.register("cycle_text", F.pandas_udf(cycle_text, "string"))
    smooth_bits.__annotations__ = {"n": pd.Series, "bit": pd.Series, "return": str}
    spark.udf.register("smooth_bits", F.pandas_udf(smooth_bits, "string"))
    spark.udtf.register("bit_runs", F.udtf(BitRuns, returnType="bit int, l long, r long"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION chebyshev_support(x DOUBLE, mu DOUBLE, sigma DOUBLE) RETURNS DOUBLE RETURN CASE WHEN abs(x - mu) <= sigma THEN 1.0D ELSE (sigma / (x - mu)) * (sigma / (x - mu)) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION run_tau(mid DOUBLE, before DOUBLE, after DOUBLE) RETURNS DOUBLE RETURN mid / (before + after)")


def create_views(panel: DataFrame, models: DataFrame, candidates: DataFrame | None = None, schemas: DataFrame | None = None) -> None:
    for name, df in (("panel", panel), ("models", models), ("candidates", candidates), ("schemas", schemas)):
        if df is not None:
            df.createOrReplaceTempView(name)
