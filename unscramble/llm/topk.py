"""Exact top-k by inner product as a Voronoi kNN join.

Components become floor(scale x). Pivots are taken from a bounded sample, every vector joins the cell of its nearest
pivot, and each cell is summed up by its size, its largest distance to the pivot and its K best-placed rows. Query
cells are gathered in groups of bounded size. With |x - p| the distance to the cell's pivot, a query q scores at most
q.p + |q| |x - p| with x, and a group's members at most max over its queries of that. A cell's summary also gives
scores that its K first rows are sure to reach, hence for each group a bound that no result can be below. Only rows
that may reach the bound are copied to a group; groups and the rows sent to them are cut in lanes, solved with blocked
products, and the K best of all lanes are kept. All bounds are rounded outward, products are exact in whole numbers.

Vectors that are null, empty, or hold null, NaN or infinite components take no part. Shorter vectors count as followed
by zeros up to the greatest length. Ties go to the smaller vec_id. Fewer than K candidates give fewer rows. Rows that
share a vec_id are candidates of their own, but not for each other; as queries their results are one list.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from unscramble.llm.common import materialize, partitions, ship_package, table

K, SCALE = 5, 256
PIVOTS, SAMPLE = 64, 2048
GROUP = 2048  # queries solved together at most
LANE = 20_000  # rows copied to a group that one task solves, about

_INT = pa.int64()


def usable(rows: DataFrame) -> DataFrame:
    """vec_id and v (array of long) of the vectors that take part."""
    v = F.col("embedding").cast("array<double>")
    finite = F.col("embedding").isNotNull() & (F.size("embedding") > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return rows.filter(F.col("vec_id").isNotNull() & finite).select(F.col("vec_id").cast("long").alias("vec_id"), F.transform(v, lambda x: F.floor(x * SCALE)).alias("v"))


def _matrix(column: pa.Array) -> np.ndarray:
    flat = np.asarray(column.flatten())
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 1)


def scores(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact inner products: in doubles where these are exact, else in 64-bit or unbounded integers."""
    most = float(np.abs(q).max(initial=0)) * float(np.abs(x).max(initial=0)) * q.shape[1]
    if most < 2.0**53:
        return (q.astype(np.float64) @ x.T.astype(np.float64)).astype(np.int64)
    if most < 2.0**63:
        return q @ x.T
    exact = q.astype(object) @ x.T.astype(object)
    return np.clip(exact, -(2**63), 2**63 - 1).astype(np.int64)


def best(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, k: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each query its k best (vec_id, score) among these rows, without itself."""
    order = np.argsort(ids, kind="stable")
    ids, x = ids[order], x[order]
    s = scores(q, x)
    s[q_ids[:, None] == ids[None, :]] = np.iinfo(np.int64).min
    for row, qid in zip(s, q_ids, strict=True):
        if len(row) > 4 * k:
            least = np.partition(row, len(row) - k)[len(row) - k]
            at = np.flatnonzero(row >= least)
        else:
            at = np.arange(len(row))
        at = at[np.argsort(-row[at].astype(np.float64) if abs(row[at]).max(initial=0) < 2**53 else -row[at].astype(object), kind="stable")]
        at = at[ids[at] != qid][:k]
        yield qid, ids[at], row[at]


def top_k(rows: DataFrame, is_query, k: int = K) -> DataFrame:
    """query_id, rank, vec_id, score. rows: vec_id, embedding; is_query: a condition on vec_id."""
    spark = rows.sparkSession
    ship_package(spark)
    out = "query_id long, vec_id long, score long"
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    data = usable(rows)
    sample = data.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE).collect()
    if not sample:
        return empty
    width = data.agg(F.max(F.size("v"))).first()[0]
    data = data.withColumn("v", F.concat("v", F.array_repeat(F.lit(0).cast("long"), F.lit(width) - F.size("v"))))
    seen = np.array([r["v"] + [0] * (width - len(r["v"])) for r in sample], np.float64)
    pivots = np.unique(seen, axis=0)
    if len(pivots) > PIVOTS:  # spread out: each next pivot is the one farthest from those before
        chosen, far = [0], np.full(len(pivots), np.inf)
        while len(chosen) < PIVOTS:
            far = np.minimum(far, ((pivots - pivots[chosen[-1]]) ** 2).sum(1))
            chosen.append(int(far.argmax()))
        pivots = pivots[chosen]
    norms = (pivots**2).sum(1)

    def assign(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _matrix(b.column("v")).astype(np.float64)
            d = np.maximum((x**2).sum(1)[:, None] + norms - 2 * x @ pivots.T, 0)
            cell = d.argmin(1)
            dist = np.sqrt(((x - pivots[cell]) ** 2).sum(1))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(cell, pa.int32()), pa.array(dist)], ["vec_id", "v", "cell", "dist"])

    cells = materialize(data.mapInArrow(assign, "vec_id long, v array<long>, cell int, dist double"), "cells")
    queries = cells.filter(is_query)

    # summaries: for each cell the distances of its k + 1 rows next to the pivot, for each query cell its size
    near = Window.partitionBy("cell", "part").orderBy("dist")
    parted = cells.select("cell", "dist", F.pmod(F.xxhash64("vec_id"), F.lit(partitions(spark))).alias("part"))
    few = parted.withColumn("r", F.row_number().over(near)).filter(F.col("r") <= k + 1).groupBy("cell").agg(F.collect_list("dist").alias("d")).collect()
    close = {r["cell"]: sorted(r["d"])[: k + 1] for r in few}
    sizes = {r["cell"]: r["count"] for r in queries.groupBy("cell").count().collect()}
    if not sizes:
        return empty

    # query groups: neighbouring query cells together, large cells cut by hash
    order = sorted(sizes, key=lambda c: (-sizes[c], c))
    group_of: dict[int, list[int]] = {}
    left: list[list] = []  # [group, room, cell]
    n_groups = 0
    for c in order:
        cuts = -(-sizes[c] // GROUP)
        if cuts == 1:
            fit = [g for g in left if g[1] >= sizes[c]]
            if fit:
                g = min(fit, key=lambda g: float(((pivots[g[2]] - pivots[c]) ** 2).sum()))
                g[1] -= sizes[c]
                group_of[c] = [g[0]]
                continue
            left.append([n_groups, GROUP - sizes[c], c])
        group_of[c] = list(range(n_groups, n_groups + cuts))
        n_groups += cuts

    def grouped(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = np.asarray(b.column("vec_id"))
            g = [group_of[c][int(i) // 1 % len(group_of[c])] for c, i in zip(b.column("cell").to_pylist(), ids, strict=True)]
            x = _matrix(b.column("v")).astype(np.float64)
            # least score that k candidates reach for this query, from the summaries alone
            size = np.sqrt((x**2).sum(1))
            dots = x @ pivots.T
            sure = np.concatenate([dots[:, [c]] - size[:, None] * np.array(d)[None, :] for c, d in close.items()], 1)
            m = sure.shape[1]
            floor = np.partition(sure, m - k - 1, 1)[:, m - k - 1] if m > k else np.full(len(x), -np.inf)
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), b.column("v"), pa.array(g, pa.int32()), pa.array(np.floor(floor - 1e-6 * (1 + np.abs(floor))))], ["vec_id", "v", "grp", "least"])

    q = materialize(queries.mapInArrow(grouped, "vec_id long, v array<long>, grp int, least double"), "queries")

    # for each (group, cell): how far from the pivot a row must be to matter; a query q needs q.p + |q| dist >= least
    def reach(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        need: dict[int, np.ndarray] = {}
        for b in batches:
            x = _matrix(b.column("v")).astype(np.float64)
            size = np.sqrt((x**2).sum(1))
            short = np.asarray(b.column("least"))[:, None] - x @ pivots.T
            with np.errstate(divide="ignore", invalid="ignore"):
                d = np.where(short <= 0, 0.0, np.where(size[:, None] > 0, short / size[:, None], np.inf))
            for g in set(b.column("grp").to_pylist()):
                mine = d[np.asarray(b.column("grp")) == g].min(0)
                need[g] = np.minimum(need[g], mine) if g in need else mine
        for g, d in need.items():
            yield pa.RecordBatch.from_arrays([pa.array([g] * len(d), pa.int32()), pa.array(range(len(d)), pa.int32()), pa.array(d * (1 - 1e-9) - 1e-6)], ["grp", "cell", "need"])

    needs = q.mapInArrow(reach, "grp int, cell int, need double").groupBy("grp", "cell").agg(F.min("need").alias("need")).filter(F.col("need") < float("inf"))
    needs = materialize(needs, "needs")
    table_of = F.broadcast(needs) if n_groups * len(pivots) <= 200_000 else needs
    sent = cells.join(table_of, "cell").filter("dist >= need")
    lanes = materialize(sent.groupBy("grp").agg(F.ceil(F.count("*") / LANE).cast("int").alias("lanes")), "lanes")
    lanes_of = F.broadcast(lanes) if n_groups <= 200_000 else lanes
    sent = sent.join(lanes_of, "grp").select("grp", F.pmod(F.xxhash64("vec_id"), "lanes").cast("int").alias("lane"), F.lit(False).alias("asks"), "vec_id", "v")
    asked = q.join(lanes_of, "grp").select("grp", F.explode(F.sequence(F.lit(0), F.col("lanes") - 1)).alias("lane"), F.lit(True).alias("asks"), "vec_id", "v")

    def solve(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come by (group, lane), queries first; a block of rows at a time is held."""
        key, held, block = None, None, []

        def answers() -> Iterator[pa.RecordBatch]:
            if held is not None and block:
                ids, x = np.concatenate([b[0] for b in block]), np.concatenate([b[1] for b in block])
                got = [(np.full(len(i), qid), i, s) for qid, i, s in best(*held, ids, x, k)]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([g[j] for g in got]), _INT) for j in range(3)], ["query_id", "vec_id", "score"])
            block.clear()

        for b in batches:
            keys = np.stack([np.asarray(b.column("grp")), np.asarray(b.column("lane"))], 1)
            edges = np.flatnonzero(np.any(np.diff(keys, axis=0) != 0, axis=1)) + 1
            ids, x, asks = np.asarray(b.column("vec_id")), _matrix(b.column("v")), np.asarray(b.column("asks").to_pylist(), bool)
            for lo, hi in zip([0, *edges], [*edges, len(ids)], strict=True):
                if lo == hi:
                    continue
                if tuple(keys[lo]) != key:
                    yield from answers()
                    key, held = tuple(keys[lo]), None
                a = asks[lo:hi]
                if a.any():
                    new = ids[lo:hi][a], x[lo:hi][a]
                    held = new if held is None else (np.concatenate([held[0], new[0]]), np.concatenate([held[1], new[1]]))
                if not a.all():
                    block.append((ids[lo:hi][~a], x[lo:hi][~a]))
                if sum(len(i) for i, _ in block) >= 4096:
                    yield from answers()
        yield from answers()

    laid = asked.union(sent).repartition(partitions(spark), "grp", "lane").sortWithinPartitions("grp", "lane", F.desc("asks"))
    found = laid.mapInArrow(solve, out)
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op2_voronoi_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


OP2_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(CAST(x AS DOUBLE)))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.v, c.v) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0
), r AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS "rank", vec_id, score FROM s
)
SELECT query_id, "rank", vec_id, score FROM r WHERE "rank" <= 5
"""
