"""Best-fit packing of tokenized documents into sequences of a fixed length, in bulk-synchronous supersteps.

Sizes are whole numbers up to the sequence length, so range-sorted documents and range-sorted gaps are run-length
encoded: one class for each size, however large the corpus. A superstep takes the largest class that still waits,
sweeps the gap classes upward from its own size (the successor sweep), lets the lowest ranks take the tightest gaps,
updates the gaps, and goes on with the next class. Every step moves a whole class, and the result is the one of
sequential best-fit decreasing. Only class totals reach the driver (at most one row for each size); rows learn their
place from their rank in their class, which is found with a two-level count, so no class has to fit into one task.

Null text counts as empty; an empty document is its end token alone. Rows with equal ids are packed one by one.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from unscramble.llm import chunks
from unscramble.llm.common import materialize, partitions, ship_package, table, whole_text

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def token_pieces(docs: DataFrame, tokenizer_path: str, limit: int = 4096, end_id: int = 1) -> DataFrame:
    """Each document's ids and an end id, cut at every limit ids. The ids themselves stay where they were made."""
    ship_package(docs.sparkSession)
    end = np.uint32(end_id).astype("<u4").tobytes()

    def cut(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            for doc, ids in zip(batch.column("doc_id").to_pylist(), chunks.id_bytes(batch.column("text"), tokenizer_path), strict=True):
                ids += end
                n = len(ids) // 4
                rows += [(doc, k, at, min(limit, n - at), zlib.crc32(ids[4 * at : 4 * (at + limit)])) for k, at in enumerate(range(0, n, limit))]
            cols = list(zip(*rows, strict=True)) or [[]] * 5
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text")).mapInArrow(cut, PIECES)


def place_classes(counts: dict[int, int], limit: int) -> list[tuple[int, int, int, int, int, int]]:
    """Supersteps over size classes: (size, first rank, ranks, first sequence, items a sequence, offset) for each match.

    Gaps of one size are kept as runs of consecutive sequences.
    """
    gaps: dict[int, list[tuple[int, int]]] = {}  # gap -> runs (first sequence, sequences)
    order: list[int] = []  # gaps in ascending order
    opened, out = 0, []

    def add(gap: int, first: int, n: int) -> None:
        if gap and n:
            if gap not in gaps:
                gaps[gap] = []
                insort(order, gap)
            gaps[gap].append((first, n))

    for size in sorted(counts, reverse=True):
        left, rank = counts[size], 0

        def fill(first: int, n: int, gap: int) -> None:
            """Put as many as fit into sequences first.. with this gap; what is left of the run keeps its gap."""
            nonlocal left, rank
            fit = gap // size
            whole = min(n, left // fit)
            if whole:
                out.append((size, rank, whole * fit, first, fit, limit - gap))
                add(gap - fit * size, first, whole)
                rank, left = rank + whole * fit, left - whole * fit
            if left and whole < n:  # the last sequence takes fewer than fit
                out.append((size, rank, left, first + whole, left, limit - gap))
                add(gap - left * size, first + whole, 1)
                rank, left, whole = rank + left, 0, whole + 1
            add(gap, first + whole, n - whole)

        at = bisect_left(order, size)
        for gap in order[at:]:
            if not left:
                break
            runs = gaps.pop(gap)
            del order[bisect_left(order, gap)]
            for run in runs:
                if left:
                    fill(*run, gap)
                else:
                    add(gap, *run)
        if left:
            n = -(-left // (limit // size))
            opened, first = opened + n, opened
            fill(first, n, limit)
    return out


def pack(pieces: DataFrame, limit: int = 4096) -> DataFrame:
    """Adds sequence_id and offset to pieces (doc_id, piece, start, length, ...). Lengths are 1 to limit.

    All columns of pieces stay, whatever their names, but for sequence_id and offset, which are replaced.
    The pieces are read three times: give a table that is stored, not a costly plan.
    """
    spark = pieces.sparkSession
    kept = [c for c in pieces.columns if c not in ("sequence_id", "offset")]
    order = ["doc_id", "piece", *[c for c in ("ids_crc32",) if c in kept]]
    keyed = pieces.select(
        F.struct(*kept).alias("row"),
        F.col("length").cast("long").alias("length"),
        F.pmod(F.xxhash64("doc_id", "piece", "start"), F.lit(4 * partitions(spark))).alias("lane"),
    )
    per_lane = keyed.groupBy("length", "lane").agg(F.count("*").alias("n"))
    totals = {r["length"]: r["n"] for r in keyed.groupBy("length").agg(F.count("*").alias("n")).collect()}
    if totals and not 1 <= min(totals) <= max(totals) <= limit:
        raise ValueError(f"piece lengths must be 1 to {limit}")
    rows = place_classes(totals, limit)
    matches = spark.createDataFrame(rows, "length long, first_rank long, ranks long, first_sequence long, fit long, base long")
    before = Window.partitionBy("length").orderBy("lane").rowsBetween(Window.unboundedPreceding, -1)
    offsets = per_lane.select("length", "lane", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("ahead"))
    inside = Window.partitionBy("length", "lane").orderBy(*[f"row.{c}" for c in order])
    ranked = keyed.withColumn("in_lane", F.row_number().over(inside) - 1).join(offsets, ["length", "lane"])
    ranked = ranked.select("row", "length", (F.col("in_lane") + F.col("ahead")).alias("rank"))
    step = F.col("rank") - F.col("first_rank")
    here = (ranked["length"] == matches["length"]) & step.between(F.lit(0), F.col("ranks") - 1)
    placed = ranked.join(F.broadcast(matches) if len(rows) <= 1_000_000 else matches, here)
    return placed.select(
        *[F.col("row")[c].alias(c) for c in kept],
        (F.col("first_sequence") + F.floor(step / F.col("fit"))).cast("long").alias("sequence_id"),
        (F.col("base") + F.pmod(step, F.col("fit")) * ranked["length"]).cast("long").alias("offset"),
    )


def pack_documents(docs: DataFrame, tokenizer_path: str, limit: int = 4096, end_id: int = 1) -> DataFrame:
    return pack(materialize(token_pieces(docs, tokenizer_path, limit, end_id), "pieces"), limit)


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
