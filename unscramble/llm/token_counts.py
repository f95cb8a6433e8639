"""Token counts with a digest cache.

The cache is a Parquet table (content digest, tokenizer digest, n_tokens) in shared storage that only grows. A run
joins the digests of its texts with it, encodes each distinct text that is missing once, appends, and joins again.
Neither tokenizer here normalises the white space or case that a count depends on, so the content is normalised only
by turning null into the empty text. Texts that occur many times meet in a partial aggregate before any shuffle.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.llm import chunks
from unscramble.llm.common import materialize, scratch_path, ship_package, table, whole_text

CACHE = "digest string, version string, n_tokens long"


def tokenizer_version(path: str) -> str:
    return hashlib.sha256(Path(path).read_bytes()).hexdigest()


def read_cache(spark: SparkSession, path: str, version: str) -> DataFrame:
    """One row for each digest of this tokenizer version; runs at the same time may have stored a digest twice."""
    try:
        stored = spark.read.schema(CACHE).parquet(path)
    except AnalysisException as e:
        if "PATH_NOT_FOUND" not in str(e):
            raise
        stored = spark.createDataFrame([], CACHE)
    return stored.filter(F.col("version") == version).groupBy("digest").agg(F.max("n_tokens").alias("n_tokens"))


def count_tokens(docs: DataFrame, tokenizer_path: str, cache_path: str) -> DataFrame:
    """doc_id, n_bytes and n_tokens of every row of docs (doc_id, text)."""
    spark, version = docs.sparkSession, tokenizer_version(tokenizer_path)
    ship_package(spark)
    texts = docs.select("doc_id", whole_text().alias("text")).withColumn("digest", F.sha2("text", 256))

    def encode(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            counts = chunks.count_ids(b.column("text"), tokenizer_path)
            yield pa.RecordBatch.from_arrays([b.column("digest"), pa.array([version] * len(counts), pa.string()), pa.array(counts, pa.int64())], ["digest", "version", "n_tokens"])

    misses = texts.select("digest", "text").join(read_cache(spark, cache_path, version), "digest", "left_anti").dropDuplicates(["digest"])
    misses.select("digest", "text").mapInArrow(encode, CACHE).write.mode("append").parquet(cache_path)
    # stored, so that no aggregate stands between the shuffle and the join, and a digest with many rows can be split
    counts = materialize(read_cache(spark, cache_path, version), "counts")
    return texts.select("doc_id", "digest", F.octet_length("text").cast("long").alias("n_bytes")).join(counts, "digest")


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts with a cache that starts empty, so that the query always does all its work; a user names a lasting one."""
    import public_tokenizers

    counted = count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), scratch_path(spark, "token-cache"))
    return counted.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > 1024).alias("over_limit"))
