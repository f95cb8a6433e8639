"""Order MinHash fingerprints.

A text is the set of its k-mers (runs of K code points), each numbered by how often it occurred before. For every one
of TUPLES hash functions the SIZE smallest numbered k-mers are chosen; taken in text order they are hashed to one
number. Two texts agree in a number when they share the chosen k-mers and their order, so the share of equal numbers
falls with edit distance, also with edits that only move text.

Texts shorter than K are one padded k-mer; the empty text (and null) has the all-zero fingerprint, which is like itself
only. Equal texts have equal fingerprints.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.llm.common import partitions, table, whole_text

K, TUPLES, SIZE = 12, 32, 2
BLOCK = 8192  # k-mers hashed at once by all functions

_rng = np.random.Generator(np.random.PCG64(12))
_XOR = _rng.integers(0, 1 << 32, (TUPLES, 1), dtype=np.uint32)
_MUL = _rng.integers(0, 1 << 32, (TUPLES, 1), dtype=np.uint32) | np.uint32(1)
_LEVEL = _rng.integers(0, 1 << 63, 8, dtype=np.uint64) | np.uint64(1)
_TOP = np.uint32(0xFFFFFFFF)


def _mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x *= np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    return x


def kmer_hashes(text: str) -> np.ndarray:
    """A 64-bit hash of each k-mer, by joining hashes of runs of 1, 2, 4, 8 and at last K = 8 + 4 code points."""
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    if not len(codes):
        return codes
    if len(codes) < K:
        codes = np.concatenate([codes, np.full(K - len(codes), 0x110000, np.uint64)])
    h = _mix(codes + np.uint64(1))
    h = h[:-1] * _LEVEL[0] + h[1:]
    four = h[:-2] * _LEVEL[1] + h[2:]
    eight = four[:-4] * _LEVEL[2] + four[4:]
    return _mix(eight[:-4] * _LEVEL[3] + four[8:])


def numbered(kmers: np.ndarray) -> np.ndarray:
    """32-bit hashes of (k-mer, number of equal k-mers before it)."""
    n = len(kmers)
    bits = np.uint64(max(1, n.bit_length()))
    order = (kmers >> bits << bits) | np.arange(n, dtype=np.uint64)
    order.sort()
    group = order >> bits
    same = np.zeros(n, bool)
    np.equal(group[1:], group[:-1], out=same[1:])
    if not same.any():
        return (kmers >> np.uint64(32)).astype(np.uint32)
    at = np.arange(n)
    nth = at - np.maximum.accumulate(np.where(same, 0, at))
    number = np.empty(n, np.uint64)
    number[(order & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64)] = nth
    return np.where(number == 0, kmers, _mix(kmers ^ (number * _LEVEL[4]))).__rshift__(np.uint64(32)).astype(np.uint32)


def smallest(elements: np.ndarray, first: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """For each hash function the SIZE smallest values and their places (-1 where there are fewer)."""
    values, places = np.full((TUPLES, 0), _TOP), np.full((TUPLES, 0), -1)
    rows = np.arange(TUPLES)
    for at in range(0, len(elements), BLOCK):
        x = elements[None, at : at + BLOCK] ^ _XOR
        x *= _MUL
        v, p = [], []
        for _ in range(min(SIZE, x.shape[1])):
            i = x.argmin(1)
            v.append(x[rows, i])
            p.append(i + (first + at))
            x[rows, i] = _TOP
        values, places = merge((values, places), (np.stack(v, 1), np.stack(p, 1)))
    return values, places


def merge(a: tuple, b: tuple) -> tuple[np.ndarray, np.ndarray]:
    values, places = np.concatenate([a[0], b[0]], 1), np.concatenate([a[1], b[1]], 1)
    keep = np.argsort(values, 1, kind="stable")[:, :SIZE]
    return np.take_along_axis(values, keep, 1), np.take_along_axis(places, keep, 1)


def signature(kmers: np.ndarray, places: np.ndarray) -> np.ndarray:
    """TUPLES 32-bit numbers from the chosen k-mers in text order."""
    if not len(kmers):
        return np.zeros(TUPLES, np.uint32)
    out = np.zeros(TUPLES, np.uint64)
    for column in np.sort(places, 1).T:
        out = _mix(out * _LEVEL[5] + kmers[column] + np.uint64(1))
    return (out >> np.uint64(32)).astype(np.uint32)


def fingerprint(text: str) -> np.ndarray:
    kmers = kmer_hashes(text)
    return signature(kmers, smallest(numbered(kmers))[1])


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    return float((a == b).mean())


class _Text:
    """A text's k-mers and the minima of the part that its edited text keeps."""

    def __init__(self, doc_id: int | None, text: str):
        self.doc_id, self.text, self.kept = doc_id, text, len(text) - len(text) // 4
        self.kmers = kmer_hashes(text)
        elements = numbered(self.kmers)
        self.shared = max(0, self.kept - K + 1) if len(text) >= K else 0
        self.low = smallest(elements[: self.shared])
        self.print = signature(self.kmers, merge(self.low, smallest(elements[self.shared :], self.shared))[1])

    def edited(self, other: str) -> tuple[str, np.ndarray]:
        """The edited text and its fingerprint; k-mers inside the kept part have the same numbers as before."""
        text = self.text[: self.kept] + other[: len(self.text) - self.kept]
        if text == self.text:
            return text, self.print
        kmers = kmer_hashes(text)
        shared = self.shared if len(text) >= K else 0
        low = merge(self.low if shared else smallest(kmers[:0]), smallest(numbered(kmers)[shared:], shared))
        return text, signature(kmers, low[1])


def _place(bounds: list[int], key: Column) -> Column:
    """Index of the last bound that is not above the key, by a search in two steps."""
    width = max(1, int(len(bounds) ** 0.5))
    groups = [bounds[i : i + width] for i in range(0, len(bounds), width)]
    array = lambda xs: "array(" + ",".join(f"{x}L" if x > -(1 << 63) else "cast('-9223372036854775808' as bigint)" for x in xs) + ")"
    coarse = F.expr(array([g[0] for g in groups]))
    fine = F.expr("array(" + ",".join(map(array, groups)) + ")")
    group = F.greatest(F.size(F.filter(coarse, lambda b: b <= key)), F.lit(1))
    return (group - 1) * width + F.size(F.filter(F.element_at(fine, group), lambda b: b <= key)) - 1


def in_order_with_next(docs: DataFrame) -> DataFrame:
    """Rows (part, extra, doc_id, text): each part is a range of ids in order, then, as extra rows, the next part's first.

    The last part ends with the very first row. Texts move once; the bounds come from the ids alone. Quantiles are
    doubles, which are no ids of the table beyond 2^53, so each part is then bounded by the least id in it.
    """
    spark = docs.sparkSession
    ids = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("k"))
    n = 4 * partitions(spark)
    found = ids.agg(F.min("k").alias("least"), F.percentile_approx("k", [i / n for i in range(1, n)] or [0.5], 10_000).alias("cuts")).first()
    rough = sorted({found["least"], *found["cuts"]}) if found["least"] is not None else [0]
    bounds = sorted(r["k"] for r in ids.groupBy(_place(rough, F.col("k")).alias("own")).agg(F.min("k").alias("k")).collect()) or [0]
    key = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63)))
    part = _place(bounds, key).cast("int")
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text"), part.alias("own"), key.isin(bounds[:1]).alias("very_first"), key.alias("k"))
    starts = F.element_at(F.expr("array(" + ",".join(f"{b}L" if b > -(1 << 63) else "cast('-9223372036854775808' as bigint)" for b in bounds) + ")"), F.col("own") + 1) == F.col("k")
    before = F.when(F.col("very_first"), F.lit(len(bounds) - 1)).otherwise(F.col("own") - 1)
    places = F.when(starts, F.array(F.struct(F.col("own").alias("part"), F.lit(False).alias("extra")), F.struct(before.alias("part"), F.lit(True).alias("extra")))).otherwise(
        F.array(F.struct(F.col("own").alias("part"), F.lit(False).alias("extra")))
    )
    spread = keyed.select("doc_id", "text", F.explode(places).alias("p")).select("p.part", "p.extra", "doc_id", "text")
    return spread.repartition(partitions(spark), "part").sortWithinPartitions("part", "extra", "doc_id", "text")


RESULT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def edited_fingerprints(docs: DataFrame) -> DataFrame:
    """Fingerprints of all texts and of their edited texts, and the likeness to those and to the next document's."""

    def close(own: _Text, nxt: _Text) -> tuple:
        text, printed = own.edited(nxt.text)
        sha = hashlib.sha256(text.encode("utf-8", "surrogatepass")).hexdigest()
        return own.doc_id, len(own.text), sha, own.print.tobytes().hex(), printed.tobytes().hex(), likeness(own.print, printed), likeness(own.print, nxt.print)

    def walk(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, part = None, None

        def left(one: _Text | None) -> None:
            if one is not None:
                raise ValueError(f"part {part} ends without the document that follows {one.doc_id}")

        for b in batches:
            out = []
            for at, extra, doc, text in zip(*(b.column(c).to_pylist() for c in ("part", "extra", "doc_id", "text")), strict=True):
                if at != part:
                    left(held)
                    held, part = None, at
                if extra and held is None:
                    continue  # a second row with the id that the next part starts with
                new = _Text(doc, text)
                if held is not None:
                    out.append(close(held, new))
                held = None if extra else new
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64())
            cols = list(zip(*out, strict=True)) or [[]] * 7
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], [x.split()[0] for x in RESULT.split(", ")])
        left(held)

    return in_order_with_next(docs).mapInArrow(walk, RESULT)


def op1_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edited_fingerprints(table(spark, sf_dir, "documents"))
