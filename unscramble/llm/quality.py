"""Quality classifier: nearest-neighbour voting in a latent semantic space.

A text's terms are its words (lower case, letters only), the shape of each token (letter case, what punctuation is
around it) and repetition (a token equal to the one before, how many tokens are distinct), each hashed to a bounded
number of columns. Columns are weighted by TF-IDF and projected on the leading singular vectors of the labelled sample.
The projected labelled vectors are broadcast (SAMPLE rows of RANK numbers at most, whatever the corpus), every document
gets exact cosines to all of them in blocks, and its NEIGHBOURS nearest vote with their similarity as weight.

Labels come only from rows whose crc32 of doc_id as text is not divisible by 5; of those the SAMPLE with the smallest
hash of doc_id are taken. The columns lang, source and doc_id never enter a score. Ties among neighbours go to the
smaller place in the sample. Null and empty texts have no terms and get the sample's share of label 1.
"""

from __future__ import annotations

import re
import struct
from collections.abc import Iterable, Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.llm.chunks import Memo, before_spaces, focus, joined, parts_of
from unscramble.llm.common import ship_package, table, whole_text

SAMPLE, RANK, NEIGHBOURS = 4096, 48, 15
WORD_COLUMNS, SHAPE_COLUMNS = 3072, 1024
COLUMNS = WORD_COLUMNS + SHAPE_COLUMNS
WORD_WEIGHT, PRIOR_WEIGHT, CUT = 0.35, 0.1, 0.3

_LETTERS = re.compile(r"[^\W\d_]+")


def _columns(token: str) -> tuple[int, int]:
    """Columns of a token's word and shape."""
    f = _LETTERS.search(token)
    word = f[0] if f else token
    around = re.sub(r"[^\W_]+", "w", token)[:12]
    case = "n" if not f else "u" if word.isupper() and len(word) > 1 else "l" if word.islower() else "c" if word.istitle() else "m"
    h = xxhash.xxh3_64_intdigest
    return h(word.lower()) % WORD_COLUMNS, WORD_COLUMNS + h(f"{case} {around}", 1) % SHAPE_COLUMNS


_TOKEN = np.dtype([("token", "<u8"), ("columns", "<i4", 2)])
_PACK = struct.Struct("<Qii").pack


def _tokens_in(chunk: str) -> bytes:
    """Hash and columns of each token in a chunk of text."""
    return b"".join([_PACK(xxhash.xxh3_64_intdigest(t), *_columns(t)) for t in chunk.split()])


_known = Memo(_tokens_in, 64 << 20)


def terms_of(texts: pa.Array | list[str]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each text the columns of its terms and their damped frequencies."""
    focus("terms", _known.clear)
    for chunks, starts, block in parts_of(texts, before_spaces):
        data, ends = joined(chunks, starts, _known.__getitem__)
        data = data.view(_TOKEN)
        for text, a, b in zip(block.to_pylist(), (ends[:-1] // _TOKEN.itemsize).tolist(), (ends[1:] // _TOKEN.itemsize).tolist(), strict=True):
            n = b - a
            if not n:
                yield np.zeros(0, np.int64), np.zeros(0, np.float32)
                continue
            token = data["token"][a:b]
            distinct = len(np.unique(token))
            again = np.count_nonzero(token[1:] == token[:-1]) / n
            lines = text.split("\n")
            extra = [f"again {min(9, round(10 * again))}", f"distinct {round(10 * distinct / n) if n >= 50 else -1}", f"lines {round(4 * len(set(lines)) / len(lines))}"]
            counts = np.bincount(data["columns"][a:b].ravel(), minlength=COLUMNS)
            at = np.flatnonzero(counts)
            value = (counts[at] / n).astype(np.float32)
            value = np.sqrt(value) * np.where(at < WORD_COLUMNS, np.float32(WORD_WEIGHT), np.float32(1))
            own = np.array([WORD_COLUMNS + xxhash.xxh3_64_intdigest(e, 2) % SHAPE_COLUMNS for e in extra])
            yield np.concatenate([at, own]), np.concatenate([value, np.full(len(own), 0.5, np.float32)])


def terms(text: str) -> tuple[np.ndarray, np.ndarray]:
    return next(terms_of([text]))


class Neighbours:
    """Weights and axes of the latent space, and the labelled vectors in it."""

    def __init__(self, rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray):
        n = len(rows)
        x = np.zeros((n, COLUMNS), np.float32)
        for i, (at, value) in enumerate(rows):
            np.add.at(x[i], at, value)
        self.labels = labels.astype(np.float32)
        self.prior = float(labels.mean()) if n else 0.5
        self.idf = (1 + np.log((1 + n) / (1 + (x > 0).sum(0)))).astype(np.float32)
        x *= self.idf
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)
        g = np.random.Generator(np.random.PCG64(4))
        rank = min(RANK, max(n, 1))
        q = g.standard_normal((COLUMNS, rank + 16)).astype(np.float32)
        for _ in range(4):  # subspace iteration
            q, _ = np.linalg.qr(x.T @ (x @ q))
        _, _, v = np.linalg.svd(x @ q, full_matrices=False)
        self.axes = np.ascontiguousarray((q @ v.T)[:, :rank]).astype(np.float32)
        self.vectors = self._unit(x @ self.axes)

    @staticmethod
    def _unit(x: np.ndarray) -> np.ndarray:
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)

    def project(self, found: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
        """Unit vectors of the latent space (or zeros) from texts' terms."""
        out = np.zeros((len(found), self.axes.shape[1]), np.float32)
        for i, (at, value) in enumerate(found):
            if len(at):
                out[i] = (value * self.idf[at]) @ self.axes[at]
        return self._unit(out)

    def score(self, texts: pa.Array | list[str], block: int = 256) -> np.ndarray:
        """Shares of label 1 among the nearest neighbours, weighted by similarity and drawn to the prior a little."""
        out = np.full(len(texts), self.prior)
        k = min(NEIGHBOURS, len(self.labels))
        found = terms_of(texts)
        for at in range(0, len(texts) if k else 0, block):
            x = self.project(list(islice(found, block)))
            cosines = x @ self.vectors.T
            near = np.argpartition(-cosines, k - 1, axis=1)[:, :k] if k < cosines.shape[1] else np.tile(np.arange(k), (len(x), 1))
            w = np.maximum(np.take_along_axis(cosines, near, 1), 0) ** 4
            votes = (w * self.labels[near]).sum(1) + PRIOR_WEIGHT * self.prior
            known = np.linalg.norm(x, axis=1) > 0
            out[at : at + block] = np.where(known, votes / (w.sum(1) + PRIOR_WEIGHT), self.prior)
        return np.clip(out, 0, 1)


def held_out():
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Neighbours:
    """Fit to at most sample labelled texts, none of them held out."""
    known = labels.filter(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out())
    known = known.groupBy("doc_id").agg(F.max("quality").alias("quality"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = list(terms_of(b.column("text")))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("quality"), pa.array([a.astype("<i4").tobytes() for a, _ in got], pa.binary()), pa.array([v.astype("<f4").tobytes() for _, v in got], pa.binary())], ["doc_id", "quality", "at", "value"])

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text"))
    rows = texts.join(F.broadcast(chosen), "doc_id").select("doc_id", F.col("quality").cast("int").alias("quality"), "text").mapInArrow(run, "doc_id long, quality int, at binary, value binary").collect()
    rows = sorted({r["doc_id"]: r for r in rows}.values(), key=lambda r: r["doc_id"])
    return Neighbours([(np.frombuffer(r["at"], "<i4").astype(np.int64), np.frombuffer(r["value"], "<f4")) for r in rows], np.array([r["quality"] for r in rows], np.float64))


def with_scores(docs: DataFrame, model: Neighbours, name: str = "score") -> DataFrame:
    """docs with a column of scores, which takes the place of one of that name. Each document is read once, never moved."""
    ship_package(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    docs = docs.drop(name)
    schema = docs.withColumn(name, F.lit(0.0)).schema

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(b.schema.get_field_index("text")).fill_null("")
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(shared.value.score(texts), pa.float64())], [*b.schema.names, name])

    return docs.mapInArrow(run, schema)


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = fit(docs, table(spark, sf_dir, "labels"))
    scored = with_scores(docs.select("doc_id", "text"), model)
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted"))
