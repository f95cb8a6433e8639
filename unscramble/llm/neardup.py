"""Near-duplicate classes by improved consistent weighted sampling over TF-IDF shingles.

Weights. A shingle is five consecutive words (what white space parts, in lower case, letters and digits only; a shorter
text is one shingle). Its weight is its count in
the text times the mean inverse document frequency of its words. Frequencies are counted over all documents in a table
of 2^20 counters addressed by word hash, so what is broadcast has the same size for any corpus. Frequencies of whole
shingles would need two shuffles of every shingle, and would make the words that near copies share (which are frequent
because of the copies) weigh next to nothing against the few that differ.

Candidates. Equal word sequences fall together first. Of the rest SAMPLES consistent weighted samples are taken and cut
in BANDS; documents with an equal band are candidates. In each bucket the most central member is the anchor and every
other member is compared with it. Members that end outside the anchor's class are open. Samples of open members and of
their buckets are compared in blocks inside tasks; documents that look alike so, over all buckets, form groups, and the
open ones of a group are compared with the whole group in blocks, over inverted indexes. After that every candidate
pair has been verified or lies within one class, and pairs were never rows: a document is sent once to each block.

Before texts are moved for a candidate pair, its samples must look alike: a pair at the threshold fails that with a
probability of MISS at most (as samples estimate the similarity at every length). alike=0 verifies every candidate pair.

Verification is the exact weighted Jaccard similarity of the two whole texts (0.8 or more). Classes are the connected
components of verified pairs and carry their smallest doc_id.

Null text is empty. Texts without words are equal only to the same text. Rows that repeat a doc_id are told apart by
their texts, each of which is in the class it is like (classes of different texts have one name if the same doc_id is
the smallest of both); rows without doc_id get no class. An empty table gives no rows.
"""

from __future__ import annotations

import math
import re
import struct
from collections.abc import Callable, Iterable, Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.llm.chunks import Memo, before_spaces, focus, joined, parts_of
from unscramble.llm.common import drop_scratch, materialize, may_hold, partitions, ship_package, table, whole_text

SHINGLE, THRESHOLD = 5, 0.8
SAMPLES, BANDS = 64, 16
COUNTERS, PER_ROW = 1 << 20, 1 << 14
WORDS = re.compile(r"\w+")
_U = np.uint64
_PRIME = [_U(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5)]



def _hashes_in(chunk: str) -> bytes:
    """Hashes of the words in a chunk of text: what white space parts, letters and digits only; tokens without have none."""
    words = ["".join(WORDS.findall(token.lower())) for token in chunk.split()]
    return b"".join([_PACK(xxhash.xxh3_64_intdigest(w) or 1) for w in words if w])


_PACK = struct.Struct("<Q").pack
_hashes = Memo(_hashes_in, 96 << 20)


def word_hashes_of(texts: pa.Array | list[str]) -> Iterator[np.ndarray]:
    """For each text the hashes of its words, in order."""
    focus("word hashes", _hashes.clear)
    for chunks, starts, _ in parts_of(texts, before_spaces):
        data, ends = joined(chunks, starts, _hashes.__getitem__)
        data = data.view(_U)
        for a, b in zip((ends[:-1] // 8).tolist(), (ends[1:] // 8).tolist(), strict=True):
            yield data[a:b]


def word_hashes(text: str) -> np.ndarray:
    return next(word_hashes_of([text]))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> _U(29))
    x *= _PRIME[1]
    x ^= x >> _U(32)
    return x


class Weights:
    """Inverse document frequencies, and from them the weighted shingles of a text."""

    def __init__(self, counts: np.ndarray, documents: int):
        self.idf = (1 + np.log((1 + documents) / (1 + np.maximum(counts, 1)))).astype(np.float32)

    def shingles(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """Sorted distinct shingle hashes and their weights."""
        return self.of_words(word_hashes(text))

    def of_words(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(h):
            return h, np.zeros(0, np.float32)
        idf = self.idf[(h >> _U(44)).astype(np.int64)].astype(np.float64)
        width = min(SHINGLE, len(h))
        n = len(h) - width + 1
        s, w = np.zeros(n, _U), np.zeros(n)
        for k in range(width):
            s = s * _PRIME[0] + _mixed(h[k : k + n] + _PRIME[k])
            w += idf[k : k + n]
        s = _mixed(s)
        order = np.argsort(s)
        s = s[order]
        first = np.ones(n, bool)
        np.not_equal(s[1:], s[:-1], out=first[1:])
        at = np.flatnonzero(first)
        count = np.diff(np.append(at, n))
        return s[at], (w[order][at] / width * count).astype(np.float32)


def weighted_jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    if not len(a[0]) or not len(b[0]):
        return 0.0
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    both = float(np.minimum(a[1][i], b[1][j]).sum(dtype=np.float64))
    return both / (float(a[1].sum(dtype=np.float64)) + float(b[1].sum(dtype=np.float64)) - both)


_rng = np.random.Generator(np.random.PCG64(3))
_XOR, _ODD = (_rng.integers(0, 1 << 32, SAMPLES, dtype=np.uint32) for _ in range(2))
_ODD |= np.uint32(1)
_random: list[np.ndarray] = []


def _tables() -> list[np.ndarray]:
    """ln of Gamma(2, 1) by its lower share, the same by its upper share, and what ln c - r is at least in each class.

    Shares are 32 bits wide, and tables are addressed by the leading 20 bits of a share as a float, so small shares are
    as fine as large ones. A class is the 8 leading bits of the shares of c and r.
    """
    if not _random:
        at = np.linspace(-14, 4, 60_000)
        x = np.exp(at)
        low, high = -np.expm1(-x) - x * np.exp(-x), np.exp(-x) * (1 + x)
        share = (np.arange((_LAST >> 12) - (_FIRST >> 12) + 2, dtype=np.uint32) + np.uint32(_FIRST >> 12) << np.uint32(12)).view(np.float32).astype(np.float64)
        small = np.interp(np.log(share), np.log(low), at)
        large = np.interp(-np.log(share), -np.log(high), at)
        edge = np.maximum(np.arange(256) / 256, 2.0**-33).astype(np.float32)
        least = small[_entry(edge)][:, None] - np.exp(large[_entry(edge)])[None, :]
        _random.extend((small, np.exp(large), (least - 0.01).astype(np.float32).ravel()))
    return _random


_FIRST, _LAST = (int(np.float32(x).view(np.uint32)) for x in (2.0**-33, 1.0))


def _entry(share: np.ndarray) -> np.ndarray:
    return (share.view(np.uint32) >> np.uint32(12)).astype(np.int64) - (_FIRST >> 12)


def _chosen(shingle: np.ndarray, lane: np.ndarray, kind: np.ndarray, log_weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The value that is to be the least, and the level, of shingles in a sample; kind is the class of c and r there.

    r and c are Gamma(2, 1) and beta is uniform, all of the shingle's own: no rows of random numbers are shared.
    """
    by_low, by_high, _ = _tables()
    h = _mixed((shingle + lane.astype(_U) * _PRIME[4]) * _PRIME[3])
    more = _mixed(h * _PRIME[2])
    share = lambda bits, rest: ((bits << 24 | rest.view(np.int64)) + 0.5).astype(np.float32) * np.float32(2.0**-32)
    log_c = by_low[_entry(share(kind >> 8, h >> _U(40)))]
    r = by_high[_entry(share(kind & 255, h & _U(0xFFFFFF)))]
    beta = (more >> _U(11)) * 2.0**-53
    level = np.floor(log_weight / r + beta)
    return log_c - r * (level - beta + 1), level.astype(np.int64)


def _kinds(shingles: np.ndarray) -> np.ndarray:
    """Class of each (shingle, sample), 16 bits."""
    h = (shingles ^ (shingles >> _U(32))).astype(np.uint32)[:, None] ^ _XOR
    h *= _ODD
    h ^= h >> np.uint32(15)
    h *= np.uint32(0x9E3779B1)
    h >>= np.uint32(16)
    return h.astype(np.int64)


def samples(shingles: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """SAMPLES hashes, each of a chosen (shingle, level); equal with the probability of the weighted Jaccard similarity.

    A value is at least ln c - r - ln weight, so only those whose class can hold the least one are worked out.
    """
    least = _tables()[2]
    best = np.full(SAMPLES, np.inf)
    who, level = np.zeros(SAMPLES, np.int64), np.zeros(SAMPLES, np.int64)
    lanes = np.arange(SAMPLES)
    logs = np.log(weights.astype(np.float64))
    short = logs.astype(np.float32)[:, None]

    def meet(i: np.ndarray, lane: np.ndarray, kind: np.ndarray) -> None:
        value, t = _chosen(shingles[i], lane, kind, logs[i])
        at = np.flatnonzero(value < best[lane])
        at = at[np.argsort(-value[at], kind="stable")]  # the least value is written last
        best[lane[at]], who[lane[at]], level[lane[at]] = value[at], i[at], t[at]

    at, step = 0, 64
    while at < len(shingles):
        kind = _kinds(shingles[at : at + step])
        low = least.take(kind)
        low -= short[at : at + step]
        if at == 0:
            i = low.argmin(0)
            meet(i, lanes, kind[i, lanes])
        can = np.flatnonzero(low <= best.astype(np.float32))
        meet(can // SAMPLES + at, can % SAMPLES, kind.ravel()[can])
        at, step = at + step, 384
    return _mixed(shingles[who] * _PRIME[2] + level.astype(_U) * _PRIME[3] + lanes.astype(_U))


def bands(chosen: np.ndarray) -> np.ndarray:
    """One signed 64-bit key for each band; the band's number is part of it."""
    out = np.arange(BANDS, dtype=_U) * _PRIME[4]
    for column in chosen.reshape(BANDS, -1).T:
        out = _mixed(out * _PRIME[0] + column)
    return out.view(np.int64)


# --- over documents ---------------------------------------------------------------------------------------------


def _texts(docs: DataFrame) -> DataFrame:
    """doc_id, digest of the text, text. A row is named by doc_id and digest, as a doc_id may have several texts."""
    return docs.filter(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), _digest().alias("digest"), whole_text().alias("text"))


def _digest() -> Column:
    return F.xxhash64(whole_text())


def counted(texts: DataFrame, cells_of: Callable[[pa.Array], Iterator[np.ndarray]]) -> tuple[np.ndarray, int]:
    """How many texts have each of COUNTERS cells, and the number of texts. cells_of: the distinct cells of each text.

    Tasks send their counters in rows of a fixed size, which are summed in two rounds; 8 MB reach the driver.
    """

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(COUNTERS, np.int64), 0
        for b in batches:
            cells = cells_of(b.column("text"))
            while some := list(islice(cells, 512)):
                n += len(some)
                total += np.bincount(np.concatenate(some), minlength=COUNTERS)
        if n:
            yield blob(range(COUNTERS // PER_ROW), total.reshape(-1, PER_ROW), n)

    def blob(rows: Iterable[int], values: Iterable[np.ndarray], n: int) -> pa.RecordBatch:
        rows = list(rows)
        data = [v.astype("<i8" if v.max(initial=0) >> 31 else "<i4").tobytes() for v in values]
        return pa.RecordBatch.from_arrays([pa.array(rows, pa.int32()), pa.array(data, pa.binary()), pa.array([n] * len(rows), pa.int64())], ["row", "counts", "n"])

    def add(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        seen: dict[int, int] = {}
        for b in batches:
            for row, data, n in zip(*(b.column(c).to_pylist() for c in ("row", "counts", "n")), strict=True):
                v = np.frombuffer(data, "<i4" if len(data) == 4 * PER_ROW else "<i8").astype(np.int64)
                sums[row] = sums[row] + v if row in sums else v
                seen[row] = seen.get(row, 0) + n
        for row, v in sums.items():
            yield blob([row], [v], seen[row])

    kind, many = "row int, counts binary, n long", partitions(texts.sparkSession)
    lanes = texts.select("text").mapInArrow(count, kind).withColumn("lane", F.pmod(F.spark_partition_id(), F.lit(64)))
    half = lanes.repartition(many, "row", "lane").select("row", "counts", "n").mapInArrow(add, kind)
    out = np.zeros((COUNTERS // PER_ROW, PER_ROW), np.int64)
    n = 0
    for r in half.repartition(min(64, many), "row").mapInArrow(add, kind).collect():
        out[r["row"]] = np.frombuffer(r["counts"], "<i4" if len(r["counts"]) == 4 * PER_ROW else "<i8")
        n = r["n"]
    return out.ravel(), n


def _word_cells(texts: pa.Array) -> Iterator[np.ndarray]:
    return (np.unique((h >> _U(44)).astype(np.int32)) for h in word_hashes_of(texts))


def document_frequencies(docs: DataFrame) -> tuple[np.ndarray, int]:
    """How many documents hold a word of each counter, and the number of documents."""
    return counted(_texts(docs), _word_cells)


def sketches(docs: DataFrame, weights) -> DataFrame:
    """doc_id, digest, content (digest of the word sequence), sample (16 bits of each) and bands of every document.

    weights: broadcast of Weights.
    """

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys, cuts, short = [], [], []
            texts = b.column("text")
            words_of = word_hashes_of(texts)
            while words := list(islice(words_of, 64)):  # step by step, as each step has tables of its own to keep at hand
                keys += [xxhash.xxh3_128_hexdigest(w.tobytes()) if len(w) else "-" + xxhash.xxh3_128_hexdigest(texts[len(keys) + i].as_py()) for i, w in enumerate(words)]
                sets = [weights.value.of_words(w) for w in words]
                chosen = [samples(*x) if len(x[0]) else None for x in sets]
                cuts += [np.zeros(0, np.int64) if c is None else bands(c) for c in chosen]
                short += [b"" if c is None else c.astype("<u2").tobytes() for c in chosen]
            offsets = np.concatenate([[0], np.cumsum([len(c) for c in cuts])]).astype(np.int32)
            flat = np.concatenate(cuts) if cuts else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("digest"), pa.array(keys, pa.string()), pa.array(short, pa.binary()), pa.ListArray.from_arrays(offsets, flat)], ["doc_id", "digest", "content", "sample", "bands"])

    return _texts(docs).mapInArrow(run, "doc_id long, digest long, content string, sample binary, bands array<long>")


def verified(pairs: DataFrame, texts: DataFrame, weights, threshold: float) -> DataFrame:
    """The pairs (a, b) whose texts are similar enough. texts: doc_id, text; one row for each id."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rb in batches:
            if not rb.num_rows:
                continue
            both = rb.column("tb").dictionary_encode()  # anchors occur many times
            anchors = [weights.value.of_words(w) for w in word_hashes_of(both.dictionary)]
            which = both.indices.to_pylist()
            keep = pa.array([weighted_jaccard(weights.value.of_words(w), anchors[k]) >= threshold for w, k in zip(word_hashes_of(rb.column("ta")), which, strict=True)])
            yield pa.RecordBatch.from_arrays([rb.column("a").filter(keep), rb.column("b").filter(keep)], ["a", "b"])

    left = texts.select(F.col("doc_id").alias("a"), F.col("text").alias("ta"))
    right = texts.select(F.col("doc_id").alias("b"), F.col("text").alias("tb"))
    return pairs.join(left, "a").join(right, "b").select("a", "ta", "b", "tb").mapInArrow(run, "a long, b long")


#: Up to so many links (of a spanning forest) components are finished by one task; beyond, by rounds over tables.
ONE_TASK = 250_000


def _forest(batches: Iterable[pa.RecordBatch], labels: bool) -> Iterator[pa.RecordBatch]:
    """Links (a, b) made a spanning forest: each node with the least node it is connected with."""
    up: dict[int, int] = {}

    def find(x: int) -> int:
        root = x
        while (y := up.setdefault(root, root)) != root:
            root = y
        while up[x] != root:
            up[x], x = root, up[x]
        return root

    for batch in batches:
        for a, b in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), strict=True):
            a, b = find(a), find(b)
            if a != b:
                up[max(a, b)] = min(a, b)
    nodes = list(up)
    for at in range(0, len(nodes), 50_000):
        part = [(x, find(x)) for x in nodes[at : at + 50_000]]
        part = part if labels else [(x, y) for x, y in part if x != y]
        yield pa.RecordBatch.from_arrays([pa.array([p[k] for p in part], pa.int64()) for k in (0, 1)], ["node", "label"] if labels else ["a", "b"])


def components(edges: DataFrame, one_task: int = ONE_TASK) -> DataFrame:
    """node, label (the smallest node that it is connected with) of all nodes of edges (a, b).

    Every task first makes its links a forest. If all forests together are small, one task joins them.
    """
    forest = materialize(edges.select("a", "b").mapInArrow(lambda it: _forest(it, False), "a long, b long"), "forest")
    if forest.count() <= one_task:
        return materialize(forest.coalesce(1).mapInArrow(lambda it: _forest(it, True), "node long, label long"), "labels")
    return spread_components(forest)


def spread_components(edges: DataFrame) -> DataFrame:
    """Components by rounds: the least label among neighbours, then the label's own label, until nothing changes."""
    both = materialize(edges.select("a", "b").union(edges.select("b", "a")).distinct(), "edges")
    labels = materialize(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.min("a")).alias("label")), "labels")
    total = None
    while True:
        now = labels.agg(F.sum(F.col("label").cast("decimal(38,0)"))).first()[0]
        if now == total:
            return labels
        total = now
        near = both.join(labels, both["b"] == labels["node"]).groupBy(F.col("a").alias("node")).agg(F.min("label").alias("around"))
        hop = labels.join(near, "node", "left").select("node", F.least("label", F.coalesce("around", "label")).alias("label"))
        hop = materialize(hop, "labels")
        jump = hop.select(F.col("node").alias("label"), F.col("label").alias("further"))
        labels = materialize(hop.join(jump, "label", "left").select("node", F.coalesce("further", "label").alias("label")), "labels")


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, alike: int | None = None) -> DataFrame:
    """doc_id, class_id, n_links (verified links of its text to other texts) of every document that has an id.

    alike: so many of SAMPLES samples must be equal before a candidate pair is verified; None derives it from threshold.
    """
    return _classed(docs, threshold, alike).select("doc_id", F.col("head.doc_id").alias("class_id"), "n_links")


def _classed(docs: DataFrame, threshold: float, alike: int | None) -> DataFrame:
    """doc_id, digest, head (doc_id and digest of the class's first row), n_links of every row that has an id.

    Inside, each content is a node with a number of its own; the columns doc_id of members and texts hold that number.
    """
    spark = docs.sparkSession
    ship_package(spark)
    least = least_equal(threshold) if alike is None else alike
    counts, n = document_frequencies(docs)
    weights = spark.sparkContext.broadcast(Weights(counts, n))
    signs = materialize(sketches(docs, weights), "sketches")
    contents = signs.groupBy("content").agg(F.min(F.struct("doc_id", "digest")).alias("row"), F.first("bands").alias("bands"), F.first("sample").alias("sample"))
    reps = materialize(contents.withColumn("node", F.monotonically_increasing_id()), "contents")
    members = _with_anchors(reps.select(F.col("node").alias("doc_id"), F.explode("bands").alias("bucket")))

    named = members.select(F.col("doc_id").alias("node")).distinct()
    wanted = materialize(reps.join(named, "node", "left_semi").select("row.doc_id", "row.digest", "node", F.xxhash64("row.doc_id", "row.digest").alias("k")), "wanted")
    near = may_hold(wanted, "k", _texts(docs), F.xxhash64("doc_id", "digest")).filter("_may").drop("_may")
    found = near.join(wanted.drop("k"), ["doc_id", "digest"]).dropDuplicates(["doc_id", "digest"])
    texts = materialize(found.select(F.col("node").alias("doc_id"), "text"), "texts")
    star = members.filter("doc_id <> anchor").select(F.col("doc_id").alias("a"), F.col("anchor").alias("b")).distinct()
    signs_of = materialize(reps.join(named, "node", "left_semi").select(F.col("node").alias("doc_id"), "sample"), "signs")
    edges = materialize(verified(look_alike(star, signs_of, least), texts, weights, threshold), "links")
    labels = components(edges)
    more = left_over(members, signs_of, texts, weights, threshold, labels, least)
    if not more.isEmpty():
        edges = edges.union(more)
        labels = components(edges)
    drop_scratch(members, wanted, texts, signs_of)

    linked = F.array(F.struct(F.col("a").alias("x"), F.col("b").alias("y")), F.struct(F.col("b").alias("x"), F.col("a").alias("y")))
    degree = edges.select(F.explode(linked).alias("e")).distinct().groupBy(F.col("e.x").alias("node")).agg(F.count("*").alias("n_links"))
    heads = labels.join(reps.select("node", "row"), "node").groupBy("label").agg(F.min("row").alias("head"))
    classes = labels.join(heads, "label").select("node", "head").join(degree, "node", "left")
    named = reps.select("content", "node", "row").join(classes, "node", "left").select("content", F.coalesce("head", "row").alias("head"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))
    return signs.select("doc_id", "digest", "content").join(named, "content").select("doc_id", "digest", "head", "n_links")


def _with_anchors(keyed: DataFrame) -> DataFrame:
    """bucket, doc_id, anchor of buckets with several members.

    The anchor is the member whose buckets are the largest in sum, as the text that others are copies of has the
    commonest bands; ties go to the smallest id.
    """
    sizes = keyed.groupBy("bucket").agg(F.count("*").alias("n")).filter("n > 1")
    shared = keyed.join(sizes, "bucket").groupBy("doc_id").agg(F.sum("n").alias("c"), F.collect_list("bucket").alias("buckets"))
    ranked = materialize(shared.select("doc_id", F.explode("buckets").alias("bucket"), "c"), "shared")
    best = ranked.groupBy("bucket").agg(F.max(F.struct("c", (-F.col("doc_id")).alias("i"))).alias("k")).select("bucket", (-F.col("k.i")).alias("anchor"))
    out = materialize(ranked.join(best, "bucket").select("bucket", "doc_id", "anchor"), "members")
    drop_scratch(ranked)
    return out


BLOCK = 1024  # open members of a bucket or group that one task compares with others of it
LANE = 16_384  # so many others meet a block in one task
MISS = 5e-6


def least_equal(threshold: float) -> int:
    """So many of SAMPLES a pair at the threshold has equal but for a probability of MISS, by the binomial law."""
    below, k = 0.0, 0
    while k < SAMPLES:
        below += math.comb(SAMPLES, k) * threshold**k * (1 - threshold) ** (SAMPLES - k)
        if below > MISS:
            break
        k += 1
    return k


#: 36 at a similarity of 0.8; such a pair has no equal band with a probability of 0.0002.
ALIKE = least_equal(THRESHOLD)


def look_alike(pairs: DataFrame, signs: DataFrame, least: int) -> DataFrame:
    """The pairs (a, b) with at least so many equal samples, so that no texts are moved for chance candidates."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x, y = (np.frombuffer(b"".join(b.column(c).to_pylist()), "<u2").reshape(b.num_rows, -1) for c in ("sa", "sb"))
            keep = pa.array((x == y).sum(1) >= least)
            yield pa.RecordBatch.from_arrays([b.column("a").filter(keep), b.column("b").filter(keep)], ["a", "b"])

    left, right = (signs.select(F.col("doc_id").alias(c), F.col("sample").alias(f"s{c}")) for c in "ab")
    return pairs.join(left, "a").join(right, "b").select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long")


def _laid_out(rows: DataFrame, key: str) -> DataFrame:
    """rows (key, doc_id, open, ...) by (key, block, lane) for comparing open ones with all: open ones first (turn 0).

    Open ones are dealt to blocks and all are dealt to lanes, both of bounded size: a task sees the open ones of one
    block and the rows of one lane.
    """
    sizes = rows.groupBy(key).agg(F.ceil(F.count_if("open") / BLOCK).cast("int").alias("blocks"), F.ceil(F.count("*") / LANE).cast("int").alias("lanes")).filter("blocks > 0")
    spread = rows.join(sizes, key)
    own = lambda n, seed: F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.col(n)).cast("int")
    place = lambda block, lane, turn: F.struct(block.alias("block"), lane.alias("lane"), F.lit(turn).alias("turn"))
    asks = F.transform(F.sequence(F.lit(0), F.col("lanes") - 1), lambda lane: place(own("blocks", 1), lane, 0))
    meets = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda block: place(block, own("lanes", 2), 1))
    places = F.concat(F.when(F.col("open"), asks).otherwise(F.filter(asks, lambda _: F.lit(False))), meets)
    return spread.withColumn("p", F.explode(places)).select(*rows.columns, "p.block", "p.lane", "p.turn")


def left_over(members: DataFrame, signs: DataFrame, texts: DataFrame, weights, threshold: float, labels: DataFrame, least: int) -> DataFrame:
    """Links (a, b) of the candidate pairs that the anchors leave open: one side is not in its anchor's class.

    Open members first meet their buckets as samples, which leaves the members that look like one of another class.
    Members that are left in a common bucket form groups, in which each text stands once; outside the commonest class
    of a group all are open, and meet the group as weighted shingles. Common weights come from an inverted index of the
    block, so pairs exist only as counters inside the task, and only links come out.
    """
    found = labels.select(F.col("node").alias("doc_id"), F.col("label").alias("own"))
    main = labels.select(F.col("node").alias("anchor"), F.col("label").alias("main"))
    named = members.join(found, "doc_id", "left").withColumn("own", F.coalesce("own", "doc_id")).join(main, "anchor", "left").withColumn("main", F.coalesce("main", "anchor"))
    named = named.select("bucket", "doc_id", "own", (F.col("own") != F.col("main")).alias("open"))
    many = partitions(texts.sparkSession)

    def look(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, asks, table, classes = None, [], None, None
        for rb in batches:
            out = set()
            for bucket, block, lane, turn, doc, own, sample in zip(*(rb.column(c).to_pylist() for c in ("bucket", "block", "lane", "turn", "doc_id", "own", "sample")), strict=True):
                if (bucket, block, lane) != key:
                    key, asks, table = (bucket, block, lane), [], None
                if turn == 0:
                    asks.append((doc, own, sample))
                elif asks:
                    if table is None:
                        table, classes = np.stack([np.frombuffer(x[2], "<u2") for x in asks]), np.array([x[1] for x in asks])
                    hit = np.flatnonzero(((table == np.frombuffer(sample, "<u2")).sum(1) >= least) & (classes != own))
                    if len(hit):
                        out.add((bucket, doc))
                        out.update((bucket, asks[i][0]) for i in hit)
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], pa.int64()) for k in (0, 1)], ["bucket", "doc_id"])

    laid = _laid_out(named, "bucket").join(signs, "doc_id").repartition(many, "bucket", "block", "lane").sortWithinPartitions("bucket", "block", "lane", "turn")
    alive = laid.select("bucket", "block", "lane", "turn", "doc_id", "own", "sample").mapInArrow(look, "bucket long, doc_id long").distinct()
    alive = materialize(alive, "alive")
    none = texts.sparkSession.createDataFrame([], "a long, b long")
    if alive.isEmpty():
        return none

    first = alive.groupBy("bucket").agg(F.min("doc_id").alias("b"))
    together = components(alive.join(first, "bucket").select(F.col("doc_id").alias("a"), "b"))
    grouped = together.select(F.col("node").alias("doc_id"), F.col("label").alias("grp")).join(found, "doc_id", "left").withColumn("own", F.coalesce("own", "doc_id"))
    grouped = materialize(grouped, "grouped")
    commonest = grouped.groupBy("grp", "own").agg(F.count("*").alias("n")).groupBy("grp").agg(F.max_by("own", F.struct("n", "own")).alias("main"))
    grouped = grouped.join(commonest, "grp").select("grp", "doc_id", "own", (F.col("own") != F.col("main")).alias("open"))

    def vectors(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [weights.value.of_words(w) for w in word_hashes_of(b.column("text"))]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([s.tobytes() for s, _ in got], pa.binary()), pa.array([w.tobytes() for _, w in got], pa.binary())], ["doc_id", "s", "w"])

    used = texts.join(grouped.select("doc_id"), "doc_id", "left_semi").select("doc_id", "text").mapInArrow(vectors, "doc_id long, s binary, w binary")
    laid = _laid_out(grouped, "grp").join(used, "doc_id").repartition(many, "grp", "block", "lane").sortWithinPartitions("grp", "block", "lane", "turn")

    def solve(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, asks, index = None, [], None
        for rb in batches:
            out = []
            for grp, block, lane, turn, doc, own, s, w in zip(*(rb.column(c).to_pylist() for c in ("grp", "block", "lane", "turn", "doc_id", "own", "s", "w")), strict=True):
                if (grp, block, lane) != key:
                    key, asks, index = (grp, block, lane), [], None
                s, w = np.frombuffer(s, _U), np.frombuffer(w, np.float32)
                if turn == 0:
                    asks.append((doc, own, s, w))
                    continue
                if not asks:
                    continue
                index = index or _Index(asks)
                out += [(max(doc, x), min(doc, x)) for x in index.like(doc, own, s, w, threshold)]
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], pa.int64()) for k in (0, 1)], ["a", "b"])

    links = materialize(laid.select("grp", "block", "lane", "turn", "doc_id", "own", "s", "w").mapInArrow(solve, "a long, b long").distinct(), "links")
    drop_scratch(alive, grouped)
    return links


class _Index:
    """Inverted index of some weighted sets (doc, class, shingles, weights)."""

    def __init__(self, sets: list[tuple]):
        self.docs, self.own = np.array([x[0] for x in sets], np.int64), np.array([x[1] for x in sets], np.int64)
        self.total = np.array([x[3].sum(dtype=np.float64) for x in sets])
        s = np.concatenate([x[2] for x in sets])
        order = np.argsort(s, kind="stable")
        self.s, self.w = s[order], np.concatenate([x[3] for x in sets])[order].astype(np.float64)
        self.who = np.repeat(np.arange(len(sets)), [len(x[2]) for x in sets])[order]

    def like(self, doc: int, own: int, s: np.ndarray, w: np.ndarray, threshold: float) -> list[int]:
        """Docs of other classes whose weighted Jaccard similarity reaches the threshold, exactly."""
        lo, hi = np.searchsorted(self.s, s, "left"), np.searchsorted(self.s, s, "right")
        n = hi - lo
        at = np.repeat(lo - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
        both = np.bincount(self.who[at], np.minimum(self.w[at], np.repeat(w, n)), len(self.docs))
        good = (both >= threshold * (self.total + w.sum(dtype=np.float64) - both)) & (self.own != own) & (self.docs != doc)
        return self.docs[good].tolist()


def one_of_each_class(docs: DataFrame, threshold: float = THRESHOLD, alike: int | None = None) -> DataFrame:
    """The first row of each class (smallest doc_id, then digest), once, and rows without doc_id.

    Only rows that go, or that occur several times, are shuffled (and those that the bit map takes for such).
    """
    classes = materialize(_classed(docs, threshold, alike), "classes")
    first = F.max((F.col("doc_id") == F.col("head.doc_id")) & (F.col("digest") == F.col("head.digest"))).alias("first")
    looked_at = classes.groupBy("doc_id", "digest").agg(F.count("*").alias("n"), first).filter("n > 1 OR NOT first")
    looked_at = materialize(looked_at.select("doc_id", F.col("digest").alias("_digest"), "first", F.xxhash64("doc_id", "digest").alias("k")), "looked_at")
    # whole rows travel in one column, so that no name of theirs meets one of ours
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").cast("long").alias("doc_id"), _digest().alias("_digest"))
    split = may_hold(looked_at, "k", packed.filter("doc_id IS NOT NULL"), F.xxhash64("doc_id", "_digest"))
    gone = looked_at.filter("NOT first").select("doc_id", "_digest")
    rest = split.filter("_may").join(gone, ["doc_id", "_digest"], "left_anti").dropDuplicates(["doc_id", "_digest"])
    return split.filter("NOT _may").select("row.*").unionByName(rest.select("row.*")).unionByName(packed.filter("doc_id IS NULL").select("row.*"))


def op3_weighted_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
