"""WARC archives: a writer with revisit records, and a splittable reader.

Archives are files of gzip members, one record each. The reader lists files and sizes, gives every task a byte range,
and looks for the gzip magic in it; a candidate counts as a member only if it inflates and starts with a WARC version
line whose headers can be read. A task owns the records that start inside its range and reads past the end of the range
for the last one, so that ranges can be cut anywhere and a lost task is just run again.

Of records with equal payloads of at least LEAST bytes those with the smallest page_id are responses, the others
revisit it and carry no payload; smaller payloads are always responses. Digest and length of the full payload stand in
the headers. Null html is an empty payload; null urls are empty. Rows with equal page_id and payload are all written,
and all are responses if that page_id is the smallest. Rows without page_id count as larger than all others.

Files are written and read by the executors with Arrow's file systems (local and shared folders, HDFS, object stores).
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.llm.common import partitions, scratch_path, ship_package, table

LEAST = 100
RANGE = 4 << 20  # bytes of an archive that a task reads by default
MAGIC = b"\x1f\x8b\x08"
STEP = 1 << 16
VERSION = b"WARC/1."


def _at(path: str) -> tuple[pafs.FileSystem, str]:
    if path.startswith("/"):
        return pafs.LocalFileSystem(), path
    if path.startswith("file:"):
        return pafs.LocalFileSystem(), "/" + path.removeprefix("file:").lstrip("/")
    return pafs.FileSystem.from_uri(path)


# --- records ----------------------------------------------------------------------------------------------------


def record(kind: str, url: str, page_id: int | None, payload: bytes, digest: str, size: int, refers_to: int | None) -> bytes:
    """One gzip member. A revisit's block is empty; X- headers are extension fields, as the format allows."""
    named = "" if page_id is None else str(page_id)
    head = [
        "WARC/1.1",
        f"WARC-Type: {kind}",
        f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{named} {url} {digest}')}>",
        "WARC-Date: 2000-01-01T00:00:00Z",
        f"WARC-Target-URI: {''.join(c for c in url if c >= ' ')}",
        f"WARC-Payload-Digest: sha256:{digest}",
        f"X-Page-Id: {named}",
        f"X-Payload-Bytes: {size}",
        "Content-Type: text/html; charset=utf-8",
    ]
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"X-Refers-To-Page-Id: {refers_to}"]
    block = b"" if kind == "revisit" else payload
    head.append(f"Content-Length: {len(block)}")
    squeeze = zlib.compressobj(6, zlib.DEFLATED, 31)
    return squeeze.compress("\r\n".join(head).encode("utf-8", "surrogatepass") + b"\r\n\r\n" + block + b"\r\n\r\n") + squeeze.flush()


def parse(data: bytes) -> tuple[dict[str, str], bytes]:
    head, _, rest = data.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "replace").split("\r\n")
    if not head.startswith(VERSION) or any(": " not in x and not x.endswith(":") for x in lines[1:]):
        raise ValueError("not a record")
    headers = dict(x.split(":", 1) for x in lines[1:])
    headers = {k.lower(): v.strip() for k, v in headers.items()}
    block = rest[: int(headers["content-length"])]
    if len(block) != int(headers["content-length"]):
        raise ValueError("short record")
    return headers, block


# --- writing ----------------------------------------------------------------------------------------------------


def with_kinds(pages: DataFrame, least: int = LEAST) -> DataFrame:
    """page_id, url, payload, payload_bytes, payload_digest, record_type, refers_to."""
    known = pages.select(
        F.col("page_id").cast("long").alias("page_id"),
        F.coalesce("url", F.lit("")).alias("url"),
        F.encode(F.coalesce("html", F.lit("")), "UTF-8").alias("payload"),
    )
    known = known.withColumn("payload_bytes", F.octet_length("payload").cast("long")).withColumn("payload_digest", F.sha2("payload", 256))
    small = known.select("page_id", "payload_digest", "payload_bytes").filter(F.col("payload_bytes") >= least)
    firsts = small.groupBy("payload_digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n"))
    firsts = firsts.filter("n > 1 AND first IS NOT NULL").drop("n")
    # only digests meet by digest; payloads are dealt by page and digest, so that copies of one payload stay apart
    again = small.join(firsts, "payload_digest").filter(~F.col("page_id").eqNullSafe(F.col("first")))
    again = again.groupBy(F.col("page_id").alias("_page"), F.col("payload_digest").alias("_digest")).agg(F.min("first").alias("first"))
    joined = known.join(again, F.col("page_id").eqNullSafe(F.col("_page")) & (F.col("payload_digest") == F.col("_digest")), "left")
    return joined.select(
        "page_id", "url", "payload", "payload_bytes", "payload_digest",
        F.when(F.col("first").isNotNull(), "revisit").otherwise("response").alias("record_type"),
        F.col("first").alias("refers_to"),
    )


def write(pages: DataFrame, path: str, least: int = LEAST) -> list[str]:
    """Write archives below path; the names of the files. Attempts write files of their own, and only reported files count."""

    ship_package(pages.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = _at(path)
        out, name, size = None, "", 0
        for b in batches:
            if b.num_rows and out is None:
                fs.create_dir(base, recursive=True)
                name = f"part-{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex}.warc.gz"
                out = fs.open_output_stream(f"{base}/{name}", compression=None)
            columns = [b.column(c) for c in ("record_type", "url", "page_id", "payload", "payload_digest", "payload_bytes", "refers_to")]
            for row in zip(*columns, strict=True):  # one payload at a time becomes a Python object
                data = record(*(x.as_py() for x in row))
                out.write(data)
                size += len(data)
        if out is not None:
            out.close()
            yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([size], pa.int64())], ["name", "bytes"])

    rows = with_kinds(pages, least).select("record_type", "url", "page_id", "payload", "payload_digest", "payload_bytes", "refers_to")
    return [r["name"] for r in rows.mapInArrow(run, "name string, bytes long").collect()]


# --- reading ----------------------------------------------------------------------------------------------------


def members(f, start: int, end: int, size: int) -> Iterator[tuple[int, dict[str, str], bytes]]:
    """(offset, headers, block) of the records that start in [start, end)."""
    at, buffer, base = start, b"", start
    while at < end:
        if at - base >= len(buffer) - len(MAGIC) and base + len(buffer) < size:
            f.seek(at)
            buffer, base = f.read(STEP), at
        found = buffer.find(MAGIC, at - base)
        if found < 0:
            if base + len(buffer) >= min(size, end + len(MAGIC)):
                return
            at = base + max(len(buffer) - len(MAGIC) + 1, at - base)
            f.seek(at)
            buffer, base = f.read(STEP), at
            continue
        at = base + found
        if at >= end:
            return
        got = _member(f, at, buffer[found:])
        if got is None:
            at += 1
        else:
            length, headers, block = got
            yield at, headers, block
            at += length
            if at - base > len(buffer):
                f.seek(at)
                buffer, base = f.read(STEP), at


def _member(f, at: int, head: bytes) -> tuple[int, dict[str, str], bytes] | None:
    """The member at this offset, if it is one: its compressed length, headers and block."""
    inflate = zlib.decompressobj(31)
    parts, taken, data, seen = [], 0, head, b""
    f.seek(at + len(head))
    try:
        while True:
            got = inflate.decompress(data)
            taken += len(data)
            parts.append(got)
            if len(seen) < len(VERSION):
                seen += got[: len(VERSION)]
                if not VERSION.startswith(seen[: len(VERSION)]):
                    return None  # seen early, so that false candidates cost little
            if inflate.eof:
                return taken - len(inflate.unused_data), *parse(b"".join(parts))
            data = f.read(STEP)
            if not data:
                return None
    except (zlib.error, ValueError, KeyError):
        return None


RECORD = "file string, offset long, page_id long, url string, record_type string, payload binary, payload_bytes long, payload_digest string, refers_to long, intact boolean"


def byte_ranges(spark: SparkSession, path: str, names: list[str] | None, span: int) -> DataFrame:
    """name, start, stop, size: a row for each range. The driver lists files; executors count the ranges out."""
    fs, base = _at(path)
    infos = fs.get_file_info([f"{base}/{n}" for n in names]) if names is not None else fs.get_file_info(pafs.FileSelector(base, allow_not_found=True))
    files = [(i.base_name, i.size) for i in infos if i.is_file and i.size and i.base_name.endswith(".warc.gz")]
    total = sum(-(-size // span) for _, size in files)
    starts = F.explode(F.sequence(F.lit(0).cast("long"), F.col("size") - 1, F.lit(span).cast("long")))
    ranges = spark.createDataFrame(files, "name string, size long").select("name", starts.alias("start"), "size")
    ranges = ranges.select("name", "start", F.least(F.col("start") + span, "size").alias("stop"), "size")
    return ranges.repartition(max(1, min(total, 4 * partitions(spark))), "name", "start")


def read(spark: SparkSession, path: str, names: list[str] | None = None, span: int = RANGE, payloads: bool = True) -> DataFrame:
    """All records of the archives below path (or of the files named). intact: the payload has the digest of its header.

    Without payloads every record is still read and checked whole, but its payload is not handed on.
    """
    ship_package(spark)
    tasks = byte_ranges(spark, path, names, span)
    kept = [x.split() for x in RECORD.split(", ") if payloads or x != "payload binary"]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = _at(path)
        kinds = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary(), "boolean": pa.bool_()}
        number = lambda s: int(s) if s else None
        rows: dict[str, list] = {name: [] for name, _ in kept}
        held = 0

        def out() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array(rows[name], kinds[kind]) for name, kind in kept], [name for name, _ in kept])
            for column in rows.values():
                column.clear()
            return batch

        for b in batches:
            for name, start, stop, size in zip(*(b.column(c).to_pylist() for c in ("name", "start", "stop", "size")), strict=True):
                with fs.open_input_file(f"{base}/{name}") as f:
                    for at, h, block in members(f, start, stop, size):
                        digest = h.get("warc-payload-digest", "").removeprefix("sha256:")
                        kind = h.get("warc-type", "")
                        intact = kind == "revisit" or hashlib.sha256(block).hexdigest() == digest
                        n = len(block) if kind == "response" else number(h.get("x-payload-bytes", ""))
                        record = (name, at, number(h.get("x-page-id", "")), h.get("warc-target-uri", ""), kind, block, n, digest, number(h.get("x-refers-to-page-id", "")), intact)
                        for (field, _), value in zip(RECORD_FIELDS, record, strict=True):
                            if field in rows:
                                rows[field].append(value)
                        held += 256 + len(block) * payloads
                        if held > 4 << 20:
                            yield out()
                            held = 0
        yield out()

    return tasks.mapInArrow(run, ", ".join(" ".join(x) for x in kept))


RECORD_FIELDS = [tuple(x.split()) for x in RECORD.split(", ")]


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch_path(spark, "warc")
    names = write(table(spark, sf_dir, "pages").select("page_id", "url", "html"), path)
    got = read(spark, path, names, payloads=False)
    return got.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "intact")


OP8_SQL = """
WITH p AS (
  SELECT page_id, encode(coalesce(html, '')) AS payload FROM pages
), d AS (
  SELECT page_id, CAST(octet_length(payload) AS BIGINT) AS payload_bytes, sha256(payload) AS payload_digest FROM p
), f AS (
  SELECT *, CASE WHEN payload_bytes >= 100 THEN min(page_id) OVER (PARTITION BY payload_digest) ELSE page_id END AS first FROM d
)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id <> first THEN first END AS refers_to, true AS intact
FROM f
"""
