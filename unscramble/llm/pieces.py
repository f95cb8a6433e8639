"""SentencePiece encoding and decoding with weighted finite-state transducers.

The model file is compiled to three transducers: the normaliser (character map, spaces, dummy prefix), the pieces
with byte fallback (a trie whose accepting states give piece ids), and, for BPE models, an automaton over neighbouring
pieces that gives weight 0 to pairs which BPE itself would leave side by side and no path to all others. An input is
composed with them position by position and the tropical shortest path is taken. For a unigram model arcs weigh minus
the piece's score; for a BPE model one path is left, which is the library's segmentation.

The composition runs on chunks between places that no piece crosses, and equal chunks share one result. Decoding is the inverse transducer: pieces to bytes, bytes to text, dummy prefix taken off.
Null text is the empty text, which has no pieces.
"""

from __future__ import annotations

import math
import re
import struct
import zlib
from collections.abc import Iterable, Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.llm.chunks import ROOM, Memo, focus, parts_of
from unscramble.llm.common import ship_package, table, whole_text

MARK = "▁"
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6  # piece types of the model format


def _fields(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """Field numbers and values of a protocol-buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        value = shift = 0
        while True:
            b = data[at]
            at += 1
            value |= (b & 127) << shift
            shift += 7
            if b < 128:
                return value

    while at < len(data):
        tag = varint()
        match tag & 7:
            case 0:
                yield tag >> 3, varint()
            case 1:
                yield tag >> 3, data[at : at + 8]
                at += 8
            case 2:
                n = varint()
                yield tag >> 3, data[at : at + n]
                at += n
            case 5:
                yield tag >> 3, data[at : at + 4]
                at += 4
            case kind:
                raise ValueError(f"wire type {kind}")


class Normaliser:
    """A transducer from text to normal text: the longest key of the character map at each place, else one character.

    The map is a trie in the form of a double array of 32-bit units, and the strings that keys stand for. squeeze: runs of
    spaces become one and those at the ends go, after the map has been applied.
    """

    def __init__(self, charsmap: bytes, squeeze: bool):
        size = struct.unpack_from("<I", charsmap)[0] if charsmap else 0
        self.units = np.frombuffer(charsmap, "<u4", size // 4, 4).tolist() if charsmap else []
        self.strings, self.squeeze = charsmap[4 + size :], squeeze

    def longest(self, data: bytes, at: int) -> tuple[int, int]:
        """Length of the longest key that starts here (0 if none) and where its string starts."""
        units, length, found = self.units, 0, 0
        if not units:
            return 0, 0
        node = units[0] >> 10 << ((units[0] & 512) >> 6)
        for i in range(at, len(data)):
            node ^= data[i]
            unit = units[node]
            if unit & 0x800000FF != data[i]:
                break
            node ^= unit >> 10 << ((unit & 512) >> 6)
            if unit >> 8 & 1:
                length, found = i - at + 1, units[node] & 0x7FFFFFFF
        return length, found

    def __call__(self, text: str) -> str:
        data, out, at = text.encode("utf-8", "replace"), [], 0
        while at < len(data):
            n, found = self.longest(data, at)
            if n:
                out.append(self.strings[found : self.strings.index(0, found)])
            else:
                head = data[at]
                n = 1 if head < 0x80 else 2 if head < 0xE0 else 3 if head < 0xF0 else 4
                out.append(data[at : at + n])
            at += n
        normal = b"".join(out).decode("utf-8", "replace")
        return re.sub(" +", " ", normal).strip(" ") if self.squeeze else normal


def _states(ids: dict[str, int]) -> dict[str, int]:
    """States of the trie of pieces: each beginning of a piece, with the piece's id or -1 if it isn't one."""
    return {p[:i]: ids.get(p[:i], -1) for p in ids for i in range(1, len(p) + 1)}


class Transducer:
    """The compiled model."""

    def __init__(self, path: str):
        self.ids, self.scores, self.bytes, self.texts = {}, [], {}, []
        self.prefix, squeeze, self.kind, self.unknown, charsmap = True, True, 1, 0, b""
        for field, value in _fields(Path(path).read_bytes()):
            if field == 1:
                piece, score, kind = "", 0.0, NORMAL
                for f, v in _fields(value):
                    if f == 1:
                        piece = v.decode()
                    elif f == 2:
                        score = struct.unpack("<f", v)[0]
                    elif f == 3:
                        kind = v
                n = len(self.scores)
                if kind in (USER, UNUSED):
                    raise ValueError("user-defined and unused pieces are not compiled")
                if kind == NORMAL:
                    self.ids[piece] = n
                elif kind == BYTE:
                    self.bytes[int(piece[3:5], 16)] = n
                elif kind == UNKNOWN:
                    self.unknown = n
                self.scores.append(score)
                self.texts.append(bytes([int(piece[3:5], 16)]) if kind == BYTE else b"" if kind == CONTROL else b" \xe2\x81\x87 " if kind == UNKNOWN else piece.replace(MARK, " ").encode())
            elif field == 2:
                self.kind = next((v for f, v in _fields(value) if f == 3), 1)
            elif field == 3:
                spec = dict(_fields(value))
                charsmap, self.prefix, squeeze = spec.get(2, b""), bool(spec.get(3, 1)), bool(spec.get(4, 1))
        self.normal = Normaliser(charsmap, squeeze) if charsmap or squeeze else None
        if self.kind not in (1, 2):
            raise ValueError("the model must be unigram or BPE")
        self.longest = max(map(len, self.ids))
        if any(MARK in p.lstrip(MARK) for p in self.ids):
            raise ValueError("a piece crosses a space mark")
        #: Neighbouring characters inside pieces; no piece, and so no path's arc, spans any other two.
        self.joined = {p[i : i + 2] for p in self.ids for i in range(len(p) - 1)}
        self.apart = np.zeros((256, 256), bool)
        self.apart[:128, :128] = [[chr(a).replace(" ", MARK) + chr(b).replace(" ", MARK) not in self.joined for b in range(128)] for a in range(128)]
        self.apart = self.apart.ravel()
        self.heads = _states(self.ids)
        self.pairs: dict[str, dict[str, bool]] = {}  # of the automaton over neighbours, as far as it was asked for
        self.held = 0

    def merged(self, text: str) -> list[str]:
        """BPE by its rule: of all neighbours whose join is a piece, the highest score first, leftmost on ties."""
        parts = list(text)
        while True:
            best, at = -math.inf, -1
            for i in range(len(parts) - 1):
                n = self.ids.get(parts[i] + parts[i + 1])
                if n is not None and self.scores[n] > best:
                    best, at = self.scores[n], i
            if at < 0:
                return parts
            parts[at : at + 2] = [parts[at] + parts[at + 1]]

    def side_by_side(self, a: str, b: str) -> bool:
        """May b follow a? Weight 0 if so. a is empty at the start, where b must be a piece that merging reaches."""
        return self.merged(a + b) == ([a, b] if a else [b])

    def _only_path(self, chunk: str) -> list[str]:
        """The path that the automaton over neighbouring pieces leaves. Weights are 0, so a state that is reached is done."""
        n, state, pairs = len(chunk), self.heads.get, self.pairs
        last: list[str | None] = [None] * (n + 1)
        last[0] = ""
        for i in range(n):
            before = last[i]
            if before is None:
                continue
            known = pairs.get(before)
            if known is None:
                known = pairs[before] = {}
            for j in range(i + 1, n + 1):
                arc = chunk[i:j]
                piece = state(arc)
                if last[j] is None and (j == i + 1 or (piece is not None and piece >= 0)):
                    may = known.get(arc)
                    if may is None:
                        may = known[arc] = self.side_by_side(before, arc)
                        self.held += 1
                    if may:
                        last[j] = arc
                if piece is None:
                    break
            if last[n] is not None:
                break
        if self.held > 400_000:
            pairs.clear()
            self.held = 0
        out = []
        while n:
            out.append(last[n])
            n -= len(last[n])
        return out[::-1]

    def shortest_path(self, chunk: str) -> list[str]:
        """Pieces (or single characters for byte fallback) of the least total weight from start to end."""
        if self.kind == 2:
            return self._only_path(chunk)
        n = len(chunk)
        weight: list[float] = [math.inf] * (n + 1)
        last: list[str] = [""] * (n + 1)
        weight[0] = 0.0
        for i in range(n):
            if weight[i] == math.inf:
                continue
            for j in range(i + 1, min(n, i + self.longest) + 1):
                arc = chunk[i:j]
                piece = self.ids.get(arc)
                if piece is not None or j == i + 1:
                    cost = weight[i] + (-self.scores[piece] if piece is not None else 1e6)
                    if cost < weight[j]:
                        weight[j], last[j] = cost, arc
                if arc not in self.heads:
                    break
        out = []
        while n:
            out.append(last[n])
            n -= len(last[n])
        return out[::-1]

    def chunk_ids(self, chunk: str) -> bytes:
        ids: list[int] = []
        for arc in self.shortest_path(chunk):
            piece = self.ids.get(arc)
            if piece is not None:
                ids.append(piece)
            elif self.bytes:
                ids += [self.bytes[b] for b in arc.encode()]
            elif not ids or ids[-1] != self.unknown:
                ids.append(self.unknown)
        return np.asarray(ids, "<u4").tobytes()

    def segments(self, chunk: str) -> list[str]:
        """The chunk cut where no piece can span; paths through the parts are found apart."""
        if not self.bytes:
            return [chunk]  # neighbouring unknown characters make one piece
        cuts = [i for i in range(1, len(chunk)) if chunk[i - 1 : i + 1] not in self.joined]
        return [chunk[a:b] for a, b in zip([0, *cuts], [*cuts, len(chunk)], strict=True)]

    def cut(self, data: np.ndarray) -> np.ndarray:
        """The same for the bytes of whole texts, between ASCII characters only."""
        out = np.zeros(len(data), bool)
        if self.bytes and len(data) > 1:
            out[1:] = self.apart[data[:-1].astype(np.int32) * 256 + data[1:]]
        return out

    def byte_table(self) -> pa.Array:
        """The bytes that each id stands for."""
        if not hasattr(self, "_bytes"):
            self._bytes = pa.array(self.texts, pa.large_binary())
        return self._bytes

    def decode(self, ids: Iterable[int]) -> str:
        text = b"".join(map(self.texts.__getitem__, ids)).decode("utf-8", "replace")
        return text[1:] if self.prefix and text[:1] == " " else text


_MODELS: dict[str, tuple] = {}


def compiled(path: str) -> tuple[Transducer, Memo, Memo]:
    """One compiled model for each worker process, with memos of chunks and of chunks at the start of a text."""
    if path not in _MODELS:
        t = Transducer(path)
        segments = Memo(t.chunk_ids, ROOM // 2)

        def ask(chunk: str) -> bytes:
            marked = chunk.replace(" ", MARK)
            return segments[marked] if chunk.isascii() else b"".join([segments[x] for x in t.segments(marked)])

        first = Memo(lambda chunk: ask(" " + chunk if t.prefix else chunk), ROOM // 8)
        rest = Memo(ask, ROOM)
        _MODELS[path] = t, rest, first, lambda: (rest.clear(), first.clear(), segments.clear(), t.pairs.clear())
    focus(path, _MODELS[path][3])
    return _MODELS[path][:3]


def encode_blocks(texts: pa.Array | list[str], path: str) -> Iterator[tuple[np.ndarray, np.ndarray, pa.Array]]:
    """Blocks of consecutive texts: all their ids, where each text's ids start and, last, their number, and the texts.

    A text's first chunk has the dummy prefix before it. The texts that come out are normalised.
    """
    model, rest, first = compiled(path)
    if model.normal:
        texts = [model.normal(t) for t in (texts if isinstance(texts, list) else texts.to_pylist())]
    for chunks, starts, block in parts_of(texts, model.cut):
        coded = chunks.dictionary_encode()
        said, which = coded.dictionary.to_pylist(), np.asarray(coded.indices).astype(np.int64)
        head = np.zeros(len(chunks), bool)
        head[starts[:-1][np.diff(starts) > 0]] = True
        at_head, place = np.unique(which[head], return_inverse=True)
        values = [first[said[k]] for k in at_head.tolist()]
        used = np.zeros(len(said), bool)
        used[which[~head]] = True
        values += [rest[x] if u else b"" for x, u in zip(said, used.tolist(), strict=True)]
        which += len(at_head)
        which[head] = place
        if not len(chunks):
            yield np.zeros(0, "<u4"), np.zeros(len(starts), np.int64), block
            continue
        row = pa.array(values, pa.large_binary()).take(pa.array(which))
        yield np.frombuffer(row.buffers()[2] or b"", "<u4"), np.frombuffer(row.buffers()[1], np.int64)[starts] // 4, block


def encode(texts: pa.Array | list[str], path: str) -> Iterator[bytes]:
    """Ids of each text as little-endian unsigned 32-bit."""
    for ids, ends, _ in encode_blocks(texts, path):
        for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
            yield ids[a:b].tobytes()


def encode_documents(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, ids (array of int)."""
    ship_package(docs.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [np.frombuffer(x, "<u4").astype(np.int32) for x in encode(b.column("text"), path)]
            offsets = np.concatenate([[0], np.cumsum([len(x) for x in got])]).astype(np.int32)
            ids = pa.ListArray.from_arrays(offsets, np.concatenate(got) if got else np.zeros(0, np.int32))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), ids], ["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text")).mapInArrow(run, "doc_id long, ids array<int>")


def decode_documents(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id, text of rows (doc_id, ids)."""
    ship_package(encoded.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = compiled(path)[0]
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([model.decode(x or []) for x in b.column("ids").to_pylist()], pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def decode_blocks(model: Transducer, ids: np.ndarray, ends: np.ndarray) -> Iterator[bytes]:
    """The bytes of each text of a block: pieces to bytes, dummy prefix taken off."""
    row = model.byte_table().take(pa.array(ids.astype(np.int64)))
    data = np.frombuffer(row.buffers()[2] or b"", np.uint8)
    at = np.frombuffer(row.buffers()[1], np.int64)[ends] if len(ids) else np.zeros(len(ends), np.int64)
    for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        yield data[a + (model.prefix and b > a and data[a] == 32) : b].tobytes()


def op6_piece_transducer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: number and checksum of ids, and whether and how long the text is that comes back from them."""
    import public_tokenizers

    path = public_tokenizers.path("piece_bpe_32k.model")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = compiled(path)[0]
        for b in batches:
            rows = []
            for ids, ends, texts in encode_blocks(b.column("text"), path):
                texts = texts.cast(pa.large_binary()).to_pylist()
                for a, z, text, back in zip(ends[:-1].tolist(), ends[1:].tolist(), texts, decode_blocks(model, ids, ends), strict=True):
                    rows.append((z - a, zlib.crc32(ids[a:z]), back == text, len(back.decode("utf-8", "replace"))))
            cols = list(zip(*rows, strict=True)) or [[]] * 4
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.bool_(), pa.int64()), strict=True))], ["doc_id", "n_pieces", "ids_crc32", "round_trip", "decoded_chars"])

    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text"))
    return docs.mapInArrow(run, "doc_id long, n_pieces long, ids_crc32 long, round_trip boolean, decoded_chars long")
