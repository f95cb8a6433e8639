"""Exact tokenizer results from a memo of text chunks.

A chunk is a piece of text whose tokens do not depend on what stands around it. Natural text repeats few chunks very
often, so a block of texts is cut into chunks on its bytes, Arrow finds the distinct ones, the memo or else the library
answers for those, and Arrow puts the answers back in the order of the text.

A memo is bounded in bytes and in entries and keeps what is asked for often; long chunks are never kept.
"""

from __future__ import annotations

import contextlib
import ctypes
import gc
import os
import re
import struct
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

KEEP_CHARS, KEEP_CHUNKS = 48, 600_000
ROOM = 96 << 20  # bytes that a memo may hold, about
BLOCK = 8 << 20  # bytes of text that are cut together, about
#: What an entry of a memo takes beside its characters, about: objects of key and value, and their place in the table.
ENTRY = 200
#: A word with punctuation behind it: for tokenizers that split there and put all into lower case.
WORD = re.compile(r"[\t-\r ]*([A-Za-zÀ-ÖØ-öø-ÿ]+)([,.!?;:*#$%&|]*)")
#: A word right behind one tab or line end, which these tokenizers take apart.
LINE = re.compile(r"([\t-\r])([A-Za-zÀ-ÖØ-öø-ÿ]+)")


# --- memos ------------------------------------------------------------------------------------------------------

_focus: list = [None, lambda: None]


def focus(name: object, clear: Callable[[], None]) -> None:
    """Of all memos of a worker process only one is filled: the one before is emptied when another comes into use."""
    if _focus[0] != name:
        _focus[1]()
        give_back()
        _focus[:] = name, clear


def give_back() -> None:
    """Free memory of this process goes back to the system, where the C library and Arrow have a way to."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


class Memo(dict):
    """Answers found when first asked for, in two generations that together take about room bytes.

    When the young generation is full the old one goes, and the young one becomes the old one; what is asked for again
    comes back from there. So frequent chunks stay, and answers never depend on what is held.
    """

    def __init__(self, ask: Callable[[str], object], room: int = ROOM, limit: int = KEEP_CHUNKS):
        super().__init__()
        self.ask, self.room, self.limit = ask, room // 2, limit
        self.old: dict = {}
        self.held = 0

    def __missing__(self, chunk: str):
        value = self.old.get(chunk)
        if value is None:
            value = self.ask(chunk)
        if len(chunk) <= KEEP_CHARS:
            if self.held >= self.room or len(self) >= self.limit:
                self.old = self.copy()
                self.held = 0
                super().clear()
            self.held += ENTRY + 2 * len(chunk)
            self[chunk] = value
        return value

    def clear(self) -> None:
        super().clear()
        self.old, self.held = {}, 0


# --- cutting ----------------------------------------------------------------------------------------------------


def _among(*codes: int) -> np.ndarray:
    table = np.zeros(256, bool)
    table[list(codes)] = True
    return table


_SPACE = _among(9, 10, 11, 12, 13, 32)
#: Bytes behind which no run of white space may be cut: white space itself, and what some libraries take for it.
_SPACE_OR_LIKE = _among(9, 10, 11, 12, 13, 32, 0x1C, 0x1D, 0x1E, 0x1F)
_HEADS = _among(0xE1, 0xE2, 0xE3, 0xEF)  # the first byte of all three-byte characters that may be white space
_SECONDS = _among(0x80, 0x81, 0x9A, 0xA0, 0xBB)


def before_spaces(data: np.ndarray) -> np.ndarray:
    """Where a run of white space starts behind a character that surely isn't white space."""
    out = np.zeros(len(data), bool)
    if len(data) < 2:
        return out
    np.logical_and(_SPACE[data[1:]], ~_SPACE_OR_LIKE[data[:-1]], out=out[1:])
    at = np.flatnonzero(out)
    wide = at[data[at - 1] >= 0x80]  # few: the character before has several bytes
    two, three = data[np.maximum(wide - 2, 0)], data[np.maximum(wide - 3, 0)]
    out[wide[(two == 0xC2) | (_HEADS[three] & _SECONDS[two])]] = False
    return out


_LETTER = _among(*range(0x41, 0x5B), *range(0x61, 0x7B))
_STOP = _among(*b",.;:!?")


def before_spaces_and_stops(data: np.ndarray) -> np.ndarray:
    """Also where a stop follows a letter; for tokenizers that part letters from punctuation before all else."""
    out = before_spaces(data)
    if len(data) > 1:
        out[1:] |= _STOP[data[1:]] & _LETTER[data[:-1]]
    return out


def parts_of(texts: pa.Array | list[str], cut: Callable[[np.ndarray], np.ndarray]) -> Iterator[tuple[pa.Array, np.ndarray, pa.Array]]:
    """Blocks of consecutive texts as (chunks, for each text where its chunks start and, last, their number, texts)."""
    texts = pa.array(texts, pa.large_string()) if isinstance(texts, list) else texts.cast(pa.large_string())
    at = 0
    while at < len(texts):
        ends = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset + at : texts.offset + len(texts) + 1]
        n = max(1, int(np.searchsorted(ends, ends[0] + BLOCK, "right")) - 1)
        ends = ends[: n + 1]
        data = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]]
        edge = np.append(cut(data), True)
        edge[ends - ends[0]] = True
        edges = np.flatnonzero(edge)
        if len(data):
            chunks = pa.Array.from_buffers(pa.large_string(), len(edges) - 1, [None, pa.py_buffer(edges.astype(np.int64)), pa.py_buffer(data)])
        else:
            chunks = pa.array([], pa.large_string())
        yield chunks, np.searchsorted(edges, ends - ends[0]), texts.slice(at, n)
        at += n


def answers(chunks: pa.Array, get: Callable[[str], object]) -> tuple[list, pa.Array]:
    """What get says of each distinct chunk, and for each chunk which of these it is."""
    coded = chunks.dictionary_encode()
    return list(map(get, coded.dictionary.to_pylist())), coded.indices


def sums(chunks: pa.Array, starts: np.ndarray, get: Callable[[str], int]) -> list[int]:
    """For each text the sum over its chunks."""
    said, which = answers(chunks, get)
    total = np.concatenate([[0], np.cumsum(np.array(said, np.int64)[np.asarray(which)])]) if said else np.zeros(1, np.int64)
    return np.diff(total[starts]).tolist()


def joined(chunks: pa.Array, starts: np.ndarray, get: Callable[[str], bytes]) -> tuple[np.ndarray, np.ndarray]:
    """All chunks' bytes one after the other, and where those of each text start and, last, their number."""
    said, which = answers(chunks, get)
    if not said:
        return np.zeros(0, np.uint8), np.zeros(len(starts), np.int64)
    row = pa.array(said, pa.large_binary()).take(which)
    return np.frombuffer(row.buffers()[2] or b"", np.uint8), np.frombuffer(row.buffers()[1], np.int64)[starts]


# --- tokenizers -------------------------------------------------------------------------------------------------

#: One word of letters that normalisers leave alone, for each kind of memo: the library's model can be asked directly.
PLAIN = {"count": re.compile(r" ?[A-Za-zÀ-ÖØ-öø-ÿ]+"), "bytes": re.compile(r"[a-zß-öø-ÿ]+")}

_TOOLS: dict = {}


def _byte_letters() -> dict[int, str]:
    """How byte-level tokenizers write the UTF-8 bytes of a code point below 256: visible bytes as themselves, others from U+0100 on."""
    visible = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    hidden = [b for b in range(256) if b not in visible]
    letters = {b: chr(b) for b in visible} | {b: chr(256 + i) for i, b in enumerate(hidden)}
    return {c: "".join(letters[b] for b in chr(c).encode()) for c in range(256)}


BYTE_LETTERS = _byte_letters()


def tokenizer(path: str):
    from tokenizers import Tokenizer

    if path not in _TOOLS:
        t = Tokenizer.from_file(path)
        t.no_truncation()
        t.no_padding()
        _TOOLS[path] = t
    return _TOOLS[path]


def cuts(path: str) -> Callable[[np.ndarray], np.ndarray]:
    """Where texts may be cut for this tokenizer: behind letters too, unless one of its special strings goes on there."""
    if (path, "cuts") not in _TOOLS:
        special = [str(x.content).encode() for x in tokenizer(path).get_added_tokens_decoder().values()]
        inside = any(before_spaces_and_stops(np.frombuffer(x, np.uint8)).any() for x in special)
        _TOOLS[path, "cuts"] = before_spaces if inside else before_spaces_and_stops
    return _TOOLS[path, "cuts"]


def memo(path: str, kind: str) -> Memo:
    """kind: 'count' or 'bytes' (little-endian unsigned 32-bit ids). One memo for each worker process."""
    if (path, kind) not in _TOOLS:
        t = tokenizer(path)
        gc.set_threshold(200_000, 20, 50)  # the memo holds no cycles, and walking it often costs more than all else

        plain, model = PLAIN[kind].fullmatch, t.model
        number = struct.Struct("<I").pack

        def of(text: str):
            if plain(text):
                got = model.tokenize(text.translate(BYTE_LETTERS))
                return len(got) if kind == "count" else b"".join([number(y.id) for y in got])
            got = t.encode_batch_fast([text], add_special_tokens=False)[0]
            return len(got) if kind == "count" else np.asarray(got.ids, "<u4").tobytes()

        parts = Memo(of, ROOM // 4)

        def ids_in_parts(text: str) -> bytes:
            if not (f := WORD.fullmatch(text)):
                return parts[text]
            return parts[f[1].lower()] + parts[f[2]] if f[2] else parts[f[1].lower()]

        def count_in_parts(text: str) -> int:
            return of(f[1]) + of(f[2]) if (f := LINE.fullmatch(text)) else of(text)

        _TOOLS[path, kind] = Memo(count_in_parts if kind == "count" else ids_in_parts, ROOM)
        _TOOLS[path, kind, "clear"] = lambda: (_TOOLS[path, kind].clear(), parts.clear())
    focus((path, kind), _TOOLS[path, kind, "clear"])
    return _TOOLS[path, kind]


def blocks(texts: list[str], chars: int = 1 << 18) -> Iterable[list[str]]:
    """Consecutive texts, together of about so many characters."""
    block, size = [], 0
    for t in texts:
        block.append(t)
        size += len(t)
        if size >= chars:
            yield block
            block, size = [], 0
    if block:
        yield block


def count_ids(texts: pa.Array | list[str], path: str) -> list[int]:
    """Numbers of ids by the library; for tokenizers whose pre-tokens never hold white space after other characters."""
    get = memo(path, "count").__getitem__
    return [n for chunks, starts, _ in parts_of(texts, cuts(path)) for n in sums(chunks, starts, get)]


def id_bytes(texts: pa.Array | list[str], path: str) -> Iterator[bytes]:
    """Ids by the library, for tokenizers that drop white space; each text's as little-endian unsigned 32-bit."""
    get = memo(path, "bytes").__getitem__
    for chunks, starts, _ in parts_of(texts, cuts(path)):
        data, ends = joined(chunks, starts, get)
        for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
            yield data[a:b].tobytes()
