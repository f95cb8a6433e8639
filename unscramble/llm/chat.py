"""Chat formatting in windows of a token budget.

A conversation's turns, in order of turn, become training examples: windows of whole turns. Prefix sums of the turns'
token counts choose each window's span: as many new turns as fit beside the system turn, which windows keep, and a
limited history of the turns just before, which is repeated. The loss mask covers assistant texts of new turns only, so
every assistant text is a target exactly once. Token counts are those of whole formatted turns. The budget comes first:
where a turn leaves no room for the system turn it stands without, and only a turn that alone exceeds the budget makes
a window that does, in which it is alone.

The template writes ``<|im_start|>role`` + line end + text + ``<|im_end|>`` + line end. Control strings inside texts
are broken up by a backslash behind their first character and backslashes are doubled, so that no text can hold a
control string and every text can be read back. Roles are percent-encoded.

Null text and null role are empty. Rows of a conversation with equal turn go by role and text. Conversations stream
through a task in order and are never held whole; rows without conv_id form one conversation.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator
from urllib.parse import quote, unquote

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.llm import chunks
from unscramble.llm.common import partitions, ship_package, table

BUDGET, HISTORY = 1024, 256
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"
#: Strings that tokenizers or templates treat as control marks.
CONTROL = (OPEN, CLOSE, "<|endoftext|>", "<|startoftext|>", "<s>", "</s>", "<unk>", "<pad>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")

_CONTROL = re.compile("|".join(map(re.escape, CONTROL)))
_ESCAPED = re.compile(r"\\(\\?)")


def escape(text: str) -> str:
    text = text.replace("\\", "\\\\")
    return _CONTROL.sub(lambda m: f"{m[0][0]}\\{m[0][1:]}", text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text)


def render(role: str, text: str) -> tuple[str, int, int]:
    """A formatted turn, and where its text starts and ends in it."""
    head = f"{OPEN}{quote(role, safe='')}\n"
    body = escape(text)
    return f"{head}{body}{CLOSE}\n", len(head), len(head) + len(body)


_TURN = re.compile(rf"{re.escape(OPEN)}([^\n]*)\n(.*?){re.escape(CLOSE)}\n", re.S)


def read_back(text: str) -> list[tuple[str, str]]:
    """(role, text) of every turn of a formatted window."""
    return [(unquote(m[1]), unescape(m[2])) for m in _TURN.finditer(text)]


class Windows:
    """One conversation's windows; turns are added in order and whole windows come out."""

    def __init__(self, budget: int, history: int):
        self.budget, self.history = budget, history
        self.system: tuple | None = None
        self.recent: list[tuple] = []  # turns that the next window may repeat, latest last
        self.new: list[tuple] = []
        self.before: list[tuple] = []  # repeated turns of the open window
        self.sum, self.n, self.number = 0, 0, 0

    def add(self, role: str, text: str, tokens: int) -> Iterator[dict]:
        turn = (role, text, tokens)
        if self.n == 0 and role == "system":
            self.system = turn
        if self.new and self.sum + tokens > self.budget:
            yield self.close()
        if not self.new:
            self.begin(tokens)
        self.new.append(turn)
        self.sum += tokens
        self.n += 1

    def begin(self, tokens: int) -> None:
        """Repeat the system turn and as much history as leaves room for the next turn."""
        self.before = []
        keeps = bool(self.system and self.number and self.system[2] + tokens <= self.budget)
        self.sum = self.system[2] if keeps else 0
        room = min(self.history, self.budget - self.sum - tokens)
        for turn in reversed(self.recent):
            if turn[2] > room:
                break
            room -= turn[2]
            self.sum += turn[2]
            self.before.insert(0, turn)
        if keeps:
            self.before.insert(0, self.system)

    def close(self) -> dict:
        parts, spans, at = [], [], 0
        for k, (role, text, _) in enumerate(self.before + self.new):
            part, start, end = render(role, text)
            if role == "assistant" and k >= len(self.before):
                spans.append((at + start, at + end))
            parts.append(part)
            at += len(part)
        out = {"window": self.number, "text": "".join(parts), "loss": spans, "n_repeated": len(self.before), "n_new": len(self.new), "n_tokens": self.sum}
        self.recent = self._last([t for t in self.recent + self.new if t is not self.system])
        self.new, self.number = [], self.number + 1
        return out


    def _last(self, turns: list[tuple]) -> list[tuple]:
        """The last turns that together are no longer than the history."""
        room, n = self.history, 0
        for turn in reversed(turns):
            room -= turn[2]
            if room < 0:
                break
            n += 1
        return turns[len(turns) - n :]


WINDOW = "conv_id long, window int, text string, loss array<struct<start: int, end: int>>, n_repeated int, n_new int, n_tokens long"


def format_conversations(turns: DataFrame, tokenizer_path: str, budget: int = BUDGET, history: int = HISTORY) -> DataFrame:
    """Windows of all conversations, those of one conversation next to each other and in order."""
    ship_package(turns.sparkSession)
    arrow = pa.schema([("conv_id", pa.int64()), ("window", pa.int32()), ("text", pa.string()), ("loss", pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))), ("n_repeated", pa.int32()), ("n_new", pa.int32()), ("n_tokens", pa.int64())])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, conv, out = None, object(), []

        def put(windows: Iterable[dict]) -> None:
            out.extend(w | {"conv_id": conv, "loss": [{"start": a, "end": b} for a, b in w["loss"]]} for w in windows)

        for b in batches:
            cols = [b.column(c).to_pylist() for c in ("conv_id", "role", "text")]
            sizes = chunks.count_ids([render(r, t)[0] for r, t in zip(cols[1], cols[2], strict=True)], tokenizer_path)
            for c, role, text, n in zip(*cols, sizes, strict=True):
                if c != conv:
                    if state:
                        put([state.close()])
                    state, conv = Windows(budget, history), c
                put(state.add(role, text, n))
                if len(out) >= 500:
                    yield pa.RecordBatch.from_pylist(out, arrow)
                    out.clear()
        if state:
            put([state.close()])
        if out:
            yield pa.RecordBatch.from_pylist(out, arrow)

    rows = turns.select(F.col("conv_id").cast("long").alias("conv_id"), "turn", *[F.coalesce(F.col(c).cast("string"), F.lit("")).alias(c) for c in ("role", "text")])
    laid = rows.repartition(partitions(turns.sparkSession), "conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return laid.mapInArrow(run, WINDOW)


DIGEST = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_windows long, n_repeated long"


def digests(windows: DataFrame) -> DataFrame:
    """What can be read back from windows, which must be in the order that format_conversations gives."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        conv, acc = object(), None

        def row() -> tuple:
            return conv, acc[0], acc[1].hexdigest(), acc[2], acc[3].hexdigest(), acc[4], acc[5], acc[6]

        kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.int64())
        names = [x.split()[0] for x in DIGEST.split(", ")]
        batch = lambda rows: pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows, strict=True)) or [[]] * 8, kinds, strict=True)], names)
        for b in batches:
            out = []
            for w in b.to_pylist():
                if w["conv_id"] != conv:
                    if acc:
                        out.append(row())
                    conv, acc = w["conv_id"], [0, hashlib.sha256(), 0, hashlib.sha256(), 0, 0, 0]
                for role, text in read_back(w["text"])[w["n_repeated"] :]:
                    acc[0] += 1
                    acc[1].update(f"{role}\n{text}\n".encode())
                for span in w["loss"]:
                    target = unescape(w["text"][span["start"] : span["end"]])
                    acc[2] += len(target)
                    acc[3].update(target.encode())
                acc[4] += len(w["text"])
                acc[5] += 1
                acc[6] += w["n_repeated"]
            yield batch(out)
        if acc:
            yield batch([row()])

    return windows.mapInArrow(run, DIGEST)


def op5_chat_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    said = "</s>[INST] ok [/INST]"
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    extra = spark.sql(f"SELECT * FROM VALUES (-7L, 0L, 'user', '{said}'), (-7L, 1L, 'assistant', '{said}') AS t(conv_id, turn, role, text)")
    return digests(format_conversations(turns.unionByName(extra), public_tokenizers.path("byte_bpe_50k.json")))
