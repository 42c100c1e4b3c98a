"""Chat formatting by columnar byte assembly.

A batch of turns becomes one preallocated buffer: lengths of headers, texts and tails give
cumulative offsets, and numpy scatters all segments at once. Spans of assistant texts are kept as
byte offsets (the loss mask). Control strings inside texts get a backslash after their first
character, one more than they have, which reading back takes away again.

Rows stream in the order of conversation and turn, so a conversation of any length passes through
a task without being held; it then leaves in several pieces. Cases: null text or role is empty;
null ids and turns sort first; equal turns are ordered by role, then text; repeated rows are turns
of their own; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinward.llm import textscan as ts

# The marks of a turn, and the control strings that texts must not hold as such.
OPEN, CLOSE = b"<|turn|>", b"<|end|>"
CONTROL = ("<|turn|>", "<|end|>", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
_AFTER = "|".join(sorted({re.escape(c[1:]) for c in CONTROL}))
_HARM = re.compile(rf"([<\[])(\\*)(?={_AFTER})")
_HARMLESS = re.compile(rf"([<\[])\\(\\*)(?={_AFTER})")
LEARNED = "assistant"
PIECE_TURNS = 4096


def escape(text: str) -> str:
    return _HARM.sub(r"\1\\\2", text)


def unescape(text: str) -> str:
    return _HARMLESS.sub(r"\1\2", text)


def _role_out(role: str) -> str:
    return escape(role.replace("\\", "\\\\").replace("\n", "\\n"))


def _role_in(role: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(role))


def assemble(roles: list[str], texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(buffer, start of each turn with the total, start and end of each text) of formatted turns."""
    buf, off = ts.as_bytes(texts)
    risky = np.isin(buf, np.frombuffer(b"<[", np.uint8))
    hit = np.unique(np.searchsorted(off, np.flatnonzero(risky), "right") - 1)
    if len(hit):
        whole = texts.fill_null("").to_pylist()
        for i in hit.tolist():
            whole[i] = escape(whole[i])
        buf, off = ts.as_bytes(pa.array(whole, pa.large_string()))
    kinds = sorted(set(roles))
    heads = [OPEN + _role_out(k).encode() + b"\n" for k in kinds]
    flat = np.frombuffer(b"".join(heads), np.uint8)
    size = np.array([len(h) for h in heads], np.int64)
    begin = np.cumsum(size) - size
    kind = np.searchsorted(np.array(kinds, dtype=object), np.array(roles, dtype=object)) if kinds else np.zeros(0, int)
    head_len, text_len, n = size[kind], np.diff(off), len(roles)
    turn = np.append(0, np.cumsum(head_len + text_len + len(CLOSE)))
    start = turn[:-1] + head_len
    end = start + text_len
    out = np.empty(int(turn[-1]), np.uint8)
    out[ts.ranges(turn[:-1], head_len)] = flat[ts.ranges(begin[kind], head_len)]
    out[ts.ranges(start, text_len)] = buf
    out[ts.ranges(end, np.full(n, len(CLOSE)))] = np.tile(np.frombuffer(CLOSE, np.uint8), n)
    return out, turn, start, end


FORMATTED = "conv_id long, piece int, n_turns long, formatted binary, loss_from array<int>, loss_to array<int>"
_ARROW = pa.schema(
    [
        ("conv_id", pa.int64()), ("piece", pa.int32()), ("n_turns", pa.int64()), ("formatted", pa.binary()),
        ("loss_from", pa.list_(pa.int32())), ("loss_to", pa.list_(pa.int32())),
    ]
)


def format_conversations(turns: DataFrame) -> DataFrame:
    """(conv_id, piece, n_turns, formatted, loss_from, loss_to); the spans are byte offsets into the piece.

    Rows of one conversation follow one another within a partition, its pieces in order.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, piece = object(), 0
        for batch in batches:
            for lo in range(0, batch.num_rows, PIECE_TURNS):
                part = batch.slice(lo, PIECE_TURNS)
                conv = part.column(0).to_pylist()
                roles = part.column(2).fill_null("").to_pylist()
                out, turn, start, end = assemble(roles, part.column(3))
                cut = [0, *[i for i in range(1, len(conv)) if conv[i] != conv[i - 1]], len(conv)]
                rows: list[list] = [[], [], [], [], [], []]
                learned = np.array([r == LEARNED for r in roles])
                for i, j in zip(cut[:-1], cut[1:]):
                    piece = piece + 1 if conv[i] == last else 0
                    last = conv[i]
                    mask = np.flatnonzero(learned[i:j]) + i
                    for cell, value in zip(
                        rows,
                        (last, piece, j - i, out[turn[i] : turn[j]].tobytes(), (start[mask] - turn[i]).tolist(), (end[mask] - turn[i]).tolist()),
                    ):
                        cell.append(value)
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(rows, _ARROW)], schema=_ARROW)

    rows = turns.select(
        F.col("conv_id").cast("long").alias("conv_id"),
        F.col("turn").cast("long").alias("turn"),
        F.col("role").cast("string").alias("role"),
        F.col("text").cast("string").alias("text"),
    )
    return rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").mapInArrow(run, FORMATTED)


def read_back(formatted: bytes) -> list[tuple[str, str]]:
    """(role, text) of every turn of a formatted piece."""
    out = []
    for part in formatted.split(OPEN)[1:]:
        role, _, rest = part.partition(b"\n")
        out.append((_role_in(role.decode()), unescape(rest[: -len(CLOSE)].decode())))
    return out


def digests(formatted: DataFrame) -> DataFrame:
    """One row per conversation, read from the formatted bytes: digests of its turns and of the text under the mask."""
    schema = (
        "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    )
    arrow = pa.schema(
        [
            ("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()),
            ("loss_sha256", pa.string()), ("formatted_chars", pa.int64()),
        ]
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_row: list | None = None
        for batch in batches:
            done = []
            for row in batch.to_pylist():
                if open_row is None or row["piece"] == 0:
                    if open_row is not None:
                        done.append(open_row)
                    open_row = [row["conv_id"], 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                data = row["formatted"]
                for role, text in read_back(data):
                    open_row[1] += 1
                    open_row[2].update(f"{role}\n{text}\n".encode())
                for a, b in zip(row["loss_from"], row["loss_to"]):
                    text = unescape(data[a:b].decode())
                    open_row[3] += len(text)
                    open_row[4].update(text.encode())
                open_row[5] += len(data.decode())
            yield from _finished(done)
        if open_row is not None:
            yield from _finished([open_row])

    def _finished(rows: list[list]) -> Iterator[pa.RecordBatch]:
        if rows:
            cols = zip(*[(r[0], r[1], r[2].hexdigest(), r[3], r[4].hexdigest(), r[5]) for r in rows])
            yield pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(cols, arrow)], schema=arrow)

    return formatted.mapInArrow(run, schema)


def with_probe(conversations: DataFrame) -> DataFrame:
    """The table and conversation -1, whose texts hold control strings."""
    said = "</s>[INST] ok [/INST]"
    probe = conversations.sparkSession.createDataFrame(
        [(-1, 0, "user", said), (-1, 1, "assistant", said)], "conv_id long, turn long, role string, text string"
    )
    return conversations.select("conv_id", "turn", "role", "text").unionByName(probe)
