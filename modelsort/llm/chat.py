"""Chat formatting by columnar byte assembly, with its exact reader.

A turn becomes ``<|turn|>ROLE<|text|>TEXT<|end|>\\n``. In roles and texts a
``<`` that stands before ``|`` or a backslash gets a backslash after it; so no
mark can occur in them, and taking the backslash after ``<`` away restores them.
A batch is laid out in numpy: segment lengths, cumulative offsets and scatter
indices, then marks and contents are copied into one buffer that Arrow takes over.

A conversation is cut into pieces by turn number, so that one conversation with
a large share of all turns spreads over many tasks. Pieces in order give its text.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from modelsort.llm.bytetext import blocks, row_sums, utf8_view

TURN, TEXT, END = b"<|turn|>", b"<|text|>", b"<|end|>\n"
LOSS_ROLE = "assistant"
#: Turn numbers that one piece of a conversation spans.
PIECE_TURNS = 256

PIECE = pa.schema([
    ("conv_id", pa.int64()), ("block", pa.int64()), ("piece", pa.int64()), ("n_turns", pa.int64()), ("formatted", pa.string()),
    ("loss_spans", pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))),
])
PIECE_DDL = "conv_id long, block long, piece long, n_turns long, formatted string, loss_spans array<struct<start:long,stop:long>>"
BACK_DDL = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def _escapes(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Bytes after which a backslash goes."""
    mask = np.zeros(len(data), bool)
    if len(data):
        mask[:-1] = (data[:-1] == 60) & ((data[1:] == 124) | (data[1:] == 92))
        mask[offsets[1:][offsets[1:] > 0] - 1] = False
    return mask


def _scatter(out: np.ndarray, at: np.ndarray, data: np.ndarray, offsets: np.ndarray, mask: np.ndarray) -> None:
    """Copy each row's bytes to ``out`` from ``at`` on, with its escapes."""
    if not len(data):
        return
    extra = np.cumsum(mask) - mask
    rows = np.flatnonzero(np.diff(offsets))
    shift = (at - offsets[:-1])[rows] - extra[offsets[:-1][rows]]
    where = np.repeat(shift, np.diff(offsets)[rows]) + np.arange(len(data)) + extra
    out[where] = data
    out[where[mask] + 1] = 92


def assemble(roles: pa.Array, texts: pa.Array, loss_role: str = LOSS_ROLE) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Formatted bytes of all turns, turn offsets in them, and the offsets of texts and their ends."""
    role, role_at = utf8_view(roles)
    text, text_at = utf8_view(texts)
    role_mask, text_mask = _escapes(role, role_at), _escapes(text, text_at)
    lengths = np.empty((len(role_at) - 1, 5), np.int64)
    lengths[:, 0], lengths[:, 2], lengths[:, 4] = len(TURN), len(TEXT), len(END)
    lengths[:, 1] = np.diff(role_at) + row_sums(role_mask, role_at)
    lengths[:, 3] = np.diff(text_at) + row_sums(text_mask, text_at)
    ends = np.cumsum(lengths.ravel()).reshape(-1, 5)
    starts = ends - lengths
    out = np.empty(int(ends[-1, -1]) if len(ends) else 0, np.uint8)
    for column, mark in ((0, TURN), (2, TEXT), (4, END)):
        out[starts[:, column][:, None] + np.arange(len(mark))] = np.frombuffer(mark, np.uint8)
    _scatter(out, starts[:, 1], role, role_at, role_mask)
    _scatter(out, starts[:, 3], text, text_at, text_mask)
    return out, np.append(starts[:, 0], len(out)), starts[:, 3], ends[:, 3]


def _pieces(batch: pa.RecordBatch, last: tuple | None, loss_role: str) -> tuple[pa.RecordBatch, tuple]:
    """Pieces of sorted turns; one that goes on from the batch before takes the next piece number."""
    out, turn_at, text_from, text_to = assemble(batch.column("role"), batch.column("text"), loss_role)
    conv, block = batch.column("conv_id"), batch.column("block")
    keys = list(zip(conv.to_pylist(), block.to_pylist(), strict=True))
    cuts = [0, *(i for i in range(1, len(keys)) if keys[i] != keys[i - 1]), len(keys)]
    chars = np.concatenate([[0], np.cumsum((out & 0xC0) != 0x80)])
    loss = pc.fill_null(pc.equal(batch.column("role"), loss_role), False).to_numpy(zero_copy_only=False)
    rows: dict[str, list] = {f.name: [] for f in PIECE if f.name != "formatted"}
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        number = last[1] + 1 if last and last[0] == keys[a] else 0
        last = (keys[a], number)
        base = chars[turn_at[a]]
        spans = [{"start": int(chars[text_from[i]] - base), "stop": int(chars[text_to[i]] - base)} for i in range(a, b) if loss[i]]
        for name, value in zip(rows, (*keys[a], number, b - a, spans), strict=True):
            rows[name].append(value)
    offsets = turn_at[cuts].astype(np.int32)
    formatted = pa.StringArray.from_buffers(len(cuts) - 1, pa.py_buffer(offsets), pa.py_buffer(out))
    columns = {**{k: pa.array(v, PIECE.field(k).type) for k, v in rows.items()}, "formatted": formatted}
    return pa.RecordBatch.from_arrays([columns[f.name] for f in PIECE], schema=PIECE), last


def format_conversations(turns: DataFrame, loss_role: str = LOSS_ROLE) -> DataFrame:
    """Pieces ``conv_id, block, piece, n_turns, formatted, loss_spans`` of every conversation.

    Ordered by block, then piece, they give the conversation; ``loss_spans`` are
    code points within ``formatted`` of the texts that are trained on. Turns go by
    number (null first), ties by role, then text, repeated rows stay. Null roles
    and texts are empty; turns without ``conv_id`` form one conversation of null id.
    """
    rows = turns.select(
        F.col("conv_id").cast("long").alias("conv_id"),
        F.floor(F.col("turn") / PIECE_TURNS).cast("long").alias("block"),
        "turn",
        F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"),
        F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = None
        for batch in batches:
            _, offsets = utf8_view(batch.column("text"))
            for a, b in blocks(offsets, 16 << 20):
                out, last = _pieces(batch.slice(a, b - a), last, loss_role)
                yield out

    return rows.repartition("conv_id", "block").sortWithinPartitions("conv_id", "block", "turn", "role", "text").mapInArrow(run, PIECE_DDL)


def unescape(text: str) -> str:
    return text.replace("<\\", "<")


def parse(formatted: str) -> list[tuple[str, str]]:
    """Roles and texts of formatted turns."""
    turns = formatted.split(TURN.decode())[1:]
    found = []
    for turn in turns:
        role, rest = turn.split(TEXT.decode())
        text, tail = rest.split(END.decode())
        if tail:
            raise ValueError("text between turns")
        found.append((unescape(role), unescape(text)))
    return found


def read_back(pieces: DataFrame) -> DataFrame:
    """Per conversation, what its formatted pieces hold: turns, their digest, and the text under the loss mask.

    Pieces stream through in order, so a task holds one piece at a time.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state, done = None, []

        def close() -> None:
            if state:
                conv, n, turns, chars, loss, size = state
                done.append({"conv_id": conv, "n_turns": n, "turns_sha256": turns.hexdigest(), "loss_chars": chars, "loss_sha256": loss.hexdigest(), "formatted_chars": size})

        schema = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])
        for batch in batches:
            for conv, formatted, spans in zip(batch.column("conv_id").to_pylist(), batch.column("formatted"), batch.column("loss_spans").to_pylist(), strict=True):
                formatted = formatted.as_py()
                if state is None or state[0] != conv:
                    close()
                    state = [conv, 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                for role, text in parse(formatted):
                    state[1] += 1
                    state[2].update(f"{role}\n{text}\n".encode())
                for span in spans:
                    text = unescape(formatted[span["start"] : span["stop"]])
                    state[3] += len(text)
                    state[4].update(text.encode())
                state[5] += len(formatted)
            if len(done) >= 1024:
                yield pa.RecordBatch.from_pylist(done, schema)
                done.clear()
        close()
        if done:
            yield pa.RecordBatch.from_pylist(done, schema)

    return pieces.select("conv_id", "block", "piece", "formatted", "loss_spans").repartition("conv_id").sortWithinPartitions("conv_id", "block", "piece").mapInArrow(run, BACK_DDL)
