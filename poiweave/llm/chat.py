r"""Chat formatting by columnar byte assembly.

Rows are dealt by conversation and sorted; each batch is formatted as a whole: segment lengths, their running
sums and scatter indices are numpy arrays, and all headers and contents are copied into one
buffer, of which Arrow takes slices. A conversation larger than ``PIECE_BYTES`` goes out in several
pieces, so memory stays bounded however long it is.

Template: ``<|im_start|>role\ntext<|im_end|>\n``. Inside roles and texts every ``<``, backslashes, ``|``
gets one more backslash, which reading takes away, so no text can form a control string.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textkit import byte_chunks

START, END = b"<|im_start|>", b"<|im_end|>\n"
PIECE_BYTES = 4 << 20
FORMATTED = "conv_id long, piece int, formatted string, loss array<struct<start:int,end:int>>"
DIGEST = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def escape(values: pa.Array) -> pa.Array:
    return pc.replace_substring_regex(values, pattern=r"<(\\*)\|", replacement=r"<\\\1|")


def unescape(text: str) -> str:
    return re.sub(r"<\\(\\*)\|", r"<\1|", text)


def _escape_role(values: pa.Array) -> pa.Array:
    return escape(pc.replace_substring(pc.replace_substring(values, "\\", "\\\\"), "\n", "\\n"))


def _unescape_role(text: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(text))


def _flat(values: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all strings in one array, and their lengths."""
    values = values.cast(pa.large_binary())
    offsets = np.frombuffer(values.buffers()[1], np.int64)[values.offset : values.offset + len(values) + 1]
    data = values.buffers()[2]
    flat = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None and len(values) else np.empty(0, np.uint8)
    return flat, np.diff(offsets)


def assemble(roles: pa.Array, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The buffer of all turns, where each turn starts (one more entry), and where its text starts and ends."""
    role, role_n = _flat(_escape_role(pc.fill_null(roles, "")))
    text, text_n = _flat(escape(pc.fill_null(texts, "")))
    head, newline, tail = (np.frombuffer(x, np.uint8) for x in (START, b"\n", END))
    n = len(role_n)
    lengths = np.empty((n, 5), np.int64)
    lengths[:] = len(head), 0, 1, 0, len(tail)
    lengths[:, 1], lengths[:, 3] = role_n, text_n
    ends = np.cumsum(lengths).reshape(n, 5) if n else np.zeros((0, 5), np.int64)
    starts = ends - lengths
    buffer = np.empty(int(ends[-1, -1]) if n else 0, np.uint8)
    for k, fixed in ((0, head), (2, newline), (4, tail)):
        buffer[(starts[:, k, None] + np.arange(len(fixed))).ravel()] = np.tile(fixed, n)
    for k, flat, size in ((1, role, role_n), (3, text, text_n)):
        shift = starts[:, k] - (np.cumsum(size) - size)
        buffer[np.arange(len(flat)) + np.repeat(shift, size)] = flat
    return buffer, np.append(starts[:, 0], len(buffer)), starts[:, 3], ends[:, 3]


def _pieces(rows: pa.RecordBatch, done: int) -> pa.RecordBatch:
    """Formatted pieces of sorted rows. done: pieces that the first conversation already has."""
    ids = rows.column(0)
    n = len(ids)
    key, null = pc.fill_null(ids, 0).to_numpy(zero_copy_only=False), pc.is_null(ids).to_numpy(zero_copy_only=False)
    new = np.append(True, (key[1:] != key[:-1]) | (null[1:] != null[:-1]))
    first = np.flatnonzero(new)
    buffer, turn, begin, end = assemble(rows.column(1), rows.column(2))
    points = np.concatenate(([0], np.cumsum((buffer & 0xC0) != 0x80)))  # code points before each byte
    bounds = np.append(turn[first], len(buffer))
    formatted = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(first), [None, pa.py_buffer(bounds.astype(np.int64)), pa.py_buffer(buffer)]).cast(pa.large_string()).cast(pa.string())
    mine = pc.equal(pc.fill_null(rows.column(1), ""), "assistant").to_numpy(zero_copy_only=False)
    origin = points[bounds[:-1]][np.cumsum(new) - 1]
    spans = pa.StructArray.from_arrays([pa.array((points[x] - origin)[mine].astype(np.int32)) for x in (begin, end)], names=["start", "end"])
    held = np.concatenate(([0], np.cumsum(mine)))[np.append(first, n)]
    piece = np.zeros(len(first), np.int32)
    piece[:1] = done
    return pa.RecordBatch.from_arrays([ids.take(pa.array(first)).cast(pa.int64()), pa.array(piece), formatted, pa.ListArray.from_arrays(pa.array(held.astype(np.int32)), spans)], names=["conv_id", "piece", "formatted", "loss"])


def _format(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Streams sorted rows; the last conversation of a chunk waits for its further rows, unless it is a piece by itself."""
    waiting: pa.RecordBatch | None = None
    sent: tuple[int | None, int] | None = None  # a conversation that is out in part, and its pieces so far

    def out(rows: pa.RecordBatch) -> pa.RecordBatch:
        return _pieces(rows, sent[1] if sent and sent[0] == rows.column(0)[0].as_py() else 0)

    for whole in batches:
        for rows in byte_chunks(whole, "text"):
            if waiting is not None:
                rows = pa.Table.from_batches([waiting, rows]).combine_chunks().to_batches()[0]
            ids = rows.column(0)
            last = ids[len(ids) - 1].as_py()
            same = pc.is_null(ids) if last is None else pc.fill_null(pc.equal(ids, last), False)
            cut = int(np.argmax(same.to_numpy(zero_copy_only=False)))
            if cut:
                yield out(rows.slice(0, cut))
            waiting = rows.slice(cut)
            if waiting.get_total_buffer_size() > PIECE_BYTES and pc.sum(pc.binary_length(waiting.column(2))).as_py() > PIECE_BYTES:
                yield out(waiting)
                sent, waiting = (last, sent[1] + 1 if sent and sent[0] == last else 1), None
    if waiting is not None:
        yield out(waiting)


def format_conversations(conversations: DataFrame) -> DataFrame:
    """conv_id, piece, formatted, loss (code point spans of assistant texts in ``formatted``), a row for each piece.

    Turns go by turn, then role, then text, nulls first, so ties and repeated rows have one order. Null
    roles and texts are empty; rows without conv_id make one conversation without id. Extra columns are ignored; an
    empty table gives no rows.
    """
    rows = conversations.select(F.col("conv_id").cast("long"), F.col("role").cast("string"), F.col("text").cast("string"), "turn")
    rows = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", F.coalesce("role", F.lit("")), F.coalesce("text", F.lit("")))
    return rows.select("conv_id", "role", "text").mapInArrow(_format, FORMATTED)


def read_back(formatted: str, spans: list[dict]) -> tuple[list[tuple[str, str]], list[str]]:
    """Turns and masked texts of one formatted piece."""
    turns = []
    for part in formatted.split(END.decode())[:-1]:
        role, _, text = part.removeprefix(START.decode()).partition("\n")
        turns.append((_unescape_role(role), unescape(text)))
    return turns, [unescape(formatted[x["start"] : x["end"]]) for x in spans]


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Digests of sorted pieces; only hashes and sums are kept of an open conversation."""
    open_: list | None = None

    def row() -> list:
        conv, n, turns, chars, loss, size = open_
        return [conv, n, turns.hexdigest(), chars, loss.hexdigest(), size]

    for b in batches:
        made = []
        for x in b.to_pylist():
            if x["piece"] == 0:
                if open_:
                    made.append(row())
                open_ = [x["conv_id"], 0, hashlib.sha256(), 0, hashlib.sha256(), 0]
            turns, masked = read_back(x["formatted"], x["loss"])
            open_[1] += len(turns)
            open_[2].update("".join(f"{r}\n{t}\n" for r, t in turns).encode())
            text = "".join(masked)
            open_[3] += len(text)
            open_[4].update(text.encode())
            open_[5] += len(x["formatted"])
        yield _rows(made)
    if open_:
        yield _rows([row()])


def _rows(made: list[list]) -> pa.RecordBatch:
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
    return pa.RecordBatch.from_arrays([pa.array([m[k] for m in made], kind) for k, kind in enumerate(kinds)], names=[c.split()[0] for c in DIGEST.split(", ")])


def digest_formatted(formatted: DataFrame) -> DataFrame:
    """Digests per conversation, read back from pieces in the order in which ``format_conversations`` gives them."""
    return formatted.mapInArrow(_digest, DIGEST)
