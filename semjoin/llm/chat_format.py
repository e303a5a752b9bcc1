"""Chat formatting by columnar byte assembly, reading back included.

A turn becomes ``<|role|>`` newline text ``</s>`` newline.  In roles and texts every character that a
control string (``<|``, ``|>``, ``<s>``, ``</s>``, ``[INST]``, ``[/INST]``, ``<<SYS>>``, ``<</SYS>>``) can begin or end
with, and the backslash, becomes a backslash and a letter (``ESCAPES``); so no such character is left in
them, all that are there are the template's, and every text comes back unchanged.  For a batch of turns the lengths of all segments give cumulative offsets; headers and
contents are scattered into one preallocated buffer, which becomes the Arrow column as it is.

A conversation comes out as pieces, in order, each of whole turns: one for each batch that it
spans, so a conversation of any length needs the memory of one batch.

Defined cases: null role or text is empty; turns are ordered by turn, then role and text (null
first), so equal turn numbers have one order; rows that repeat are turns of their own; rows with a
null conversation id are one conversation; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import buffer, ranges, strings

# Fixed values of the template.
OPEN, CLOSE, END = b"<|", b"|>\n", b"</s>\n"
ESCAPES = {"\\": "\\\\", "<": "\\l", ">": "\\g", "|": "\\p", "[": "\\o", "]": "\\c"}
LOSS_ROLE = "assistant"

_ESCAPED = re.compile(r"\\(.)", re.S)
_PLAIN = {made[1]: c for c, made in ESCAPES.items()}
_NONE = -(1 << 63)


def escape(column: pa.Array) -> pa.Array:
    for c, made in ESCAPES.items():  # the backslash is the first
        column = pc.replace_substring(column, c, made)
    return column


def unescape(text: str) -> str:
    return _ESCAPED.sub(lambda m: _PLAIN[m[1]], text) if "\\" in text else text


def assemble(role: pa.Array, text: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """All turns in one buffer: bytes, offsets of the turns, begin and end of their contents."""
    role_data, role_at = buffer(escape(role))
    text_data, text_at = buffer(escape(text))
    n_role, n_text = np.diff(role_at), np.diff(text_at)
    size = n_role + n_text + len(OPEN) + len(CLOSE) + len(END)
    at = np.concatenate([[0], np.cumsum(size)])
    out = np.empty(at[-1], np.uint8)
    begin = at[:-1] + len(OPEN) + n_role + len(CLOSE)
    end = begin + n_text
    for where, fixed in ((at[:-1], OPEN), (begin - len(CLOSE), CLOSE), (end, END)):
        out[where[:, None] + np.arange(len(fixed))] = np.frombuffer(fixed, np.uint8)
    out[ranges(at[:-1] + len(OPEN), n_role)] = role_data
    out[ranges(begin, n_text)] = text_data
    return out, at, begin, end


PIECES = "conv_id bigint, piece bigint, formatted string, loss array<struct<begin:int,stop:int>>"


def _format(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    last, piece = None, 0
    for batch in batches:
        for lo in range(0, batch.num_rows, 2000):
            rows = batch.slice(lo, 2000)
            role, text = strings(rows.column(1)), strings(rows.column(2))
            data, at, begin, end = assemble(role, text)
            conv = np.asarray(pc.fill_null(rows.column(0), _NONE))
            first = np.flatnonzero(np.r_[True, conv[1:] != conv[:-1]])
            stop = np.r_[first[1:], len(conv)]
            pieces = np.zeros(len(first), np.int64)
            if conv[first[0]] == last:
                piece += 1
                pieces[0] = piece
            if len(first) > 1 or conv[first[0]] != last:
                piece = pieces[-1]
            last = conv[-1]
            texts = pa.Array.from_buffers(pa.large_string(), len(first), [None, pa.py_buffer(np.ascontiguousarray(at[np.r_[first, stop[-1]]])), pa.py_buffer(data)]).cast(pa.string())
            trained = np.asarray(pc.equal(role, LOSS_ROLE))
            of = np.repeat(np.arange(len(first)), stop - first)[trained]
            base = at[first][of]
            spans = pa.StructArray.from_arrays([pa.array((begin[trained] - base).astype(np.int32)), pa.array((end[trained] - base).astype(np.int32))], ["begin", "stop"])
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(np.bincount(of, minlength=len(first)))]).astype(np.int32)), spans)
            yield pa.RecordBatch.from_arrays([rows.column(0).take(pa.array(first)), pa.array(pieces), texts, lists], ["conv_id", "piece", "formatted", "loss"])


def format_chats(turns: DataFrame) -> DataFrame:
    """(conv_id, piece, formatted, loss): loss spans are byte ranges of the piece's escaped assistant texts."""
    rows = turns.select(F.col("conv_id").cast("long").alias("conv_id"), "role", "text", "turn")
    order = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return order.select("conv_id", "role", "text").mapInArrow(_format, PIECES)


def parse(formatted: str) -> Iterator[tuple[str, str]]:
    """The turns (role, text) of a formatted piece."""
    at = 0
    while at < len(formatted):
        at += len(OPEN)
        stop = formatted.index("|>", at)
        role, at = formatted[at:stop], stop + len(CLOSE)
        stop = formatted.index("</s>", at)
        yield unescape(role), unescape(formatted[at:stop])
        at = stop + len(END)


class _Digest:
    def __init__(self):
        self.turns = self.loss = self.chars = 0
        self.all, self.masked = hashlib.sha256(), hashlib.sha256()

    def add(self, formatted: str, loss: list[dict]) -> None:
        for role, text in parse(formatted):
            self.turns += 1
            self.all.update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
        raw = formatted.encode("utf-8", "surrogatepass")
        for s in loss:
            text = unescape(raw[s["begin"] : s["stop"]].decode("utf-8", "surrogatepass"))
            self.loss += len(text)
            self.masked.update(text.encode("utf-8", "surrogatepass"))
        self.chars += len(formatted)

    def row(self, conv):
        return conv, self.turns, self.all.hexdigest(), self.loss, self.masked.hexdigest(), self.chars


DIGESTS = "conv_id bigint, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint"


def _read(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = [x.split()[0] for x in DIGESTS.split(", ")]
    types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
    conv, state = None, None

    def made(rows):
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows), types)], names)

    for batch in batches:
        done = []
        for c, text, loss in zip(*(batch.column(i).to_pylist() for i in (0, 2, 3))):
            if state is None or c != conv:
                if state is not None:
                    done.append(state.row(conv))
                conv, state = c, _Digest()
            state.add(text, loss)
        if done:
            yield made(done)
    if state is not None:
        yield made([state.row(conv)])


def read_back(pieces: DataFrame) -> DataFrame:
    """Digests of what the formatted pieces hold, in the order that ``format_chats`` gives them."""
    return pieces.mapInArrow(_read, DIGESTS)
