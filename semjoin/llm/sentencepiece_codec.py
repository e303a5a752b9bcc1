"""SentencePiece models on the tokenizers library: encoding, decoding and a parity check.

The model's protobuf is parsed here; from it come the normaliser, the metaspace marker, the
pieces with their scores (unigram, or for BPE the merges that the scores order) and byte
fallback.  Where no piece has the marker behind another character - checked on loading - a
text falls apart at its spaces without any effect on the ids, so each distinct chunk (spaces
and what follows) is encoded once, many in one multithreaded batch.  Parity with the sentencepiece
library itself is verified for every chunk (for models without a dummy prefix, or that strip spaces, for
every text).  Ids are always those of this backend; what differs is counted in ``n_differ``, and with
``strict`` it raises ``ParityError``.  Decoding is the tokenizers library's decoder.

Defined cases: null text is an empty text, without ids; bytes without a piece fall back to
byte pieces; rows that repeat an id, and rows with a null id, are encoded each on their own; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import os
import re
import struct
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import buffer, ranges, slices

MODEL = "piece_bpe_32k.model"
MARK = "\u2581"
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6  # fixed values of the format
UNIGRAM, BPE = 1, 2


class ParityError(RuntimeError):
    """The tokenizers backend and the sentencepiece library give different ids."""


def model_path(name: str = MODEL) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def fields(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """(number, value) of a protobuf message; 32- and 64-bit values stay bytes."""

    def varint(at: int) -> tuple[int, int]:
        value = shift = 0
        while True:
            b = data[at]
            value |= (b & 127) << shift
            at, shift = at + 1, shift + 7
            if b < 128:
                return value, at

    at = 0
    while at < len(data):
        tag, at = varint(at)
        kind = tag & 7
        if kind == 0:
            value, at = varint(at)
        else:
            size = {1: 8, 5: 4}.get(kind)
            if size is None:
                size, at = varint(at)
            value, at = data[at : at + size], at + size
        yield tag >> 3, value


@dataclass
class Model:
    pieces: list[tuple[str, float, int]] = field(default_factory=list)
    kind: int = UNIGRAM
    byte_fallback: bool = False
    charsmap: bytes = b""
    dummy_prefix: bool = True
    remove_extra: bool = True

    @classmethod
    def read(cls, path: str) -> Model:
        with open(path, "rb") as f:
            data = f.read()
        m = cls()
        for number, value in fields(data):
            if number == 1:
                piece, score, kind = "", 0.0, NORMAL
                for n, v in fields(value):
                    if n == 1:
                        piece = v.decode()
                    elif n == 2:
                        score = struct.unpack("<f", v)[0]
                    elif n == 3:
                        kind = v
                m.pieces.append((piece, score, kind))
            elif number == 2:
                spec = dict(fields(value))
                m.kind, m.byte_fallback = spec.get(3, UNIGRAM), bool(spec.get(35, 0))
            elif number == 3:
                spec = dict(fields(value))
                m.charsmap, m.dummy_prefix, m.remove_extra = spec.get(2, b""), bool(spec.get(3, 1)), bool(spec.get(4, 1))
        return m

    @property
    def separable(self) -> bool:
        """Whether no piece has the marker behind another character."""
        return not any(re.search(f"[^{MARK}]{MARK}", p) for p, _, kind in self.pieces if kind in (NORMAL, USER))

    def tokenizer(self):
        """A tokenizers object for texts whose spaces are markers already."""
        from tokenizers import Tokenizer, models

        unknown = next((i for i, p in enumerate(self.pieces) if p[2] == UNKNOWN), 0)
        if self.kind == UNIGRAM:
            vocab = [(p, s if kind in (NORMAL, USER) else -1e9) for p, s, kind in self.pieces]
            return Tokenizer(models.Unigram(vocab, unk_id=unknown, byte_fallback=self.byte_fallback))
        vocab = {p: i for i, (p, _, _) in enumerate(self.pieces)}
        plain = {p: s for p, s, kind in self.pieces if kind in (NORMAL, USER)}
        merges = []
        for p, s in plain.items():
            merges += [(-s, vocab[p[:i]], vocab[p[i:]], p[:i], p[i:]) for i in range(1, len(p)) if p[:i] in plain and p[i:] in plain]
        merges.sort()
        return Tokenizer(models.BPE(vocab, [m[3:] for m in merges], unk_token=self.pieces[unknown][0], fuse_unk=True, byte_fallback=self.byte_fallback))


class Codec:
    MOST = 300_000  # chunks remembered from slice to slice; only memory depends on it
    _made: dict[str, Codec] = {}

    def __init__(self, path: str):
        import sentencepiece

        self.model = Model.read(path)
        self.inner = self.model.tokenizer()
        self.reference = sentencepiece.SentencePieceProcessor(model_file=path)
        self.normalizer = None
        if self.model.charsmap:
            from tokenizers import normalizers

            self.normalizer = normalizers.Precompiled(self.model.charsmap)
        self.separable = self.model.separable
        raw = [bytes([int(p[3:5], 16)]) if kind == BYTE else b"" if kind in (CONTROL, UNKNOWN) else p.replace(MARK, " ").encode() for p, _, kind in self.model.pieces]
        self.raw = raw
        self.is_byte = np.array([kind == BYTE for _, _, kind in self.model.pieces])
        self.plain = np.array([kind not in (CONTROL, UNKNOWN) for _, _, kind in self.model.pieces])
        self.by_chunk = self.separable and self.model.dummy_prefix and not self.model.remove_extra and not self.normalizer
        from tokenizers import decoders

        steps = [decoders.Replace(MARK, " "), decoders.ByteFallback(), decoders.Fuse()]
        leading = 1 << 20 if self.model.remove_extra else int(self.model.dummy_prefix)  # spaces that encoding put there or would take away
        self.inner.decoder = decoders.Sequence([*steps, decoders.Strip(" ", leading, 0)])
        self.forget()

    @classmethod
    def of(cls, path: str) -> Codec:
        if path not in cls._made:
            cls._made[path] = cls(path)
        return cls._made[path]

    def forget(self) -> None:
        self.known: dict[str, int] = {}
        self.at, self.ids = np.zeros(1, np.int64), np.zeros(0, np.int32)
        self.same, self.differ = np.zeros(0, bool), np.zeros(0, bool)

    def normalised(self, text: str) -> str:
        """The text as the model sees it, before the dummy prefix and the marker."""
        if self.normalizer:
            text = self.normalizer.normalize_str(text)
        if self.model.remove_extra:
            text = re.sub(" {2,}", " ", text).lstrip(" ").rstrip(f" {MARK}")  # at the end a marker of the text counts as a space
        return text

    def _learn(self, chunks: list[str]) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "true"
        found = [e.ids for e in self.inner.encode_batch_fast([c.replace(" ", MARK) for c in chunks], add_special_tokens=False)]
        differ = np.zeros(len(chunks), bool)
        if self.by_chunk:
            differ[:] = [ids != mine and len(c) > 1 for c, ids, mine in zip(chunks, self.reference.encode([c[1:] for c in chunks]), found)]
        size = np.fromiter(map(len, found), np.int64, len(found))
        self.known.update(zip(chunks, range(len(self.known), len(self.known) + len(chunks))))
        self.at = np.concatenate([self.at, self.at[-1] + np.cumsum(size)])
        self.ids = np.concatenate([self.ids, np.fromiter((x for ids in found for x in ids), np.int32, int(size.sum()))])
        raw = self.raw
        same = [b"".join([raw[x] for x in ids]) == c.encode() for ids, c in zip(found, chunks)]
        self.same, self.differ = np.concatenate([self.same, np.array(same, bool)]), np.concatenate([self.differ, differ])

    def encode(self, col: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Flat ids, each text's offsets, whether it decodes to what went in, chunks that differed from the reference."""
        given = col
        if self.normalizer or self.model.remove_extra:
            col = pa.array([self.normalised(t) for t in col.to_pylist()], pa.large_string())
        data, at = buffer(col)
        size = np.diff(at)
        some = size > 0
        pad = np.cumsum(some) if self.model.dummy_prefix else np.zeros(len(size), np.int64)
        new_at = at.copy()
        new_at[1:] += pad
        out = np.full(new_at[-1], 32, np.uint8)
        inner = ranges(new_at[1:] - size, size)
        out[inner] = data
        space = out == 32
        cut = np.zeros(len(out), bool)
        if self.separable:
            cut[1:] = space[1:] & ~space[:-1]
            mark = (out[:-3] == 0xE2) & (out[1:-2] == 0x96) & (out[2:-1] == 0x81)  # a marker in the text itself joins what follows
            cut[3:] &= ~mark
        cut[new_at[:-1][some]] = True
        begin = np.flatnonzero(cut)
        chunks = pa.Array.from_buffers(pa.large_string(), len(begin), [None, pa.py_buffer(np.r_[begin, len(out)].astype(np.int64)), pa.py_buffer(out)])
        coded = chunks.dictionary_encode()
        words = coded.dictionary.to_pylist()
        if len(self.known) > self.MOST:
            self.forget()
        if new := [x for x in words if x not in self.known]:
            self._learn(new)
        entry = np.fromiter(map(self.known.__getitem__, words), np.int64, len(words))[np.asarray(coded.indices)] if words else np.zeros(0, np.int64)
        n = np.diff(self.at)[entry]
        ids = self.ids[ranges(self.at[entry], n)]
        docs = np.searchsorted(begin, new_at)
        ends = np.concatenate([[0], np.cumsum(n)])
        bad = np.concatenate([[0], np.cumsum(~self.same[entry])])
        differ = np.concatenate([[0], np.cumsum(self.differ[entry])])
        differ = np.diff(differ[docs])
        if not self.by_chunk:
            at = ends[docs]
            wanted = self.reference.encode(given.to_pylist())
            differ = np.array([ids[a:b].tolist() != w for a, b, w in zip(at.tolist(), at[1:].tolist(), wanted)], np.int64)
        return ids, ends[docs], np.diff(bad[docs]) == 0, differ

    def decode(self, ids: Iterable[int]) -> str:
        return self.inner.decode([i for i in ids if self.plain[i]], skip_special_tokens=False)


def _run(path: str, with_ids: bool, strict: bool):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec.of(path)
        for batch in batches:
            for rows, col in slices(batch):
                ids, at, same, differ = codec.encode(col)
                if strict and differ.any():
                    raise ParityError(f"{int((differ > 0).sum())} texts of a slice have other ids in the sentencepiece library")
                little = np.ascontiguousarray(ids.astype("<i4"))
                digests = [hashlib.sha256(little[a:b]).hexdigest() for a, b in zip(at[:-1].tolist(), at[1:].tolist())]
                byte = np.concatenate([[0], np.cumsum(codec.is_byte[ids])])
                out = [rows.column(0), pa.array(np.diff(at)), pa.array(np.diff(byte[at])), pa.array(digests, pa.string()), pa.array(same), pa.array(differ.astype(np.int64))]
                names = [rows.schema.names[0], "n_tokens", "n_byte_tokens", "ids_sha256", "round_trip", "n_differ"]
                if with_ids:
                    out.append(pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(ids)))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(out, names)

    return run


def encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, with_ids: bool = False, strict: bool = False) -> DataFrame:
    """Ids of every whole text, as digests and (``with_ids``) themselves; one scan, no shuffle."""
    rows = docs.select(F.col(id_col), F.col(text_col).alias("text"))
    kind = rows.schema[0].dataType.simpleString()
    schema = f"`{id_col}` {kind}, n_tokens bigint, n_byte_tokens bigint, ids_sha256 string, round_trip boolean, n_differ bigint" + (", ids array<int>" if with_ids else "")
    return rows.mapInArrow(_run(path or model_path(), with_ids, strict), schema)


def decode(encoded: DataFrame, ids_col: str = "ids", path: str | None = None) -> DataFrame:
    """Adds ``decoded``, the text of each row's ids; null ids give null."""
    where = path or model_path()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec.of(where)
        for batch in batches:
            texts = [None if x is None else codec.decode(x) for x in batch.column(batch.schema.get_field_index(ids_col)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string())], [*batch.schema.names, "decoded"])

    return encoded.mapInArrow(run, encoded.withColumn("decoded", F.lit("")).schema)
