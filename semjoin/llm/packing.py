"""Best-fit-decreasing packing of tokenised documents into fixed windows.

Documents are tokenised, closed by an end id and, where longer than the window,
first cut into full windows; what is left of each is packed best-fit-decreasing.

Only lengths matter to that, and there are at most ``window`` of them.  So the plan is
made on the histogram of lengths (a bounded table, counted over all pieces): bins that
hold the same lengths are one group, and a segment tree over remaining capacities finds
the tightest open group.  This gives bin for bin what placing pieces one by one gives.
Pieces then take their places by their rank among pieces of their length; ranks come
from per-task counters and a running sum over tasks, so no length gathers in one task.

Defined cases: null text is an empty text (the end id alone); an empty table gives no
pieces; repeated ids are separate documents; other columns are ignored.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .scratch import Scratch, small_batches
from .words import Words, buffer, ranges, slices, split, tidy

WINDOW = 4096
END = 2
VOCABULARY = "word_bpe_49k.json"
PIECES = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, part int, place bigint"

_tokenizers: dict[str, object] = {}


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


SEPARATOR = "\x01"
_CLASS = np.zeros(256, np.int8)  # 1: ASCII letters, 2: ASCII digits and signs, 0: what may belong to either side
_CLASS[[c for c in range(0x21, 0x7F) if c != 0x27]] = 2
_CLASS[[c for c in range(0x21, 0x7F) if chr(c).isalpha()]] = 1


def chunks(w: Words) -> Words:
    """Words cut between ASCII letters and ASCII signs or digits, where no token spans either; never at an apostrophe."""
    kind = _CLASS[w.data]
    cut = np.zeros(len(kind), bool)
    cut[1:] = kind[1:] * kind[:-1] == 2
    cut[w.at[:-1]] = True
    at = np.append(np.flatnonzero(cut), len(kind))
    return Words(w.data, at, np.searchsorted(at, w.at[w.docs]))


class WordTokenizer:
    """A tokenizer file that lower-cases and whose tokens never span white space.

    Each distinct chunk is encoded once, many in one text with a separator between them.
    """

    MOST = 100_000  # chunks remembered from slice to slice; only memory depends on it
    SPECIAL = b"<|"  # texts with it may hold special tokens, and are taken word by word as they are

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core; threads would each keep memory
        self.inner = Tokenizer.from_file(path)
        (self.mark,) = self.inner.encode(SEPARATOR, add_special_tokens=False).ids
        self._keep([], np.zeros(0, np.int64), np.zeros(0, np.uint32))

    @classmethod
    def of(cls, path: str) -> WordTokenizer:
        if path not in _tokenizers:
            _tokenizers[path] = cls(path)
        return _tokenizers[path]

    def _keep(self, words: list[str], size: np.ndarray, ids: np.ndarray) -> None:
        self.known = dict(zip(words, range(len(words))))
        self.at, self.ids = np.concatenate([[0], np.cumsum(size)]), ids
        self.slices = np.zeros(len(words), np.int64)

    def shrink(self) -> None:
        """Keeps what more than one slice had."""
        again = self.slices > 1
        if again.sum() > self.MOST // 2:
            again[:] = False
        size = np.diff(self.at)
        self._keep([w for w, a in zip(self.known, again.tolist()) if a], size[again], self.ids[np.repeat(again, size)])

    def _learn(self, words: list[str]) -> None:
        odd = [x for x in words if SEPARATOR in x]
        plain = [x for x in words if SEPARATOR not in x] if odd else words
        between = f" {SEPARATOR} "
        texts = [between.join(plain[i : i + 512]) for i in range(0, len(plain), 512)]
        # A few at a time: an encoding holds its tokens as texts too.
        found = [np.array(e.ids, np.uint32) for i in range(0, len(texts), 16) for e in self.inner.encode_batch_fast(texts[i : i + 16], add_special_tokens=False)]
        flat = np.concatenate([y for x in found for y in (x, np.array([self.mark], np.uint32))]) if found else np.zeros(0, np.uint32)
        ends = np.flatnonzero(flat == self.mark)
        size = np.diff(np.r_[-1, ends]) - 1
        own = [np.array(self.inner.encode(x, add_special_tokens=False).ids, np.uint32) for x in odd]
        self.known.update(zip([*plain, *odd], range(len(self.known), len(self.known) + len(words))))
        size = np.concatenate([size, [len(x) for x in own]]).astype(np.int64)
        self.at = np.concatenate([self.at, self.at[-1] + np.cumsum(size)])
        self.ids = np.concatenate([self.ids, flat[flat != self.mark], *own])
        self.slices = np.concatenate([self.slices, np.zeros(len(words), np.int64)])

    def encode(self, col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids and each document's offsets in them."""
        special = self.SPECIAL in buffer(col)[0].tobytes()
        w = split(col, lower=not special)
        w = w if special else chunks(w)
        coded = w.array().dictionary_encode()
        words = coded.dictionary.to_pylist()
        if len(self.known) > self.MOST:
            self.shrink()
        if new := [x for x in words if x not in self.known]:
            self._learn(new)
        known = np.fromiter(map(self.known.__getitem__, words), np.int64, len(words))
        self.slices[known] += 1
        entry = known[np.asarray(coded.indices)] if words else known
        size = np.diff(self.at)[entry]
        ids = self.ids[ranges(self.at[entry], size)]
        ends = np.concatenate([[0], np.cumsum(size)])
        return ids, ends[w.docs]


def _places(lengths: np.ndarray, seen: np.ndarray) -> np.ndarray:
    """Rank of each piece among those of its length, carried on from ``seen``."""
    order = np.argsort(lengths, kind="stable")
    s = lengths[order]
    first = np.flatnonzero(np.r_[True, s[1:] != s[:-1]]) if len(s) else np.zeros(0, np.int64)
    count = np.diff(np.r_[first, len(s)])
    out = np.empty(len(s), np.int64)
    out[order] = np.arange(len(s)) - np.repeat(first, count) + seen[s]
    seen[s[first]] += count
    return out


def _cut(path: str, window: int, with_ids: bool):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = WordTokenizer.of(path)
        seen = np.zeros(window + 1, np.int64)
        part = TaskContext.get().partitionId()
        for batch in batches:
            for rows, col in slices(batch, limit=2 << 20):
                ids, at = tok.encode(col)
                n = len(col)
                whole = np.empty(len(ids) + n, np.uint32)
                end_at = at[1:] + np.arange(n)
                inner = np.ones(len(whole), bool)
                inner[end_at] = False
                whole[inner] = ids
                whole[end_at] = END
                begin = at[:-1] + np.arange(n)
                total = end_at + 1 - begin
                k = -(-total // window)
                doc = np.repeat(np.arange(n), k)
                start = (np.arange(len(doc)) - np.repeat(np.cumsum(k) - k, k)) * window
                length = np.minimum(window, total[doc] - start)
                lo = begin[doc] + start
                crc = [zlib.crc32(whole[a:b]) for a, b in zip(lo.tolist(), (lo + length).tolist())]
                out = [rows.column(0).take(pa.array(doc)), pa.array(start), pa.array(length), pa.array(crc, pa.int64()), pa.array(total[doc]), pa.array(np.full(len(doc), part, np.int32)), pa.array(_places(length, seen))]
                names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "part", "place"]
                if with_ids:
                    flat = pa.array(whole[ranges(lo, length)].astype(np.int32))
                    out.append(pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(length)]).astype(np.int32)), flat))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(out, names)
        tok.shrink()  # the worker goes on to other tasks, maybe of other stages
        tidy()

    return run


class CapacityTree:
    """Segment tree over remaining capacities 0..window: the smallest open one not below a need."""

    def __init__(self, window: int):
        self.leaves = 1 << window.bit_length()
        self.open = [0] * (2 * self.leaves)

    def add(self, capacity: int, groups: int) -> None:
        at = capacity + self.leaves
        while at:
            self.open[at] += groups
            at >>= 1

    def tightest(self, need: int) -> int | None:
        at = need + self.leaves
        if self.open[at]:
            return need
        while at > 1:
            if not at & 1 and self.open[at + 1]:
                at += 1
                while at < self.leaves:
                    at = 2 * at if self.open[2 * at] else 2 * at + 1
                return at - self.leaves
            at >>= 1
        return None


@dataclass(frozen=True)
class Plan:
    """Segments by length: pieces of ranks from ``rank`` on go ``each`` to a sequence, from ``first`` on, at ``offset``."""

    segments: dict[int, np.ndarray]  # columns: rank, first, each, offset
    sequences: int

    def place(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        seq, off = np.empty(len(length), np.int64), np.empty(len(length), np.int64)
        for n in np.unique(length):
            mine = np.flatnonzero(length == n)
            table = self.segments[int(n)]
            row = table[np.searchsorted(table[:, 0], rank[mine], "right") - 1]
            k = rank[mine] - row[:, 0]
            seq[mine] = row[:, 1] + k // row[:, 2]
            off[mine] = row[:, 3] + k % row[:, 2] * n
        return seq, off


def best_fit_decreasing(histogram: dict[int, int], window: int = WINDOW) -> Plan:
    """The plan for so many pieces of each length."""
    tree, groups = CapacityTree(window), {}
    segments: dict[int, list] = {}
    made = 0

    def release(left: int, first: int, bins: int) -> None:
        if left and bins:
            groups.setdefault(left, []).append((first, bins))
            tree.add(left, 1)

    for length in sorted(histogram, reverse=True):
        todo, rank, mine = histogram[length], 0, segments.setdefault(length, [])
        while todo:
            room = tree.tightest(length)
            if room is None:
                room, each = window, window // length
                first, bins = made, -(-todo // each)
                made += bins
            else:
                first, bins = groups[room].pop()
                tree.add(room, -1)
                each = room // length
            full = min(bins, todo // each)
            if full:
                mine.append((rank, first, each, window - room))
                release(room - each * length, first, full)
                rank, todo = rank + full * each, todo - full * each
            if full < bins:
                if todo:
                    mine.append((rank, first + full, todo, window - room))
                    release(room - todo * length, first + full, 1)
                    full, todo = full + 1, 0
                release(room, first + full, bins - full)
    return Plan({n: np.array(rows, np.int64).reshape(-1, 4) for n, rows in segments.items()}, made)


def _assign(plan: Plan, names: list[str]):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            col = lambda name: np.asarray(batch.column(batch.schema.get_field_index(name)))
            seq, off = plan.place(col("length"), col("place") + col("before"))
            kept = [batch.column(batch.schema.get_field_index(x)) for x in names]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(seq), pa.array(off)], [*names, "sequence_id", "offset"])

    return run


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, path: str | None = None, with_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, [ids,] sequence_id, offset."""
    scratch = Scratch(docs.sparkSession, "packing")
    small_batches(docs.sparkSession)
    schema = PIECES + (", ids array<int>" if with_ids else "")
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    pieces = scratch.table(rows.mapInArrow(_cut(path or vocabulary_path(), window, with_ids), schema), "pieces")
    counts = scratch.table(pieces.groupBy("part", "length").agg(F.count("*").alias("n")), "counts")
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    plan = best_fit_decreasing(histogram, window)
    before = W.partitionBy("length").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    earlier = counts.select("part", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    names = [x for x in pieces.columns if x not in ("part", "place")]
    out = ", ".join(x for x in schema.split(", ") if x.split()[0] not in ("part", "place"))
    return pieces.join(earlier.hint("merge"), ["part", "length"]).mapInArrow(_assign(plan, names), out + ", sequence_id bigint, offset bigint")
