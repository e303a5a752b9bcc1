"""Language-model scoring with a weighted backoff automaton, of which every block of texts gets its part.

Tokens are lower-cased (A-Z) words and one end per document.  Counts cover all training
documents, and every n-gram counts, however rare: nothing is pruned at any size.

  P(t)       = (c(t) + 0.1) / (N + 0.1 (V + 1)), all unseen tokens together one class
  P(t | v)   = (c(v t) + K P(t)) / (c(v) + K)
  P(t | u v) = (c(u v t) + K P(t | v)) / (c(u v) + K),    K = ``STRENGTH``

c of a context is how often it is followed by a token; a document's first token follows a start
mark.  As an automaton: contexts that were seen are states; a seen n-gram is an arc with the weight
log10 P; any other token takes the failure arc to the shorter context, at log10 K / (c + K).  Every
state's probabilities, the unseen class included, add up to one.

The whole automaton may have more arcs than any memory holds, but a block of texts (``BLOCK_BYTES``)
only ever takes arcs of its own n-grams.  So

1. texts are written once as blocks, a row each;
2. every block sends its distinct n-grams, as sorted keys of ``KEY_BITS`` by hash range, with their training
   counts in the block; a range sums them up and answers each block, in the order of its keys, with
   the counts that differ from its own (an n-gram that occurs in one block only needs no answer);
3. the answers meet their block again, which builds its part of the automaton and walks its documents
   left to right, carrying the state; long documents are walked in segments that start two tokens early.

What is gathered grows with the input and lies in shuffled tables; nothing is broadcast and the driver
sees N and V.  Two of n n-grams of one order share a key with probability n / 2^54: at 30 GB of text one
n-gram in a million counts for another too, at 100 TB one in a thousand.  A task of step 2 holds ``PART_KEYS`` keys, one of step 3 one block (or one longer text).

Defined cases: null text is an empty text (the end alone); without training tokens every token
has base probability 1 and score 0; rows that repeat an id are scored apart; rows with a null id
train; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from .scratch import Scratch, small_batches
from .words import mix, slices, split, strings, tidy, word_hashes

BLOCK_BYTES = 6 << 20
KEY_BITS = 56
PART_KEYS = 1_000_000
KEYS_PER_BYTE = 0.28  # of distinct n-grams to bytes of text, about; only the number of parts depends on it
STRENGTH = 4.0
SEGMENT = 256
CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_U = np.uint64
END = _U(0x6C62272E07BB0142)
START = _U(0x9AE16A3B2F90404F)
_C = _U(0x9FB21C651E98DF25)
TOKEN, PAIR, TRIPLE = _U(1), _U(2), _U(3)  # orders, in the lowest two bits of a key; 0 is the start mark


def held_out(id_column: Column, modulus: int = 10, remainder: int = 0) -> Column:
    return F.coalesce(F.crc32(id_column.cast("string")) % modulus == remainder, F.lit(False))


def tokens(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Token hashes, ends included, and each document's offsets."""
    w = split(col, lower=True)
    h = word_hashes(w)
    n = len(col)
    at = w.docs + np.arange(n + 1)
    out = np.empty(len(h) + n, _U)
    word = np.ones(len(out), bool)
    word[at[1:] - 1] = False
    out[word] = h
    out[at[1:] - 1] = END
    return out, at


def _key(h: np.ndarray, order: np.uint64) -> np.ndarray:
    return (h >> _U(64 - KEY_BITS)) & ~_U(3) | order


@dataclass
class Grams:
    """The n-grams of a block: sorted distinct keys and, per token, the index of what ends there (-1: no triple)."""

    at: np.ndarray  # offsets of documents
    keys: np.ndarray
    start: int
    token: np.ndarray
    pair: np.ndarray
    triple: np.ndarray
    own: np.ndarray  # training counts in the block

    @classmethod
    def of(cls, col: pa.Array, train: np.ndarray) -> Grams:
        t, at = tokens(col)
        first = at[:-1]
        before = np.empty_like(t)
        before[1:] = t[:-1]
        before[first] = START
        two = mix(before * _C + t)
        inner = np.ones(len(t), bool)
        inner[first] = False
        inner = np.flatnonzero(inner)
        three = mix(two[inner - 1] * _C + t[inner])
        every = np.concatenate([_key(t, TOKEN), _key(two, PAIR), _key(three, TRIPLE), _key(np.array([START]), _U(0))])
        keys, index = np.unique(every, return_inverse=True)
        index = index.astype(np.int32)
        n = len(t)
        trained = np.repeat(train, np.diff(at)).astype(np.float64)
        weight = np.concatenate([trained, trained, trained[inner], [float(train.sum())]])
        triple = np.full(n, -1, np.int32)
        triple[inner] = index[2 * n : -1]
        return cls(at, keys, int(index[-1]), index[:n], index[n : 2 * n], triple, np.bincount(index, weight, len(keys)).astype(np.int64))


@dataclass
class Automaton:
    """The part of the backoff automaton that a block's n-grams can reach; state 0 has no context."""

    grams: Grams
    begin: int  # the state at a document's start
    fail: np.ndarray
    bow: np.ndarray  # log10 weights of failure arcs
    source: np.ndarray  # by n-gram: the state that its arc leaves (-1: no arc) ...
    weight: np.ndarray  # ... its log10 weight (of a token: that in state 0) ...
    target: np.ndarray  # ... and the state it leads to

    @classmethod
    def build(cls, g: Grams, count: np.ndarray, total: int, types: int, strength: float = STRENGTH) -> Automaton:
        size, n = len(g.keys), len(g.token)
        end = np.zeros(n, bool)
        end[g.at[1:] - 1] = True
        where = lambda index: (lambda out: (out.__setitem__(index[index >= 0], np.flatnonzero(index >= 0)), out)[1])(np.full(size, -1, np.int64))
        p2_at, p3_at = where(g.pair), where(g.triple)  # one place of each pair and triple
        pairs, triples = np.flatnonzero(p2_at >= 0), np.flatnonzero(p3_at >= 0)
        p2_at, p3_at = p2_at[pairs], p3_at[triples]
        head = np.zeros(n, bool)
        head[g.at[:-1]] = True
        context = np.where(head, g.start, g.token[np.maximum(np.arange(n) - 1, 0)])  # of pairs, by place
        p = np.zeros(size)
        p[g.token] = (count[g.token] + 0.1) / (total + 0.1 * (types + 1))
        p[pairs] = (count[pairs] + strength * p[g.token[p2_at]]) / (count[context[p2_at]] + strength)
        p[triples] = (count[triples] + strength * p[g.pair[p3_at]]) / (count[g.pair[p3_at - 1]] + strength)
        # States: seen tokens and pairs that a token can follow, and the start.
        open_ = np.zeros(size, bool)
        open_[g.token[~end]] = open_[g.pair[~end]] = open_[g.start] = True
        states = np.flatnonzero(open_ & (count > 0))
        number = np.zeros(size, np.int32)
        number[states] = np.arange(1, len(states) + 1)
        fail = np.zeros(len(states) + 1, np.int32)
        fail[number[pairs]] = number[g.token[p2_at]]
        fail[0] = 0
        bow = np.zeros(len(states) + 1)
        bow[1:] = np.log10(strength / (count[states] + strength))
        source = np.full(size, -1, np.int32)
        seen = count[pairs] > 0
        source[pairs[seen]] = number[context[p2_at[seen]]]
        seen = count[triples] > 0
        source[triples[seen]] = number[g.pair[p3_at[seen] - 1]]
        target = number.copy()  # of a token and a pair: its own state
        target[pairs] = np.where(number[pairs] > 0, number[pairs], number[g.token[p2_at]])
        target[triples] = target[g.pair[p3_at]]
        with np.errstate(divide="ignore"):
            return cls(g, int(number[g.start]), fail, bow, source, np.log10(p), target)

    def walk(self) -> np.ndarray:
        """log10 probability of every token: all segments take a step at a time, each carrying its state."""
        g = self.grams
        out = np.zeros(len(g.token))
        size = np.diff(g.at)
        k = -(-size // SEGMENT)
        begin = np.repeat(g.at[:-1], k)
        seg = begin + (np.arange(k.sum()) - np.repeat(np.cumsum(k) - k, k)) * SEGMENT
        stop = np.minimum(seg + SEGMENT, np.repeat(g.at[1:], k))
        back = np.minimum(2, seg - begin)  # tokens walked again to find the state
        order = np.argsort(-(stop - seg + back), kind="stable")
        pos, seg, stop = (seg - back)[order], seg[order], stop[order]
        state = np.where(pos == begin[order], self.begin, 0).astype(np.int32)
        n = len(pos)
        longest = stop - pos
        for step in range(int(longest[0]) if n else 0):
            n = int(np.searchsorted(-longest, -step, "left"))  # those with more than ``step`` tokens
            p, s = pos[:n] + step, state[:n]
            token, pair, triple = g.token[p], g.pair[p], g.triple[p]
            three = (triple >= 0) & (self.source[triple] == s) & (s > 0)
            deep = ~three & (self.fail[s] > 0)
            score = np.where(deep, self.bow[s], 0.0)
            s = np.where(deep, self.fail[s], s)
            two = ~three & (self.source[pair] == s) & (s > 0)
            none = ~three & ~two
            score += np.where(none, self.bow[s], 0.0)
            arc = np.where(three, triple, np.where(two, pair, token))
            score += self.weight[arc]
            state[:n] = self.target[arc]
            real = p >= seg[:n]
            out[p[real]] = score[real]
        return out


def _codec() -> pa.Codec:
    return pa.Codec("zstd", compression_level=1)


def _squeezed(x: np.ndarray) -> bytes:
    """Integers byte by byte, all lowest first: high ones are mostly equal, which compression takes away."""
    planes = np.ascontiguousarray(x.view(np.uint8).reshape(len(x), x.itemsize).T)
    return _codec().compress(planes.tobytes(), asbytes=True)


def _restored(raw: bytes, n: int, kind) -> np.ndarray:
    size = np.dtype(kind).itemsize
    planes = np.frombuffer(_codec().decompress(raw, n * size, asbytes=True), np.uint8).reshape(size, n)
    return np.ascontiguousarray(planes.T).view(kind).ravel()


def _blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts, training flags and ids of about ``BLOCK_BYTES`` as one row."""
    number = TaskContext.get().partitionId() << 32
    held: list[tuple[pa.Array, np.ndarray, np.ndarray, bytes]] = []

    def block() -> pa.RecordBatch:
        nonlocal number
        ids, size, train = pa.concat_arrays([x[0] for x in held]), np.concatenate([x[1] for x in held]), np.concatenate([x[2] for x in held])
        text = b"".join([x[3] for x in held])
        held.clear()
        data = np.int64(len(text)).tobytes() + size.tobytes() + train.tobytes() + _codec().compress(text, asbytes=True)
        number += 1
        lists = pa.ListArray.from_arrays(pa.array([0, len(size)], pa.int32()), ids)
        return pa.RecordBatch.from_arrays([pa.array([number - 1], pa.int64()), lists, pa.array([len(text) + len(size)], pa.int64()), pa.array([data], pa.binary())], ["block", "ids", "bytes", "data"])

    for batch in batches:
        for rows, col in slices(batch, limit=BLOCK_BYTES // 4):
            n = len(col)
            at = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + n + 1]
            raw = col.buffers()[2]
            held.append((rows.column(0), np.diff(at), np.asarray(rows.column(2)).astype(np.uint8), bytes(memoryview(raw)[at[0] : at[-1]]) if raw is not None else b""))
            if sum(len(x[3]) for x in held) >= 7 * BLOCK_BYTES // 8:
                yield block()
    if held:
        yield block()


def _opened(n: int, raw: memoryview) -> Grams:
    size = int(np.frombuffer(raw, np.int64, 1)[0])
    length = np.frombuffer(raw[8 : 8 + 8 * n], np.int64)
    train = np.frombuffer(raw[8 + 8 * n : 8 + 9 * n], np.uint8).astype(bool)
    text = _codec().decompress(bytes(raw[8 + 9 * n :]), size) if size else pa.py_buffer(b"")
    at = np.concatenate([[0], np.cumsum(length)]).astype(np.int64)
    return Grams.of(strings(pa.Array.from_buffers(pa.large_string(), n, [None, pa.py_buffer(at), text])), train)


def _cuts(keys: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash ranges that occur among sorted keys, and where each begins."""
    part = (keys >> _U(KEY_BITS - bits)).astype(np.int64)
    cut = np.flatnonzero(np.r_[True, part[1:] != part[:-1]])
    return part[cut], np.r_[cut, len(keys)]


def _request(bits: int):
    """A block's distinct n-grams with their counts in it, by hash range."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                g = _opened(len(batch.column(1)[i]), memoryview(batch.column(2)[i].as_buffer()))
                part, cut = _cuts(g.keys, bits)
                size = np.diff(cut)
                keys, own = [], []
                for a, b in zip(cut.tolist(), cut[1:].tolist()):
                    keys.append(_squeezed(np.diff(g.keys[a:b], prepend=_U(0))))
                    own.append(_squeezed(g.own[a:b]))
                m = len(part)
                yield pa.RecordBatch.from_arrays([pa.array(part.astype(np.int32)), pa.array(np.full(m, batch.column(0)[i].as_py())), pa.array(size), pa.array(keys, pa.binary()), pa.array(own, pa.binary())], ["part", "block", "n", "keys", "own"])
            tidy()

    return run


def _answer(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """To each block, in the order of its keys: 0 where its own count is all, else the count; and N and V of the range."""
    places, keys, own = [], [], []
    for batch in batches:
        part, block, n = (batch.column(i).to_pylist() for i in range(3))
        for i in range(batch.num_rows):
            places.append((part[i], block[i], n[i]))
            keys.append(np.cumsum(_restored(batch.column(3)[i].as_buffer(), n[i], np.uint64)))
            own.append(_restored(batch.column(4)[i].as_buffer(), n[i], np.int64))
    if not places:
        return
    key, mine = np.concatenate(keys), np.concatenate(own)
    del keys, own
    distinct, index = np.unique(key, return_inverse=True)
    del key
    total = np.bincount(index, mine, len(distinct)).astype(np.int64)
    word = ((distinct & _U(3)) == TOKEN) & (total > 0)
    types, tokens_ = int(word.sum()), int(total[word].sum())
    told = total[index]
    told[told == mine] = 0
    del index, mine
    names = ["part", "block", "n", "data", "types", "tokens"]
    yield pa.RecordBatch.from_arrays([pa.array([-1], pa.int32()), pa.array([-1], pa.int64()), pa.array([0], pa.int64()), pa.array([b""], pa.binary()), pa.array([types]), pa.array([tokens_])], names)
    at = 0
    for lo in range(0, len(places), 500):
        some = places[lo : lo + 500]
        data = []
        for _, _, n in some:
            x = told[at : at + n]
            at += n
            large = x[x > 254]
            data.append(np.int64(len(large)).tobytes() + large.tobytes() + _codec().compress(np.minimum(x, 255).astype(np.uint8).tobytes(), asbytes=True))
        null = pa.nulls(len(some), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array([p for p, _, _ in some], pa.int32()), pa.array([b for _, b, _ in some], pa.int64()), pa.array([n for _, _, n in some], pa.int64()), pa.array(data, pa.binary()), null, null], names)
    tidy()


def _heard(n: int, raw: memoryview) -> np.ndarray:
    k = int(np.frombuffer(raw, np.int64, 1)[0])
    out = np.frombuffer(_codec().decompress(bytes(raw[8 + 8 * k :]), n, asbytes=True), np.uint8).astype(np.int64)
    out[out == 255] = np.frombuffer(raw[8 : 8 + 8 * k], np.int64)
    return out


def _score(total: int, types: int, strength: float, id_type: pa.DataType):
    """Rows by block, its answers in order of the ranges and then its texts; out come the documents."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        told: list[np.ndarray] = []
        for batch in batches:
            part, n = np.asarray(batch.column(1)), np.asarray(batch.column(2))
            for i in range(batch.num_rows):
                raw = memoryview(batch.column(3)[i].as_buffer())
                if part[i] != LAST:
                    told.append(_heard(int(n[i]), raw))
                    continue
                ids = batch.column(4)[i].values
                g = _opened(len(ids), raw)
                count = np.concatenate(told)
                told = []
                count = np.where(count > 0, count, g.own)
                base = np.log10((count + 0.1) / (total + 0.1 * (types + 1)))
                score = Automaton.build(g, count, total, types, strength).walk() if total else np.zeros(len(g.token))
                size = np.diff(g.at)
                sums = lambda x: pa.array(np.add.reduceat(x, g.at[:-1]).astype(np.float64))
                known = np.add.reduceat((count[g.token] > 0).astype(np.int64), g.at[:-1])
                yield pa.RecordBatch.from_arrays([ids.cast(id_type), pa.array(size), pa.array(known), sums(base[g.token]), sums(score)], ["id", "n_tokens", "known", "base", "score"])
            tidy()

    return run


LAST = (1 << 31) - 1  # sorts a block's texts behind its answers


def _written(scratch: Scratch, df: DataFrame, name: str) -> DataFrame:
    """A written table, with the shuffles that made it deleted."""
    conf = scratch.spark.conf
    was = conf.get(CLEAN)
    conf.set(CLEAN, "true")
    try:
        return scratch.table(df, name)
    finally:
        conf.set(CLEAN, was)


def score(docs: DataFrame, train: Column, id_col: str = "doc_id", text_col: str = "text", strength: float = STRENGTH) -> DataFrame:
    """One row per document: id, n_tokens, n_known, train_tokens, base_score, score; ``train`` selects what is learnt from."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "lm")
    small_batches(spark)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.coalesce(train, F.lit(False)).alias("train"))
    kind = rows.schema["id"].dataType.simpleString()
    blocks = scratch.table(rows.mapInArrow(_blocks, f"block bigint, ids array<{kind}>, bytes bigint, data binary"), "blocks")
    size = blocks.agg(F.coalesce(F.sum("bytes"), F.lit(0))).first()[0]
    bits = max(4, int(size * KEYS_PER_BYTE / PART_KEYS).bit_length())
    asked = blocks.select("block", "ids", "data").mapInArrow(_request(bits), "part int, block bigint, n bigint, keys binary, own binary")
    # The range is the partition: ranges are alike in size, whatever the texts are.
    answered = asked.repartitionById(1 << bits, F.col("part")).mapInArrow(_answer, "part int, block bigint, n bigint, data binary, types bigint, tokens bigint")
    answers = _written(scratch, answered, "answers")
    total, types = answers.agg(F.coalesce(F.sum("tokens"), F.lit(0)), F.coalesce(F.sum("types"), F.lit(0))).first()
    every = answers.where("block >= 0").select("block", "part", "n", "data", F.lit(None).cast(f"array<{kind}>").alias("ids"))
    every = every.union(blocks.select("block", F.lit(LAST).alias("part"), F.lit(0).cast("long").alias("n"), "data", "ids"))
    every = every.repartition("block").sortWithinPartitions("block", "part")
    out = every.mapInArrow(_score(total, types, strength, to_arrow_type(rows.schema["id"].dataType)), f"id {kind}, n_tokens bigint, known bigint, base double, score double")
    return out.select(F.col("id").alias(id_col), "n_tokens", F.col("known").alias("n_known"), F.lit(total).alias("train_tokens"), F.col("base").alias("base_score"), "score")
