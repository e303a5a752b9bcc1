"""Exact Jaccard self-join of documents on word shingles, as a metric-space join.

Jaccard distance is a metric, so pivots cut the space into Voronoi regions, and the triangle inequality tells
which documents near a border must be replicated.  Links are pairs at a distance of at most r = 1/4.

1. ``PIVOTS`` documents, drawn over all distinct sets and thinned so that any two are more than 3 r apart,
   are sent to all tasks.  The pass over the texts measures every document's exact distances to them.  With D its
   least one, a document lies in the region of its nearest pivot and is replicated to every region whose pivot
   is at most D + r away and nearer than 3 r: of two linked documents that are not both far, the one with the larger
   D is so replicated to the other's own region (its distance there is at most the other's D + r).  What is
   within r of a pivot is linked to it on the spot, so large groups of copies cost no shuffle of sets.
2. A document with D >= 2 r is (also) in the far region, where two such documents meet: all pivots are about equally far from it.  In this space
   that is nearly every document - nearly all distances are 1 - so whole documents as pivots cannot cut it,
   and it is cut by pivots of a single shingle instead.  A document of n shingles is at less than distance 1 from n of
   those; in one global order (common shingles last) its first n - ceil(3 n / 4) + 1 are the regions it is
   replicated to, which a linked document shares one of.
3. Each such region is cut by sizes, which are distances to the empty set: between two runs of size bands lies a
   gap that no link can bridge.  Then the smallest id is its next pivot, again with exact distances.
4. What a region still holds apart is joined recursively in the metric of parity sketches, which never exceeds the
   sets' difference: farthest-first pivots, Voronoi regions, windows of twice the largest radius, until a
   region is small or no longer shrinks; there pairs are compared, and exactly measured if the sketches allow a link.
   A document's likeliest partners are measured first, and others only while they are in another component.

Documents with equal sets are one class from the start and a class once joined is not
compared again, so groups of copies cost their size, not its square.  Regions of many
shingles that hold the same documents are kept once; more than ``BLOCK`` members are cut in blocks.
Shingles are compared by 64-bit hashes (a pair's result changes with probability below 1e-12).

Defined cases: null or empty texts have the empty set and link with nothing; with fewer
than five words the whole sequence is the one shingle; rows that repeat an id are one document, whose text is the
first of theirs in order (null first), and ``keep_one`` keeps one row of it; rows with a null id link nothing and
have the component of an equal text with an id, or null; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bitmap import bit_table, may_contain, one_each, without
from .blocks import PAIRS, index_pairs, spread, whole_groups
from .components import components_of_few
from .scratch import Scratch, small_batches
from .words import mix, ranges, shingle_sets, slices, tidy

WORDS = 5
SIMILARITY = (75, 100)  # links: 100 * intersection >= 75 * union
COMMON = 1 << 18  # shingles that the order puts last; a bound on memory, no effect on results
PARITY = 256  # bits of the parity sketch at least; it has three to six a shingle
PIVOTS = 512  # documents, of at most PIVOT_SIZE shingles: what is broadcast has a bound of 8 MB
PIVOT_SIZE = 2048
RADIUS = 1 - SIMILARITY[0] / SIMILARITY[1]
BAND = 4 / 3  # sizes of linked documents differ by this factor at most
REGION_ROWS = 700_000
BLOCK = 4000  # members of a region compared in one task
LEAF = 64  # members of a region that are compared pair by pair
FEW = 2  # partners that a row of a region asks for at first
MANY = 512  # and that few rows ask for at once sooner than by fours: a block's rows hold 50 MB of them
SLACK = 1e-9
_U = np.uint64


def _sets_hash(s: np.ndarray) -> tuple[int, int]:
    return int(mix(s).sum(dtype=_U).astype(np.int64)), int(mix(s ^ _U(0xA5A5A5A5DEADBEEF)).sum(dtype=_U).astype(np.int64))


def _parity(s: np.ndarray) -> bytes:
    """Bit i tells whether an odd number of shingles falls on i; halves of a sketch add up to a shorter one."""
    bits = max(PARITY, 1 << int(2.8 * len(s)).bit_length())
    return np.packbits((np.bincount((s >> _U(20)).astype(np.int64) & (bits - 1), minlength=bits) & 1).astype(np.uint8)).tobytes()


def _signatures(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Per document: size, 128-bit hash and parity sketch of its set; at the end the task's common shingles."""
    names = ["doc_id", "n", "h1", "h2", "parity", "common", "times"]
    token, times = np.zeros(0, _U), np.zeros(0, np.int64)
    kind = None
    for batch in batches:
        kind = batch.schema.field(0).type
        for rows, col in slices(batch):
            sets = shingle_sets(col, WORDS)
            hashes = [_sets_hash(s) for s in sets]
            m = len(sets)
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array([h[0] for h in hashes], pa.int64()), pa.array([h[1] for h in hashes], pa.int64()), pa.array([_parity(s) for s in sets], pa.binary()), pa.nulls(m, pa.list_(pa.int64())), pa.nulls(m, pa.list_(pa.int64()))], names)
            distinct = {h: s for h, s in zip(hashes, sets)}.values()
            t, c = np.unique(np.concatenate([*distinct, token[:0]]), return_counts=True)
            often = c > 1
            t, inverse = np.unique(np.concatenate([token, t[often]]), return_inverse=True)
            c = np.bincount(inverse, weights=np.concatenate([times, c[often]]), minlength=len(t)).astype(np.int64)
            if len(t) > COMMON:
                top = np.sort(np.argpartition(c, -COMMON)[-COMMON:])
                t, c = t[top], c[top]
            token, times = t, c
    if len(often := np.flatnonzero(times > 2)):
        lists = [pa.array([x[often].astype(np.int64).tolist()], pa.list_(pa.int64())) for x in (token, times)]
        yield pa.RecordBatch.from_arrays([pa.nulls(1, kind), pa.array([-1], pa.int64()), *(pa.nulls(1, pa.int64()) for _ in range(2)), pa.nulls(1, pa.binary()), *lists], names)


def window_size(n: int) -> int:
    return n - -(-n * SIMILARITY[0] // SIMILARITY[1]) + 1


@dataclass
class Pivots:
    """Sets of a bounded number of documents: their shingles, sorted, and whose they are."""

    ids: np.ndarray
    sizes: np.ndarray
    shingles: np.ndarray
    owners: np.ndarray

    @classmethod
    def of(cls, ids: list[int], sets: list[np.ndarray]) -> Pivots:
        flat = np.concatenate([*sets, np.zeros(0, _U)])
        owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
        order = np.argsort(flat, kind="stable")
        return cls(np.array(ids, np.int64), np.array([len(s) for s in sets], np.int64), flat[order], owner[order])

    def thinned(self) -> Pivots:
        """Each pivot more than 3 r away from those before it."""
        order = np.argsort(self.owners, kind="stable")
        sets = np.split(self.shingles[order], np.cumsum(self.sizes)[:-1]) if len(self.ids) else []
        a, p, d, _ = self.distances(sets)
        free, chosen = np.ones(len(sets), bool), []
        for i in range(len(sets)):
            if free[i]:
                chosen.append(i)
                free[p[(a == i) & (d <= 3 * RADIUS)]] = False
        return Pivots.of(self.ids[chosen].tolist(), [sets[i] for i in chosen])

    def distances(self, sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(set, pivot, distance, linked) of all distances below 1, by set."""
        flat = np.concatenate([*sets, np.zeros(0, _U)])
        size = np.array([len(s) for s in sets], np.int64)
        lo = np.searchsorted(self.shingles, flat)
        lo_ = np.minimum(lo, max(0, len(self.shingles) - 1))
        hit = np.flatnonzero(self.shingles[lo_] == flat) if len(self.shingles) else np.zeros(0, np.int64)
        times = np.searchsorted(self.shingles, flat[hit], "right") - lo[hit]
        of = np.repeat(np.repeat(np.arange(len(sets)), size)[hit], times)
        pair, common = np.unique(of * max(1, len(self.ids)) + self.owners[ranges(lo[hit], times)], return_counts=True)
        a, p = np.divmod(pair, max(1, len(self.ids)))
        union = size[a] + self.sizes[p] - common
        num, den = SIMILARITY
        return a, p, 1 - common / union, den * common >= num * union


def window_size(n: int) -> int:
    return n - -(-n * SIMILARITY[0] // SIMILARITY[1]) + 1


def _windows(common: np.ndarray, rank: np.ndarray, bits: int, pivots):
    """Each document's regions: of pivots, with the distance, as they are; shingles packed by hash range, shingles and ids as bytes."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        measure: Pivots = pivots.value
        for batch in batches:
            for rows, col in slices(batch):
                sets = shingle_sets(col, WORDS)
                ids = np.asarray(rows.column(0).fill_null(-1)).astype(np.int64)
                nameless = np.asarray(rows.column(0).is_null())
                seen, mine = set(), []
                for i, s in enumerate(sets):
                    # A row without an id, or whose class is met here already, is not dealt.
                    if not nameless[i] and len(s) and (key := _sets_hash(s)) not in seen:
                        seen.add(key)
                        mine.append(i)
                if not mine:
                    continue
                sets, ids = [sets[i] for i in mine], ids[mine]
                a, p, d, linked = measure.distances(sets)
                least = np.ones(len(sets))
                np.minimum.at(least, a, d)
                cell = (d < 3 * RADIUS + SLACK) & (d <= least[a] + RADIUS + SLACK)
                if cell.any():
                    yield _sent([-1], None, None, ids[a[cell]], p[cell], d[cell], linked[cell], measure.ids)
                far = np.flatnonzero(least >= 2 * RADIUS - SLACK)
                sets, ids = [sets[i] for i in far], ids[far]
                if not sets:
                    continue
                flat = np.concatenate(sets)
                place = np.minimum(np.searchsorted(common, flat), max(0, len(common) - 1))
                hot = common[place] == flat if len(common) else np.zeros(len(flat), bool)
                ends = np.cumsum([len(s) for s in sets])
                tokens, docs = [], []
                for i, s in enumerate(sets):
                    w = window_size(len(s))
                    own = hot[ends[i] - len(s) : ends[i]]
                    if own[:w].any():
                        cold, warm = s[~own], s[own]
                        s = np.concatenate([cold, warm[np.argsort(rank[place[ends[i] - len(own) : ends[i]][own]], kind="stable")]])
                    tokens.append(s[:w])
                    docs.append(np.full(w, ids[i]))
                token, doc = np.concatenate(tokens), np.concatenate(docs)
                part = (token >> _U(64 - bits)).astype(np.int64) if bits else np.zeros(len(token), np.int64)
                order = np.argsort(part, kind="stable")
                part, token, doc = part[order], token[order], doc[order]
                cuts = np.flatnonzero(np.r_[True, part[1:] != part[:-1]]).tolist() + [len(part)]
                data = [token[x:y].tobytes() + np.diff(doc[x:y], prepend=0).tobytes() for x, y in zip(cuts, cuts[1:])]
                yield _sent(part[cuts[:-1]], data)

    return run


SENT = "part int, data binary, region bigint, doc bigint, d double, linked boolean, pivot bigint"


def _sent(part, data, region=None, doc=None, p=None, d=None, linked=None, ids=None) -> pa.RecordBatch:
    names = [x.split()[0] for x in SENT.split(", ")]
    if data is not None:
        m = len(data)
        return pa.RecordBatch.from_arrays([pa.array(np.asarray(part, np.int32)), pa.array(data, pa.binary()), pa.nulls(m, pa.int64()), pa.nulls(m, pa.int64()), pa.nulls(m, pa.float64()), pa.nulls(m, pa.bool_()), pa.nulls(m, pa.int64())], names)
    m = len(doc)
    # Any part will do for these; below 0 they are passed on as they are.
    return pa.RecordBatch.from_arrays([pa.array((-1 - doc % 4096).astype(np.int32)), pa.nulls(m, pa.binary()), pa.array(-1 - p), pa.array(doc), pa.array(d), pa.array(linked), pa.array(ids[p])], names)


DEALT = "region bigint, doc bigint, d double, linked boolean, pivot bigint"


def _shared(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Regions with two or more documents; of those with the same documents, one."""
    names = [x.split()[0] for x in DEALT.split(", ")]
    tokens, docs = [], []
    for batch in batches:
        dealt = batch.filter(pc.less(batch.column(0), 0))
        if dealt.num_rows:
            yield dealt.select(names)
        for x in batch.filter(pc.greater_equal(batch.column(0), 0)).column(1):
            raw = np.frombuffer(x.as_buffer(), np.int64)
            n = len(raw) // 2
            tokens.append(raw[:n].view(_U))
            docs.append(np.cumsum(raw[n:]))
    if not tokens:
        return
    token, doc = np.concatenate(tokens), np.concatenate(docs)
    del tokens, docs
    order = np.argsort(token)
    token, doc = token[order], doc[order]
    first = np.flatnonzero(np.r_[True, token[1:] != token[:-1]])
    size = np.diff(np.r_[first, len(token)])
    many = np.repeat(size > 1, size)
    token, doc, size = token[many], doc[many], size[size > 1]
    if not len(size):
        return
    first = np.cumsum(size) - size
    who = np.add.reduceat(mix(doc.view(_U) + _U(1)), first) + mix(size.astype(_U))
    _, keep = np.unique(who, return_index=True)
    chosen = np.zeros(len(size), bool)
    chosen[keep] = True
    rows = np.flatnonzero(np.repeat(chosen, size))
    for lo in range(0, len(rows), 100_000):
        part = rows[lo : lo + 100_000]
        m = len(part)
        yield pa.RecordBatch.from_arrays([pa.array(token[part].view(np.int64)), pa.array(doc[part]), pa.nulls(m, pa.float64()), pa.nulls(m, pa.bool_()), pa.nulls(m, pa.int64())], names)


def _sets(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for rows, col in slices(batch):
            sets = shingle_sets(col, WORDS)
            flat = np.concatenate([*sets, np.zeros(0, _U)]).view(np.int64)
            at = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.ListArray.from_arrays(pa.array(at), pa.array(flat))], ["doc", "s"])


def _differ(sketches: list[np.ndarray], a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Bits that differ between the sketches of each pair, both folded to the shorter one's size."""
    out = np.zeros(len(a), np.int64)
    size = np.array([len(x) for x in sketches])
    kinds = size[a] * (1 << 32) + size[b]
    for kind in np.unique(kinds):
        mine = np.flatnonzero(kinds == kind)
        for lo in range(0, len(mine), 2000):
            part = mine[lo : lo + 2000]
            x, y = (np.stack([sketches[i] for i in side[part]]) for side in (a, b))
            while x.shape[1] != y.shape[1]:
                half = min(x.shape[1], y.shape[1])
                x, y = (z if z.shape[1] == half else z[:, : z.shape[1] // 2] ^ z[:, z.shape[1] // 2 :] for z in (x, y))
            out[part] = np.bitwise_count(x ^ y).sum(1, dtype=np.int64)
    return out


def _near(sketches: list[np.ndarray], n: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Which pairs a-b sizes and parity sketches don't exclude: bits that differ are a lower bound of the difference."""
    num, den = SIMILARITY
    keep = den * np.minimum(n[a], n[b]) >= num * np.maximum(n[a], n[b])
    todo = np.flatnonzero(keep)
    if not len(todo):
        return keep
    keep[todo] = _differ(sketches, a[todo], b[todo]) * (num + den) <= (n[a[todo]] + n[b[todo]]) * (den - num)
    return keep


def _not_apart(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        m = batch.num_rows
        col = lambda x: batch.column(batch.schema.get_field_index(x))
        sketches = [np.frombuffer(x.as_buffer(), np.uint8) for c in ("pa", "pb") for x in col(c)]
        n = np.concatenate([np.asarray(col("na")), np.asarray(col("nb"))])
        yield batch.select([0, 1]).filter(pa.array(_near(sketches, n, np.arange(m), np.arange(m, 2 * m))))


def _folded(sketch: np.ndarray, size: int) -> np.ndarray:
    while len(sketch) > size:
        sketch = sketch[: len(sketch) // 2] ^ sketch[len(sketch) // 2 :]
    return sketch


def voronoi_pairs(x: np.ndarray, radius: np.ndarray, rows: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of ``rows`` (each once or twice) that may be within radius[a] + radius[b]; ``x`` are sketches as 64-bit words.

    Differing bits are a metric.  A region is cut around farthest-first pivots; whatever may be within
    the largest sum of two radii of a member of a region is replicated to it.
    """
    ways = 8
    if len(rows) > LEAF:
        own = x[rows]
        d = np.empty((len(rows), ways), np.int64)
        at = 0
        for k in range(ways):
            d[:, k] = np.bitwise_count(own ^ own[at]).sum(1)
            at = int(d[:, : k + 1].min(1).argmax())
        home = d.argmin(1)
        least = d[np.arange(len(rows)), home]
        inside = d <= least[:, None] + 2 * (2 * radius[rows].max())
        if (inside.sum(0)).max() < 0.8 * len(rows):
            for k in np.unique(home):
                yield from voronoi_pairs(x, radius, rows[inside[:, k]])
            return
    n = len(rows)
    for lo in range(0, n, max(1, PAIRS // max(1, n))):
        i = np.arange(lo, min(n, lo + max(1, PAIRS // max(1, n))))
        a = np.repeat(i, n - 1 - i)
        b = a + 1 + (np.arange(len(a)) - np.repeat(np.cumsum(n - 1 - i) - (n - 1 - i), n - 1 - i))
        yield rows[a], rows[b]


LEAF_OUT = "a bigint, b bigint, g bigint, rep bigint, cursor bigint"


def _leaf(most: int):
    """Of a region's documents that are still apart and may link: to each the ``most`` likely partners behind its cursor.

    A pair belongs to the one of its two that is not of the component that most of the region's rows had at first, or to the larger
    id.  Partners come in order of likeness and id; the rows with a cursor say who has more of them.
    """

    def solve(rows: pa.Table) -> pa.RecordBatch:
        col = lambda x: np.asarray(rows.column(x).combine_chunks())
        rep, component, n, group, side, at_first = (col(x) for x in ("rep", "component", "n", "g", "side", "at_first"))
        cursor = np.asarray(rows.column("cursor").combine_chunks().fill_null(-1)).astype(np.int64)
        d = np.asarray(rows.column("d").combine_chunks().fill_null(np.nan))
        sketches = [np.frombuffer(x.as_buffer(), np.uint8) for x in rows.column("parity").combine_chunks()]
        radius = n * (SIMILARITY[1] - SIMILARITY[0]) / (SIMILARITY[0] + SIMILARITY[1])  # two of them bound the difference of a link
        first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
        bounds = list(zip(first.tolist(), [*first[1:].tolist(), len(group)]))
        main = np.empty(len(group), bool)
        for lo, hi in bounds:
            names, times = np.unique(at_first[lo:hi], return_counts=True)
            main[lo:hi] = at_first[lo:hi] == names[times.argmax()]

        def pairs():
            large = [(lo, hi) for lo, hi in bounds if hi - lo > LEAF]
            small = np.ones(len(group), bool)
            for lo, hi in large:
                small[lo:hi] = False
            i = np.flatnonzero(small)
            for a, b in index_pairs(group[i], side[i]):
                yield i[a], i[b]
            for lo, hi in large:
                short = min(len(s) for s in sketches[lo:hi])
                x = np.stack([_folded(s, short) for s in sketches[lo:hi]]).view(_U)
                for a, b in voronoi_pairs(x, radius[lo:hi], np.arange(hi - lo)):
                    a, b = a + lo, b + lo
                    keep = (side[a] < 0) | (side[a] != side[b])
                    yield a[keep], b[keep]

        # Of each owner the ``most`` least keys and one more, which tells that there are others; a key is likeness and place.
        order = np.empty(len(rep), np.int64)  # in the region, so that it is the same when fewer regions are left
        order[np.lexsort((rep, group))] = np.arange(len(rep)) - np.repeat(first, np.diff(np.r_[first, len(group)]))
        held = np.zeros((0, 3), np.int64)  # owner, key, partner
        for a, b in pairs():
            ok = (component[a] != component[b]) & ~(np.abs(d[a] - d[b]) > RADIUS + SLACK)
            a, b = a[ok], b[ok]
            near = _near(sketches, n, a, b)
            a, b = a[near], b[near]
            if not len(a):
                continue
            swap = np.where(main[a] == main[b], rep[a] < rep[b], main[a])
            a, b = np.where(swap, b, a), np.where(swap, a, b)
            key = (_differ(sketches, a, b) << 40) | order[b]
            ahead = key > cursor[a]
            held = np.unique(np.concatenate([held, np.stack([a, key, b], 1)[ahead]]), axis=0)
            held = held[_rank_within(held[:, 0]) <= most]
        rank = _rank_within(held[:, 0])
        out = held[rank < most]
        last = np.flatnonzero(rank == most) - 1  # the last one taken of those that have more
        m, k = len(out), len(last)
        both = np.sort(rep[out[:, [0, 2]]], axis=1)
        cols = [pa.array(np.r_[both[:, 0], np.zeros(k, np.int64)]), pa.array(np.r_[both[:, 1], np.zeros(k, np.int64)]), pa.array(np.r_[np.zeros(m, np.int64), group[held[last, 0]]]), pa.array(np.r_[np.zeros(m, np.int64), rep[held[last, 0]]]), pa.array(np.r_[np.full(m, -1), held[last, 1]])]
        return pa.RecordBatch.from_arrays(cols, [x.split()[0] for x in LEAF_OUT.split(", ")])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from whole_groups(batches, solve)
        tidy()

    return run


def _rank_within(owner: np.ndarray) -> np.ndarray:
    """0, 1, 2, ... within each run of equal values."""
    if not len(owner):
        return np.zeros(0, np.int64)
    first = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
    return np.arange(len(owner)) - np.repeat(first, np.diff(np.r_[first, len(owner)]))


def _dealt(left: DataFrame) -> DataFrame:
    """Adds ``g`` and ``side`` (as ``blocks.spread`` does) to members of regions: which of them meet in a task.

    Of a large region most members are joined already, in one component.  They need not meet each other, so
    they are cut in blocks that each meet the blocks of the others, and only those meet among themselves.
    """
    whole = lambda df: df.withColumn("g", F.xxhash64("region")).withColumn("side", F.lit(-1))
    large = left.where(F.col("size") > BLOCK)
    counts = large.groupBy("region", "component").agg(F.count("*").alias("rows"))
    main = counts.groupBy("region").agg(F.max_by("component", F.struct("rows", "component")).alias("main"), F.max("rows").alias("inside"), F.sum("rows").alias("rows"))
    main = main.select("region", "main", F.ceil(F.col("inside") / BLOCK).alias("inner"), F.ceil(F.greatest(F.col("rows") - F.col("inside"), F.lit(1)) / BLOCK).alias("outer"), (F.col("rows") - F.col("inside")).alias("others"))
    large = large.join(main, "region")
    block = lambda n: F.pmod(F.xxhash64("rep"), F.col(n))
    each = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))
    inside = large.where("component = main").withColumn("own", block("inner")).withColumn("other", each("outer"))
    outside = large.where("component <> main")
    across = outside.withColumn("other", block("outer")).withColumn("own", each("inner"))
    meet = lambda df, side: df.withColumn("g", F.xxhash64("region", F.lit(1), "own", "other")).withColumn("side", F.lit(side))
    cols = [*left.columns, "g", "side"]
    parts = [whole(left.where(F.col("size") <= BLOCK)), meet(inside, 0), meet(across, 1), spread(outside, ["region"], "others", "rep", BLOCK)]
    out = parts[0].select(cols)
    for x in parts[1:]:
        out = out.union(x.select(cols))
    return out


class _Join:
    def __init__(self, docs: DataFrame, id_col: str, text_col: str):
        self.rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
        self.scratch = Scratch(docs.sparkSession, "ngram")
        small_batches(docs.sparkSession)

    def signatures(self) -> DataFrame:
        return self.scratch.table(self.rows.mapInArrow(_signatures, "doc_id bigint, n bigint, h1 bigint, h2 bigint, parity binary, common array<bigint>, times array<bigint>"), "signatures")

    def classes(self) -> None:
        """members: (doc_id, n, rep); sizes: (rep, n, parity) of one document for each distinct set."""
        all_rows = self.signatures()
        self.repeated = self.scratch.table(all_rows.where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("times")).where("times > 1"), "repeated")
        self.once = self.repeated.isEmpty()
        if not self.once:  # of rows that repeat an id one stands for all
            ids = self.repeated.select("doc_id")
            some = may_contain(self.rows, "doc_id", bit_table(ids, "doc_id")).join(ids, "doc_id", "left_semi")
            self.rows = self.scratch.table(without(self.rows, "doc_id", ids).union(one_each(some, ["doc_id"])), "rows")
            all_rows = self.signatures()
        sig = all_rows.where("n >= 0").select("doc_id", "n", "h1", "h2", "parity")
        self.sizes = self.scratch.table(sig.where("n > 0").groupBy("n", "h1", "h2").agg(F.min("doc_id").alias("rep"), F.first("parity").alias("parity")), "classes")
        self.members = self.scratch.table(sig.join(self.sizes.drop("parity"), ["n", "h1", "h2"], "left").select("doc_id", "n", "rep"), "members")
        hot = all_rows.where("n < 0").select(F.explode(F.arrays_zip("common", "times")).alias("x")).groupBy("x.common").agg(F.sum("x.times").alias("times"))
        found = hot.orderBy(F.desc("times"), "common").limit(COMMON).toArrow().to_pandas()
        token = found["common"].to_numpy(np.int64).view(_U)
        order = np.argsort(token)
        self.common, self.rank = token[order], found["times"].to_numpy(np.int64)[order]
        self.tokens = self.sizes.agg(F.sum("n")).first()[0] or 0

    def pivots(self) -> Pivots:
        """Documents drawn by the hash of their id among all distinct sets, so a large group of near copies has one."""
        drawn = self.sizes.where((F.col("n") <= PIVOT_SIZE) & F.col("rep").isNotNull()).orderBy(F.xxhash64("rep"), "rep").limit(PIVOTS).select(F.col("rep").alias("doc"))
        drawn = self.scratch.table(drawn, "drawn")  # at most PIVOTS ids are broadcast and as many sets collected
        sets = self.rows.withColumnRenamed("doc_id", "doc").join(F.broadcast(drawn), "doc").mapInArrow(_sets, "doc bigint, s array<bigint>")
        got = sets.orderBy("doc").toArrow().to_pydict()
        return Pivots.of(got["doc"], [np.array(s, np.int64).view(_U) for s in got["s"]]).thinned()

    def regions(self) -> None:
        """cells: (region, rep, n, d) of regions that hold two or more classes; hubs: links (a, b) to pivots."""
        bits = max(4, int(self.tokens * 0.27 / REGION_ROWS).bit_length())
        share = self.rows.sparkSession.sparkContext.broadcast(self.pivots())
        packed = self.rows.mapInArrow(_windows(self.common, self.rank, bits, share), SENT)
        shared = self.scratch.table(packed.repartition(1 << bits, "part").mapInArrow(_shared, DEALT), "shared")
        ids = self.members.where("rep is not null").select(F.col("doc_id").alias("doc"), "rep", "n")
        dealt = shared.join(ids, "doc")
        self.hubs = self.scratch.table(dealt.where("linked and rep <> pivot").select(F.col("rep").alias("a"), F.col("pivot").alias("b")).distinct(), "hubs")
        band = F.floor(F.log(F.col("n").cast("double")) / F.log(F.lit(BAND)) + SLACK).cast("int")
        rows = dealt.groupBy("region", "rep").agg(F.first("n").alias("n"), F.first("d").alias("d")).withColumn("band", F.least(band, F.lit(62)))
        rows = self.scratch.table(rows, "dealt")
        masks = rows.groupBy("region").agg(F.bit_or(F.expr("shiftleft(1L, band)")).alias("mask"), F.count("*").alias("all")).where(F.col("all") > 1).drop("all")
        # The run of occupied bands that a band lies in is named by the highest free band below it.
        free = F.expr("~mask & (shiftleft(1L, band) - 1)")
        run = F.when(free == 0, 0).otherwise(F.length(F.bin(free)))
        rows = rows.join(masks, "region").select(F.xxhash64("region", run).alias("region"), "rep", "n", "d")
        self.cells = self.scratch.table(rows, "cells")
        self.scratch.drop(shared)

    def near(self, pairs: DataFrame) -> DataFrame:
        """Of pairs (a, b), those that sizes and sketches don't exclude."""
        sizes = lambda x: self.sizes.select(F.col("rep").alias(x), F.col("n").alias(f"n{x}"), F.col("parity").alias(f"p{x}"))
        sized = pairs.join(sizes("a"), "a").join(sizes("b"), "b")
        return self.scratch.table(sized.select("a", "b", "na", "nb", "pa", "pb").mapInArrow(_not_apart, "a bigint, b bigint"), "near")

    def measured(self, near: DataFrame) -> DataFrame:
        """(a, b, d, linked): the exact distances of pairs."""
        num, den = SIMILARITY
        needed = near.select(F.col("a").alias("doc")).union(near.select(F.col("b").alias("doc"))).distinct()
        docs = may_contain(self.rows.select(F.col("doc_id").alias("doc"), "text"), "doc", bit_table(needed, "doc"))
        sets = self.scratch.table(docs.mapInArrow(_sets, "doc bigint, s array<bigint>"), "sets")
        full = near.join(sets.select(F.col("doc").alias("a"), F.col("s").alias("sa")), "a").join(sets.select(F.col("doc").alias("b"), F.col("s").alias("sb")), "b")
        common = full.select("a", "b", F.size(F.array_intersect("sa", "sb")).cast("long").alias("i"), (F.size("sa") + F.size("sb")).cast("long").alias("both"))
        union = common.withColumn("u", F.col("both") - F.col("i"))
        out = self.scratch.table(union.select("a", "b", F.expr("1 - i / u").alias("d"), F.expr(f"{den} * i >= {num} * u").alias("linked")), "measured")
        self.scratch.drop(sets, near)
        return out

    def components(self) -> DataFrame:
        """(rep, component) of every class that links with another."""
        self.regions()
        num, den = SIMILARITY
        # In regions without one the smallest id is the pivot.
        pivots = self.cells.groupBy("region").agg(F.min("rep").alias("pivot"), F.min_by("n", "rep").alias("np"), F.count("*").alias("size"), F.max("d").isNotNull().alias("known")).where("size > 1")
        cells = self.scratch.table(self.cells.join(pivots, "region"), "with_pivots")
        fit = (F.least("n", "np") * den >= F.greatest("n", "np") * num) & ~F.col("known") & (F.col("rep") != F.col("pivot"))
        first = self.measured(self.near(cells.where(fit).select(F.col("rep").alias("a"), F.col("pivot").alias("b")).distinct()))
        near = self.scratch.table(components_of_few(first.where("linked").select("a", "b").union(self.hubs), self.scratch), "joined")
        named = cells.join(near.select(F.col("node").alias("rep"), "component"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
        named = self.scratch.table(named, "named")
        split = named.groupBy("region").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.first("known").alias("k"), F.count("*").alias("rows")).where("lo <> hi and (rows > 2 or k)").select("region")
        known = first.select(F.col("a").alias("rep"), F.col("b").alias("pivot"), F.col("d").alias("dp"))
        # A pivot that was measured is not compared again; those of the first step are no members here.
        left = named.join(split, "region").where("known or rep <> pivot").join(known, ["rep", "pivot"], "left").withColumn("d", F.coalesce("d", "dp"))
        left = _dealt(self.scratch.table(left.select("region", "rep", "n", "component", "d", "size"), "left"))
        left = left.join(self.sizes.select("rep", "parity"), "rep").select("rep", "n", F.col("component").alias("at_first"), "d", "parity", "g", "side", F.lit(-1).cast("long").alias("cursor"))
        return self.settled(left, near)

    def settled(self, left: DataFrame, near: DataFrame) -> DataFrame:
        """Joins what regions still hold apart, the likeliest pairs first.

        Once a pair links, all other pairs of its two components are settled without being measured.  So each row asks for
        a few partners, then for four times as many of those that are still in another component, and so on until no row has one left:
        every pair is measured or within a component in the end, and a group of near copies does not cost its square.
        Where few rows are left they ask for more at once, up to a quarter as many pairs as there are distinct sets, since a round costs
        its stages however little it measures.
        """
        most, first, fair = FEW, True, self.sizes.count() // 4
        while True:
            now = left.join(near.select(F.col("node").alias("rep"), "component"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
            said = now.repartition("g").sortWithinPartitions("g").mapInArrow(_leaf(most), LEAF_OUT)
            said = self.scratch.table(said, "said")
            pairs = self.scratch.table(said.where("cursor < 0").select("a", "b").distinct(), "pairs")
            if pairs.isEmpty():
                return near
            linked = self.measured(pairs).where("linked").select("a", "b")
            near = self.scratch.table(components_of_few(near.select(F.col("node").alias("a"), F.col("component").alias("b")).union(linked), self.scratch), "joined")
            more = said.where("cursor >= 0").select("g", "rep", "cursor")
            asking = more.count()
            if not asking:
                return near
            # Only regions in which a row has more to ask go on; a row without more keeps a cursor behind all of its partners.
            open_ = left.drop("cursor").join(more.select("g").distinct(), "g", "left_semi").join(more, ["g", "rep"], "left")
            old, left = left, self.scratch.table(open_.select("rep", "n", "at_first", "d", "parity", "g", "side", F.coalesce("cursor", F.lit((1 << 63) - 1)).alias("cursor")), "open")
            if not first:
                self.scratch.drop(old)
            self.scratch.drop(said)
            most, first = max(most * 4, min(MANY, fair // asking)), False


def cluster(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, n_shingles, component_id (smallest id reachable by links)."""
    join = _Join(docs, id_col, text_col)
    join.classes()
    found = join.components().select(F.col("node").alias("rep"), "component")
    out = join.members.join(found, "rep", "left")
    if not join.once:
        times = join.repeated.withColumn("again", F.explode(F.sequence(F.lit(2).cast("long"), "times"))).select("doc_id")
        out = out.unionByName(times.join(out, "doc_id"))
    return out.select(F.col("doc_id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("component", "rep", "doc_id").alias("component_id"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document of each group of linked ones stays (the smallest id), with all columns; of rows that repeat its id the first."""
    scratch = Scratch(docs.sparkSession, "ngram")
    found = scratch.table(cluster(docs, id_col, text_col), "found")
    drop = scratch.table(found.where(F.col(id_col) != F.col("component_id")).select(id_col).distinct(), "drop")
    again = scratch.table(found.groupBy(id_col).agg(F.count("*").alias("n")).where(f"n > 1 and `{id_col}` is not null").select(id_col), "again")
    kept = without(docs, id_col, drop)
    if again.isEmpty():
        return kept
    repeated = may_contain(kept, id_col, bit_table(again, id_col)).join(again, id_col, "left_semi").select(kept.columns)
    return without(kept, id_col, again).union(one_each(repeated, [id_col]))
