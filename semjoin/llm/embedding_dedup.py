"""Embedding near-duplicates: p-stable Euclidean hashing, then exact cosines.

Vectors are normalised, so a cosine of 0.95 is a distance of 0.316.  A table hashes a vector by
``PROJECTIONS`` quantised Gaussian projections of width ``WIDTH``; two vectors at that distance
share a bucket of one table with probability 0.874^18 = 0.089, so of ``TABLES`` = 60 tables some
bucket with probability 0.996 (more if they are nearer); unrelated vectors meet with 2e-6.

Equal vectors are one representative with a weight.  Buckets are first formed on keys alone;
only members of buckets with company are sent with their vectors.  A bucket of more than
``BLOCK`` members is split in blocks and every pair of blocks is a task of its own.  A pair is
counted in the first table that it shares (members carry their keys), and what leaves a bucket
is a count and a root per member, not pairs.

Defined cases: vectors that are null, empty, zero, or hold null or non-finite components link
with nothing; vectors of different lengths don't link; every row is a vector of its own, so rows
that repeat an id are linked by their own components each, and a component is named by its smallest
id; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import index_pairs, spread, whole_groups
from .components import components
from .scratch import Scratch
from .words import mix

COSINE = 0.95
TABLES = 60
PROJECTIONS = 18
WIDTH = 2.0
BLOCK = 1000
SEED = 7
_U = np.uint64


@lru_cache(8)
def _planes(size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    r = np.random.default_rng(SEED + size)
    return r.standard_normal((size, TABLES * PROJECTIONS)), r.random(TABLES * PROJECTIONS) * WIDTH, r.integers(1, 1 << 63, PROJECTIONS, dtype=np.uint64) | _U(1)


def keys_of(unit: np.ndarray) -> np.ndarray:
    """One 64-bit bucket key per vector and table."""
    planes, shift, odd = _planes(unit.shape[1])
    cell = np.floor((unit @ planes + shift) / WIDTH).astype(np.int64).view(_U).reshape(len(unit), TABLES, PROJECTIONS)
    return mix((mix(cell + _U(unit.shape[1])) * odd).sum(2, dtype=_U))


def unit_vectors(v: np.ndarray) -> np.ndarray:
    v = v.astype(np.float64)
    scale = np.abs(v).max(1, keepdims=True)
    v = v / scale
    return v / np.sqrt((v * v).sum(1, keepdims=True))


def _by_length(column: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Rows and matrices of the usable vectors, by their length."""
    if column.null_count == len(column):
        return
    size = np.asarray(pc.fill_null(pc.list_value_length(column), 0)).astype(np.int64)
    flat = column.flatten()
    bad = np.asarray(pc.is_null(flat))
    values = np.asarray(pc.fill_null(flat.cast(pa.float64()), np.nan))
    values = np.where(bad, np.nan, values)
    begin = np.cumsum(size) - size
    for n in np.unique(size[size > 0]):
        rows = np.flatnonzero(size == n)
        m = values[begin[rows][:, None] + np.arange(n)]
        ok = np.isfinite(m).all(1) & (m != 0).any(1)
        if ok.any():
            yield rows[ok], m[ok]


def _digests(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All columns (the vector is the second) and, for usable vectors, a 128-bit digest of the components."""
    for batch in batches:
        d = [None] * batch.num_rows
        for rows, m in _by_length(batch.column(1)):
            m = m + 0.0  # one zero
            for r, x in zip(rows.tolist(), m):
                d[r] = hashlib.blake2b(x.tobytes(), digest_size=16).digest()
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(d, pa.binary())], [*batch.schema.names, "digest"])


def _buckets(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(rep, weight, v, keys) with the bucket keys of all tables."""
    for batch in batches:
        for lo in range(0, batch.num_rows, 1000):
            part = batch.slice(lo, 1000)
            for rows, m in _by_length(part.column(2)):
                k = keys_of(unit_vectors(m))
                take = pa.array(rows)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(k) + 1, dtype=np.int32) * TABLES), pa.array(k.view(np.int64).ravel()))
                yield pa.RecordBatch.from_arrays([part.column(0).take(take), part.column(1).take(take), part.column(2).take(take), lists], ["rep", "weight", "v", "keys"])


def roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest member that each of 0..n-1 reaches by the links a-b."""
    label = np.arange(n)
    while len(a):
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        np.minimum.at(new, label[a], low)
        np.minimum.at(new, label[b], low)
        new = new[new]
        if (new == label).all():
            break
        label = new
    return label


def _links(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sorted bucket members in; per member (rep, links, root) out.  A bucket may span batches."""

    def solve(rows: pa.Table) -> pa.RecordBatch:
        col = lambda x: rows.column(x).combine_chunks()
        rep, weight, table = np.asarray(col("rep")), np.asarray(col("weight")), np.asarray(col("t"))
        keys = np.asarray(col("keys").flatten()).reshape(-1, TABLES)
        n = len(rep)
        size = np.asarray(pc.list_value_length(col("v")))
        x = np.zeros((n, int(size.max())))
        for at, m in _by_length(col("v")):
            x[at, : m.shape[1]] = unit_vectors(m)
        count, ea, eb = np.zeros(n, np.int64), [], []
        group = np.asarray(col("g"))
        for a, b in index_pairs(group, np.asarray(col("side"))):
            for t in range(TABLES):  # a pair met in an earlier table was counted there
                live = (t >= table[a]) | (keys[a, t] != keys[b, t])
                if not live.all():
                    a, b = a[live], b[live]
                if not len(a) or t >= table[a].max():
                    break
            same = size[a] == size[b]
            a, b = a[same], b[same]
            near = np.einsum("ij,ij->i", x[a], x[b]) >= COSINE
            a, b = a[near], b[near]
            count += np.bincount(a, weight[b], minlength=n).astype(np.int64) + np.bincount(b, weight[a], minlength=n).astype(np.int64)
            ea.append(a)
            eb.append(b)
        a, b = (np.concatenate([*e, np.zeros(0, np.int64)]).astype(np.int64) for e in (ea, eb))
        root = roots(n, a, b)
        some = np.flatnonzero(count)
        return pa.RecordBatch.from_arrays([pa.array(rep[some]), pa.array(count[some]), pa.array(rep[root[some]])], ["rep", "links", "root"])

    yield from whole_groups(batches, solve)


def link(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """One row per vector: id, n_links, component_id, kept."""
    scratch = Scratch(vectors.sparkSession, "embedding")
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).alias("v"))
    kind = rows.schema["v"].dataType.simpleString()
    digested = rows.mapInArrow(_digests, f"vec_id bigint, v {kind}, digest binary")
    digests = scratch.table(digested.select("vec_id", "digest"), "digests")
    classes = digests.where("digest is not null").groupBy("digest").agg(F.min("vec_id").alias("least"), F.count("*").alias("weight"))
    classes = scratch.table(classes.withColumn("rep", F.monotonically_increasing_id()), "classes")
    members = digests.join(classes, "digest", "left").select("vec_id", "rep", "weight")
    # One row of each class gives its vector: that of the smallest id, of which there may be several.
    first = digested.alias("d").join(classes.alias("c"), (F.col("d.digest") == F.col("c.digest")) & F.col("d.vec_id").eqNullSafe(F.col("c.least")))
    reps = first.select("rep", "weight", "v").dropDuplicates(["rep"])
    hashed = scratch.table(reps.mapInArrow(_buckets, f"rep bigint, weight bigint, v {kind}, keys array<bigint>"), "hashed")
    keyed = hashed.select("rep", F.posexplode("keys").alias("t", "key"))
    busy = scratch.table(keyed.groupBy("t", "key").agg(F.count("*").alias("n")).where("n > 1"), "busy")
    spots = spread(keyed.join(busy, ["t", "key"]), ["t", "key"], "n", "rep", BLOCK).select("rep", "t", "g", "side")
    full = scratch.table(spots, "spots").join(hashed, "rep")
    found = full.repartition("g").sortWithinPartitions("g").mapInArrow(_links, "rep bigint, links bigint, root bigint")
    found = scratch.table(found.groupBy("rep", "root").agg(F.sum("links").alias("links")), "found")
    near = scratch.table(components(found.select(F.col("rep").alias("a"), F.col("root").alias("b")), scratch).select(F.col("node").alias("rep"), "component"), "near")
    least = near.join(classes, "rep").groupBy("component").agg(F.min("least").alias("smallest"))
    near = near.join(least, "component").select("rep", "smallest")
    counts = found.groupBy("rep").agg(F.sum("links").alias("links"))
    extra = classes.select("rep", "least").join(counts, "rep", "left").join(near, "rep", "left").select("rep", "links", F.coalesce("smallest", "least").alias("component"))
    out = members.join(extra, "rep", "left")
    component = F.coalesce("component", "vec_id")
    return out.select(F.col("vec_id").alias(id_col), (F.coalesce("links", F.lit(0)) + F.coalesce(F.col("weight") - 1, F.lit(0))).alias("n_links"), component.alias("component_id"), F.col("vec_id").eqNullSafe(component).alias("kept"))
