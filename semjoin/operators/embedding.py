"""Nearest-neighbour join of embeddings, the cheap baseline, and its use as a prefilter."""

from __future__ import annotations

import time
import uuid
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semjoin import schemas
from semjoin.functions.tokens import count_column
from semjoin.operators.batching import BROADCAST_BYTES
from semjoin.state import Scratch
from semjoin.types import JoinRun

BLOCK = 2048  # vectors a block


@dataclass(frozen=True)
class EmbedderProfile:
    price: float = 0.002  # cents per 1,000 tokens read


@dataclass(frozen=True)
class HashingEmbedder:
    """Character n-gram counts, hashed to ``size`` dimensions and normalised."""

    size: int = 256
    gram: int = 3
    profile: EmbedderProfile = EmbedderProfile()

    def vectors(self, texts: list[str | None]) -> np.ndarray:
        """One row a text; the grams of all texts are hashed together."""
        lower = [f" {(t or '').lower()} " for t in texts]
        size = np.fromiter(map(len, lower), np.int64, len(lower))
        points = np.frombuffer("".join(lower).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
        n = max(0, len(points) - self.gram + 1)
        h = np.zeros(n, np.uint64)
        for k in range(self.gram):
            h = h * np.uint64(0x9E3779B97F4A7C15) + points[k : k + n]
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(32)
        text = np.repeat(np.arange(len(lower)), size)
        inside = text[:n] == text[self.gram - 1 :]
        at = text[:n][inside] * self.size + (h[inside] % np.uint64(self.size)).astype(np.int64)
        v = np.bincount(at, minlength=len(lower) * self.size).reshape(len(lower), self.size).astype(np.float64)
        norm = np.linalg.norm(v, axis=1, keepdims=True)
        return v / np.where(norm > 0, norm, 1)

    def embed(self, rows: DataFrame) -> DataFrame:
        """(row_id, vector); the caller writes it once, every evaluation would be charged."""
        make, size = self.vectors, self.size

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for lo in range(0, batch.num_rows, 500):
                    b = batch.slice(lo, 500)
                    v = make(b.column(1).to_pylist())
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(v) + 1, dtype=np.int32) * size), pa.array(v.ravel()))
                    yield pa.RecordBatch.from_arrays([b.column(0), lists], ["row_id", "vector"])

        return rows.select("row_id", "text").mapInArrow(run, "row_id bigint, vector array<double>")


def _blocks(vectors: DataFrame, name: str, n: int) -> DataFrame:
    """Vectors packed as one matrix of doubles a block; unusable vectors (null, empty, zero) are left out."""
    usable = vectors.where("size(vector) > 0 and exists(vector, x -> x <> 0)")
    block = F.pmod(F.xxhash64("row_id"), F.lit(max(1, -(-n // BLOCK)))).cast("int")
    g = usable.groupBy(block.alias(f"{name}_block")).agg(F.sort_array(F.collect_list(F.struct("row_id", F.col("vector").cast("array<double>").alias("vector")))).alias("x"))
    return g.select(f"{name}_block", F.col("x.row_id").alias(f"{name}_ids"), F.flatten("x.vector").alias(f"{name}_values"))


def _best(top: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            col = {n: batch.column(i) for i, n in enumerate(batch.schema.names)}
            for k in range(batch.num_rows):
                a, b = (np.asarray(col[f"{s}_ids"][k].values) for s in "lr")
                unit = []
                for s, ids in (("l", a), ("r", b)):
                    m = np.asarray(col[f"{s}_values"][k].values).reshape(len(ids), -1)
                    unit.append(m / np.linalg.norm(m, axis=1, keepdims=True))
                sim = np.round(unit[0] @ unit[1].T, 12)
                if top >= len(b):
                    at = np.argsort(-sim, axis=1, kind="stable")
                else:  # ids ascend, so a stable order breaks ties towards the smaller id
                    at = np.argsort(-sim, axis=1, kind="stable")[:, :top]
                n = at.shape[1]
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(a, n)), pa.array(b[at].ravel()), pa.array(np.take_along_axis(sim, at, 1).ravel())], ["left_id", "right_id", "similarity"])

    return run


def nearest(left: DataFrame, right: DataFrame, top: int = 1, rows: tuple[int, int] | None = None) -> DataFrame:
    """(left_id, right_id, similarity): the ``top`` most similar right rows of every left row, ties to the smaller id.

    Each pair of blocks is one matrix product; only its ``top`` per row leave it.  A small right
    side is broadcast, otherwise blocks meet on a square of tiles.
    """
    n, m = rows or (left.count(), right.count())
    size = right.agg(F.coalesce(F.max(F.size("vector")), F.lit(0))).first()[0]
    l, r = _blocks(left, "l", n), _blocks(right, "r", m)  # noqa: E741
    if m * max(size, 0) * 8 <= BROADCAST_BYTES:
        pairs = l.crossJoin(F.broadcast(r))
    else:
        tiles = 8
        spread = F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))
        pairs = l.withColumn("i", F.col("l_block") % tiles).withColumn("j", spread).join(r.withColumn("j", F.col("r_block") % tiles).withColumn("i", spread), ["i", "j"])
    found = pairs.select("l_ids", "l_values", "r_ids", "r_values").mapInArrow(_best(top), "left_id bigint, right_id bigint, similarity double")
    if top == 1:
        best = found.groupBy("left_id").agg(F.max_by(F.struct("right_id", "similarity"), F.struct("similarity", -F.col("right_id"))).alias("b"))
        return best.select("left_id", "b.right_id", "b.similarity")
    rank = F.row_number().over(W.partitionBy("left_id").orderBy(F.desc("similarity"), "right_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= top).drop("rank")


def embedded(left: DataFrame, right: DataFrame, embedder, name: str = "embedded") -> tuple[DataFrame, DataFrame]:
    """The vectors of both sides, made and written once."""
    if embedder is None:
        return left, right
    scratch = Scratch(left.sparkSession, name)
    return scratch.table(embedder.embed(left), "left"), scratch.table(embedder.embed(right), "right")


def embedding_join(left: DataFrame, right: DataFrame, embedder=None, direction: str = "left", min_similarity: float | None = None) -> JoinRun:
    """Every row with its most similar row of the other side.  With an embedder the sides have texts, else vectors."""
    began, run_id = time.perf_counter(), f"embedding-{uuid.uuid4().hex[:8]}"
    a, b = embedded(left, right, embedder, run_id)
    forward = lambda: nearest(a, b)
    backward = lambda: nearest(b, a).select(F.col("right_id").alias("left_id"), F.col("left_id").alias("right_id"), "similarity")
    if direction == "left":
        found = forward()
    elif direction == "right":
        found = backward()
    elif direction == "both":
        found = forward().union(backward()).dropDuplicates(["left_id", "right_id"])
    elif direction == "mutual":
        found = forward().join(backward().select("left_id", "right_id"), ["left_id", "right_id"], "left_semi")
    else:
        raise ValueError(f"unknown direction {direction!r}")
    if min_similarity is not None:
        found = found.where(F.col("similarity") >= min_similarity)
    spark = left.sparkSession
    ledger = spark.createDataFrame([], schemas.LEDGER)
    if embedder:  # every row is read once, nothing is written
        rows = left.select("text").unionByName(right.select("text"))
        ledger = rows.agg(F.coalesce(F.sum(count_column(F.col("text"))), F.lit(0)).cast("int").alias("tokens_read")).select(F.lit(run_id).alias("run_id"), F.lit(0).alias("round"), F.lit(0).cast("long").alias("left_batch"), F.lit(0).cast("long").alias("right_batch"), "tokens_read", F.lit(0).alias("tokens_written"), F.lit(0.0).alias("latency_ms"), F.lit(False).alias("overflow"), F.lit(False).alias("malformed"))
    return JoinRun(run_id, "embedding", found.select("left_id", "right_id"), ledger, seconds=time.perf_counter() - began)


def embedding_prefilter(left: DataFrame, right: DataFrame, embedder=None, top_k: int = 5, min_similarity: float | None = None) -> DataFrame:
    """Candidate pairs for ``pairwise_join(candidates=...)``; lossy where similarity is the wrong signal."""
    a, b = embedded(left, right, embedder)
    found = nearest(a, b, top_k)
    if min_similarity is not None:
        found = found.where(F.col("similarity") >= min_similarity)
    return found.select("left_id", "right_id")
