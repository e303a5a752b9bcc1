"""Asking a model from the executors; the only Python of the semantic joins."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semjoin import schemas
from semjoin.lm.base import Prompt
from semjoin.lm.cache import AnswerCache, with_hashes
from semjoin.prompts import PromptStyle
from semjoin.state import Scratch

CELLS = 16  # cells per Arrow slice; bounds what a worker holds


def _prompts(rows: list[dict], condition: str, style: PromptStyle, kind: str) -> Iterator[Prompt]:
    for c in rows:
        l, r = c["left_items"], c["right_items"]  # noqa: E741
        a, b = [x["text"] for x in l], [x["text"] for x in r]
        text = style.pair(condition, a[0], b[0]) if kind == "pair" else style.block(condition, a, b) if kind == "block" else style.single(condition, a)
        ids = lambda items: tuple(x["row_id"] for x in items)
        yield Prompt(text, kind, tuple(x["key"] for x in l), tuple(x["key"] for x in r), ids(l), ids(r))


def ask_cached(cells: DataFrame, model, condition: str, style: PromptStyle, kind: str, cache: AnswerCache, scratch: Scratch) -> DataFrame:
    """As ``ask``, with answers that are recorded taken from the cache (they cost nothing) and new ones recorded.

    Equal prompts are asked once.  Cells are written, for they are read twice.
    """
    spark = cells.sparkSession
    ids = lambda c: F.transform(c, lambda x: x["row_id"])
    keyed = scratch.table(cells.select("left_batch", "right_batch", "left_items", "right_items"), "cells")
    hashes = scratch.table(with_hashes(keyed, lambda rows: _prompts(rows, condition, style, kind)), "hashes")
    known = cache.answers(spark)
    new = hashes.join(known, "prompt", "left_anti").groupBy("prompt").agg(F.min(F.struct("left_batch", "right_batch")).alias("c"))
    new = scratch.table(new.select("prompt", "c.*"), "new")
    if not new.isEmpty():
        asked = ask(keyed.join(new, ["left_batch", "right_batch"], "left_semi"), model, condition, style, kind)
        cache.record(asked.join(new, ["left_batch", "right_batch"]))
    paid = hashes.join(new.withColumn("paid", F.lit(True)), ["prompt", "left_batch", "right_batch"], "left")
    out = paid.join(cache.answers(spark), "prompt").join(keyed, ["left_batch", "right_batch"])
    free = lambda name, zero: F.when(F.col("paid"), F.col(name)).otherwise(F.lit(zero)).alias(name)
    return out.select("left_batch", "right_batch", ids(F.col("left_items")).alias("left_ids"), ids(F.col("right_items")).alias("right_ids"), "answer", "stopped", free("tokens_read", 0).cast("int").alias("tokens_read"), free("tokens_written", 0).cast("int").alias("tokens_written"), free("latency_ms", 0.0))


def ask(cells: DataFrame, model, condition: str, style: PromptStyle, kind: str = "block", parallelism: int | None = None) -> DataFrame:
    """One answer a cell, in the ANSWER schema.  Written once by the caller: every evaluation would be charged."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            step = 1000 if kind == "pair" else CELLS
            for lo in range(0, batch.num_rows, step):
                rows = batch.slice(lo, step).to_pylist()
                got = list(model.complete(_prompts(rows, condition, style, kind)))
                cols = [
                    pa.array([c["left_batch"] for c in rows], pa.int64()), pa.array([c["right_batch"] for c in rows], pa.int64()),
                    pa.array([[x["row_id"] for x in c["left_items"]] for c in rows], pa.list_(pa.int64())), pa.array([[x["row_id"] for x in c["right_items"]] for c in rows], pa.list_(pa.int64())),
                    pa.array([a.text for a in got], pa.string()), pa.array([a.stopped for a in got], pa.bool_()),
                    pa.array([a.tokens_read for a in got], pa.int32()), pa.array([a.tokens_written for a in got], pa.int32()), pa.array([a.latency_ms for a in got], pa.float64()),
                ]
                yield pa.RecordBatch.from_arrays(cols, [x.split()[0] for x in schemas.ANSWER.split(", ")])

    cells = cells.select("left_batch", "right_batch", "left_items", "right_items")
    if parallelism:
        cells = cells.repartition(parallelism, F.xxhash64("left_batch", "right_batch"))
    return cells.mapInArrow(run, schemas.ANSWER)


def ledger_of(answers: DataFrame, run_id: str, number: int, overflow, malformed=None) -> DataFrame:
    flag = malformed if malformed is not None else F.lit(False)
    return answers.select(F.lit(run_id).alias("run_id"), F.lit(number).alias("round"), "left_batch", "right_batch", "tokens_read", "tokens_written", "latency_ms", overflow.alias("overflow"), flag.alias("malformed"))
