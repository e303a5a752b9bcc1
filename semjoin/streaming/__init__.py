"""Semantic joins on streams: arriving rows against standing ones, and two streams within a window of time."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from semjoin.operators.joins import adaptive_join, hybrid_join
from semjoin.state import exists


@dataclass
class Carried:
    """The estimate that goes from micro-batch to micro-batch; it only rises."""

    estimate: float
    batches: list[tuple[int, float]] = field(default_factory=list)


def _kept_estimate(spark: SparkSession, folder: str) -> float:
    """The highest estimate that any finished micro-batch left in the checkpoint."""
    if not exists(spark, folder):
        return 0.0
    return max((json.loads(x["value"])["estimate"] for x in spark.read.text(f"{folder}/*").collect()), default=0.0)


def _keep_estimate(spark: SparkSession, folder: str, number: int, estimate: float) -> None:
    spark.createDataFrame([(json.dumps({"estimate": estimate}),)], "value string").coalesce(1).write.mode("overwrite").text(f"{folder}/{number % 16}")


def stream_semantic_join(arriving: DataFrame, standing: DataFrame, predicate, model, out_path: str, checkpoint: str, start_estimate: float = 0.001, growth: float = 4.0, restart: str = "failed", **trigger) -> tuple[StreamingQuery, Carried]:
    """Every micro-batch of (row_id, text, key) is joined with the standing rows.

    The pairs of a batch replace what an earlier attempt at that batch wrote, so a restarted
    stream has every pair once.  The estimate lies in the checkpoint: a restarted stream goes on with it.
    """
    spark, folder = arriving.sparkSession, f"{checkpoint.rstrip('/')}-estimate"
    carried = Carried(max(start_estimate, _kept_estimate(spark, folder)))

    def each(batch: DataFrame, number: int) -> None:
        if batch.isEmpty():
            return
        run = adaptive_join(batch, standing, predicate, model, carried.estimate, growth, restart)
        reached = max(carried.estimate, run.rounds[-1].estimate if run.rounds else 0.0)
        run.pairs.write.mode("overwrite").parquet(f"{out_path}/batch={number}")
        if reached > carried.estimate or not carried.batches:
            _keep_estimate(spark, folder, number, reached)
        carried.estimate = reached
        carried.batches.append((number, reached))

    query = arriving.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()
    return query, carried


def distinct_texts(stream: DataFrame, time_col: str, delay: str) -> DataFrame:
    """Each text once within the watermark; naive timestamps are read as UTC."""
    return stream.withColumn(time_col, F.col(time_col).cast("timestamp")).withWatermark(time_col, delay).dropDuplicatesWithinWatermark(["text"])


def windowed_counts(stream: DataFrame, time_col: str, width: str, delay: str, slide: str | None = None, by: str | None = None) -> DataFrame:
    """Rows per window: how large the join problems of a windowed join will be."""
    s = stream.withColumn(time_col, F.col(time_col).cast("timestamp")).withWatermark(time_col, delay)
    w = F.window(time_col, width, slide) if slide else F.window(time_col, width)
    return s.groupBy(w, *([by] if by else [])).agg(F.count("*").alias("n_rows"))


def window_candidates(left: DataFrame, right: DataFrame, time_col: str, width: str, delay: str) -> DataFrame:
    """A stream-stream join: pairs of rows of both sides in one tumbling window, late rows within the delay included.

    Both sides have a watermark, so rows are held for the window and the delay only.
    """
    def side(stream, name):
        s = stream.withColumn(time_col, F.col(time_col).cast("timestamp")).withWatermark(time_col, delay)
        return s.select(F.window(time_col, width).alias("window"), F.col("row_id").alias(f"{name}_id"), F.col("text").alias(f"{name}_text"), F.col("key").alias(f"{name}_key"))

    return side(left, "left").join(side(right, "right"), "window")


def stream_stream_semantic_join(left: DataFrame, right: DataFrame, time_col: str, width: str, delay: str, predicate, model, out_path: str, checkpoint: str, batch_left: int = 20, batch_right: int = 20, **trigger) -> StreamingQuery:
    """Pairs of two streams that lie in one window and meet the condition; windows are the equal key of a hybrid join.

    A micro-batch brings the candidate pairs that have become possible with it; its own rows and the
    rows they meet are batched by window.  A batch that is run again replaces what it wrote.
    """
    candidates = window_candidates(left, right, time_col, width, delay)

    def each(batch: DataFrame, number: int) -> None:
        from semjoin.state import Scratch

        kept = Scratch(batch.sparkSession, "stream").table(batch, "candidates")
        if kept.isEmpty():
            return
        start = F.date_format(F.col("window.start"), "yyyy-MM-dd HH:mm:ss").alias("within")
        row = lambda s: kept.select(F.col(f"{s}_id").alias("row_id"), F.col(f"{s}_text").alias("text"), F.col(f"{s}_key").alias("key"), start).distinct()
        run = hybrid_join(row("left"), row("right"), "within", predicate, model, batch_left, batch_right)
        # Rows may meet again in a later batch; only what is new with this one is its own.
        run.pairs.join(kept.select("left_id", "right_id").distinct(), ["left_id", "right_id"], "left_semi").write.mode("overwrite").parquet(f"{out_path}/batch={number}")

    return candidates.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def stateful_batches(stream: DataFrame, by: str, size: int, timeout_ms: int | None = None) -> DataFrame:
    """(by, batch_id, row_ids, texts): rows of a key gather across micro-batches until a batch is full or has waited too long.

    ``stream`` has row_id, text and the key column.  What waits is in the stream's state, at most ``size`` rows a key.
    A time-out needs a trigger that goes on for ever; without one a short batch waits for more rows.
    """
    kind = stream.schema[by].dataType.simpleString()
    out = f"`{by}` {kind}, batch_id bigint, row_ids array<bigint>, texts array<string>"

    def gather(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ids, texts, made = state.get if state.exists else ([], [], 0)
        ids, texts = list(ids), list(texts)
        full = []
        if state.hasTimedOut:
            if ids:
                full.append((key[0], made, ids, texts))
            state.remove()
        else:
            for f in frames:
                ids += f["row_id"].tolist()
                texts += f["text"].tolist()
            while len(ids) >= size:
                full.append((key[0], made, ids[:size], texts[:size]))
                ids, texts, made = ids[size:], texts[size:], made + 1
            state.update((ids, texts, made))
            if timeout_ms is not None:
                state.setTimeoutDuration(timeout_ms)
        yield pd.DataFrame(full, columns=[by, "batch_id", "row_ids", "texts"])

    grouped = stream.select(by, "row_id", "text").groupBy(by)
    return grouped.applyInPandasWithState(gather, out, "ids array<bigint>, texts array<string>, made bigint", "append", GroupStateTimeout.NoTimeout if timeout_ms is None else GroupStateTimeout.ProcessingTimeTimeout)
