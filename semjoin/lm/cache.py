"""Answers kept as a table by the hash of their prompt: recording, replaying, and not paying twice.

The table is Parquet on a path; every run that asks something new adds a part.  With a model, prompts that
are recorded are answered from the table and the others are asked and recorded.  Without one the table is all there
is, and a prompt that it doesn't hold raises.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semjoin.state import delete, exists
from semjoin.types import ModelProfile

ANSWERS = "prompt string, answer string, stopped boolean, tokens_read int, tokens_written int, latency_ms double"


class NotRecorded(KeyError):
    """A prompt that the table of answers doesn't hold, and no model to ask."""


@dataclass(frozen=True)
class AnswerCache:
    path: str

    def answers(self, spark: SparkSession) -> DataFrame:
        """One row per prompt; of an answer recorded twice (two runs at a time) the first in order."""
        if not exists(spark, self.path):
            return spark.createDataFrame([], ANSWERS)
        kept = spark.read.schema(ANSWERS).parquet(f"{self.path.rstrip('/')}/*")
        value = F.struct("answer", "stopped", "tokens_read", "tokens_written", "latency_ms")
        return kept.groupBy("prompt").agg(F.min(value).alias("v")).select("prompt", "v.*")

    def record(self, asked: DataFrame) -> None:
        asked.select(*[x.split()[0] for x in ANSWERS.split(", ")]).write.parquet(f"{self.path.rstrip('/')}/{uuid.uuid4().hex[:12]}")

    def forget(self, spark: SparkSession) -> None:
        delete(spark, self.path)


@dataclass(frozen=True)
class RecordedOnly:
    """In a model's place where all answers come from a cache."""

    profile: ModelProfile = ModelProfile()

    def complete(self, prompts):
        raise NotRecorded("a prompt is not recorded")


def with_hashes(cells: DataFrame, make) -> DataFrame:
    """(left_batch, right_batch, prompt): the hash of every cell's prompt; ``make`` yields the prompts of rows."""
    from semjoin.lm.models import ReplayModel

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 64):
                part = batch.slice(lo, 64)
                hashes = [ReplayModel.key(p.text) for p in make(part.to_pylist())]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(hashes, pa.string())], ["left_batch", "right_batch", "prompt"])

    return cells.select("left_batch", "right_batch", "left_items", "right_items").mapInArrow(run, "left_batch bigint, right_batch bigint, prompt string")
