"""Groups of rows compared in pairs: hot ones in blocks, all in bounded steps."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PAIRS = 200_000  # compared at once


def spread(members: DataFrame, group: list[str], size: str, member: str, block: int) -> DataFrame:
    """Adds ``g`` and ``side``: a group of more than ``block`` members becomes a task for every pair of its blocks.

    Two members of a group meet under exactly one ``g``: within a block (side -1), or
    between two (sides 0 and 1).
    """
    df = members.withColumn("blocks", F.ceil(F.col(size) / block).cast("int"))
    df = df.withColumn("own", F.pmod(F.xxhash64(member), F.col("blocks")).cast("int"))
    df = df.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    df = df.withColumn("g", F.xxhash64(*group, F.least("own", "other"), F.greatest("own", "other")))
    return df.withColumn("side", F.expr("case when own = other then -1 when own < other then 0 else 1 end").cast("int")).drop("blocks", "own", "other")


def index_pairs(group: np.ndarray, side: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs within each run of equal ``group``: between sides 0 and 1, or all where side is -1."""
    first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    size = np.diff(np.r_[first, len(group)])
    i = np.arange(len(group))
    todo = np.repeat(first + size, size) - i - 1  # partners after each member
    total = np.cumsum(todo)
    at = 0
    while at < len(i):
        stop = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + PAIRS, "right")))
        k = todo[at:stop]
        a = np.repeat(i[at:stop], k)
        b = a + 1 + (np.arange(len(a)) - np.repeat(np.cumsum(k) - k, k))
        keep = (side[a] < 0) | (side[a] != side[b])
        yield a[keep], b[keep]
        at = stop


def whole_groups(batches: Iterable[pa.RecordBatch], solve: Callable[[pa.Table], pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Calls ``solve`` on tables of whole groups; rows come sorted by ``g`` and a group may span batches."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        g = np.asarray(batch.column(batch.schema.get_field_index("g")))
        cut = int(np.searchsorted(g, g[-1]))  # the last group may go on
        if cut:
            held.append(batch.slice(0, cut))
            yield solve(pa.Table.from_batches(held).combine_chunks())
            held = []
        held.append(batch.slice(cut))
    if held:
        yield solve(pa.Table.from_batches(held).combine_chunks())
