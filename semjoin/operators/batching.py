"""Dense row indexes without a global sort, batches, and the grid of cells."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semjoin.functions.tokens import count_column

BROADCAST_BYTES = 32 << 20
GROUP_CELLS = 64  # of one group in one task


def buckets_for(rows: int) -> int:
    return max(8, math.ceil(rows / 20_000))


def with_row_index(df: DataFrame, key: str = "row_id", buckets: int = 8, order: str = "hash", keep=None) -> DataFrame:
    """Adds ``row_index`` 0..n-1: by hash bucket, or (``order="key"``) in order of the key.

    Rows are numbered inside buckets; what precedes a bucket is a running sum over at most
    ``buckets`` counts.  Both depend on the rows alone, so a retried task numbers alike.  ``keep`` writes
    the rows once they are numbered, and buckets are counted in what it returns: else ``df`` is evaluated twice.
    """
    if order == "hash":
        bucket = F.pmod(F.xxhash64(key), F.lit(buckets)).cast("int")
    elif order == "key":
        bounds = df.agg(F.percentile_approx(key, [i / buckets for i in range(1, buckets)], 10_000)).first()[0] or [] if buckets > 1 else []
        bucket = F.size(F.filter(F.array(*[F.lit(b) for b in sorted(set(bounds))]), lambda b: b < F.col(key))) if bounds else F.lit(0)
    else:
        raise ValueError(f"unknown order {order!r}")
    df = df.withColumn("bucket", bucket)
    number = F.row_number().over(W.partitionBy("bucket").orderBy(key)) - 1
    if keep:
        df = keep(df.withColumn("number", number))
    counts = df.groupBy("bucket").agg(F.count("*").alias("n"))
    before = counts.select("bucket", F.coalesce(F.sum("n").over(W.orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    return (df if keep else df.withColumn("number", number)).join(F.broadcast(before), "bucket").withColumn("row_index", F.col("number") + F.col("before")).drop("bucket", "number", "before")


def _items(grouped, order_by: str) -> DataFrame:
    item = F.struct(F.col(order_by).cast("int").alias("pos"), "row_id", "text", "key", "tokens")
    return grouped.agg(F.sort_array(F.collect_list(item)).alias("items"), F.sum("tokens").alias("tokens"))


def _index_within(rows: DataFrame, by: str, buckets: int = 32) -> DataFrame:
    """``row_index`` 0..n-1 within each value of ``by``; a hot value is numbered in buckets, not in one task."""
    rows = rows.withColumn("bucket", F.pmod(F.xxhash64("row_id"), F.lit(buckets)).cast("int"))
    counts = rows.groupBy(by, "bucket").agg(F.count("*").alias("n"))
    before = counts.select(by, "bucket", F.coalesce(F.sum("n").over(W.partitionBy(by).orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    number = F.row_number().over(W.partitionBy(by, "bucket").orderBy("row_id")) - 1
    return rows.withColumn("number", number).join(before, [by, "bucket"]).withColumn("row_index", F.col("number") + F.col("before")).drop("bucket", "number", "before")


def indexed(rows: DataFrame, counter: str = "words", buckets: int = 8, order: str = "hash", by: str | None = None, keep=None) -> DataFrame:
    """Rows with ``tokens`` and ``row_index``, from which batches of any size are cut."""
    rows = rows.withColumn("tokens", count_column(F.col("text"), counter))
    return _index_within(rows, by) if by is not None else with_row_index(rows, "row_id", buckets, order, keep)


def cut_batches(rows: DataFrame, size: int, by: str | None = None, only: list[int] | None = None, tasks: int | None = None) -> DataFrame:
    """Batches of indexed rows, or of those only that are named; ``tasks``: formed in so many tasks, and not moved again to be dealt."""
    if size < 1:
        raise ValueError("a batch holds at least one row")
    rows = rows.withColumn("batch_id", F.floor(F.col("row_index") / size).cast("long")).withColumn("pos", F.col("row_index") % size + 1)
    if only is not None:
        rows = rows.where(F.col("batch_id").isin(only))
    if tasks:
        rows = rows.repartition(tasks, *([by] if by else []), "batch_id")
    return _items(rows.groupBy(*([by] if by else []), "batch_id"), "pos")


def make_batches(rows: DataFrame, size: int, counter: str = "words", buckets: int = 8, order: str = "hash", by: str | None = None, tasks: int | None = None) -> DataFrame:
    """(batch_id, items, tokens), the last one ragged; ``by`` keeps groups of that column apart, as (by, batch_id)."""
    return cut_batches(indexed(rows, counter, buckets, order, by), size, by, tasks=tasks)


def pack_batches(rows: DataFrame, token_limit: int, counter: str = "words", buckets: int = 8) -> DataFrame:
    """(batch_id, items, tokens) with at most ``token_limit`` tokens each, whatever the widths.

    In a bucket a batch takes the rows whose preceding tokens lie in one interval of
    limit - widest row, so it exceeds that interval by one row at most.
    """
    rows = rows.withColumn("tokens", count_column(F.col("text"), counter)).withColumn("bucket", F.pmod(F.xxhash64("row_id"), F.lit(buckets)))
    widest = rows.agg(F.max("tokens")).first()[0] or 0
    if widest > token_limit:
        raise ValueError(f"a row of {widest} tokens exceeds the limit of {token_limit}")
    before = F.coalesce(F.sum("tokens").over(W.partitionBy("bucket").orderBy("row_id").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    rows = rows.withColumn("part", F.floor(before / max(1, token_limit - widest + 1)).cast("long"))
    pos = F.row_number().over(W.partitionBy("bucket", "part").orderBy("row_id"))
    rows = rows.withColumn("pos", pos).withColumn("batch_id", F.col("part") * buckets + F.col("bucket"))
    return _items(rows.groupBy("batch_id"), "pos")


def make_cells(left: DataFrame, right: DataFrame, small_bytes: int | None = None, tiles: int = 8, on: str | None = None, parallelism: int | None = None, counts: tuple[int, int] | None = None) -> DataFrame:
    """All pairs of batches: (left_batch, left_items, right_batch, right_items).

    ``small_bytes`` is a bound of the right side's size: up to ``BROADCAST_BYTES`` it is sent
    to all tasks and no cell is shuffled.  Beyond that both sides are replicated on a square
    of tiles and every tile forms its own cells.  ``on`` pairs batches of equal groups only; a group
    of many cells is dealt to several tasks.

    With ``parallelism`` and the numbers of batches (``counts``) cells are dealt to so many tasks before they are
    formed, by left batches and, where those are too few, by ranges of right ones: small batches would
    otherwise end in one task, whose calls follow one another.
    """
    l = left.select(*([F.col(on)] if on else []), F.col("batch_id").alias("left_batch"), F.col("items").alias("left_items"))  # noqa: E741
    r = right.select(*([F.col(on)] if on else []), F.col("batch_id").alias("right_batch"), F.col("items").alias("right_items"))
    if on:
        count = lambda x, n: x.groupBy(on).agg(F.count("*").alias(n))
        ways = count(l, "nl").join(count(r, "nr"), on).select(on, F.ceil(F.col("nl") * F.col("nr") / GROUP_CELLS).cast("int").alias("ways"))
        ways = ways.withColumn("ways", F.least("ways", F.lit(4096)))
        l = l.join(ways, on).withColumn("way", F.pmod(F.xxhash64("left_batch"), F.col("ways")).cast("int")).drop("ways")  # noqa: E741
        r = r.join(ways, on).withColumn("way", F.explode(F.sequence(F.lit(0), F.col("ways") - 1))).drop("ways")
        return l.join(r, [on, "way"]).drop("way")
    tiles = max(tiles, math.isqrt(parallelism or 1))
    if small_bytes is not None and small_bytes <= BROADCAST_BYTES:
        if not parallelism or not counts or not all(counts):
            return l.crossJoin(F.broadcast(r))
        ways = min(counts[1], -(-parallelism // counts[0]))
        n = min(parallelism, counts[0] * ways)
        l = l.withColumn("way", F.explode(F.sequence(F.lit(0), F.lit(ways - 1))))  # noqa: E741
        l = l.repartitionById(n, F.pmod(F.col("left_batch") * ways + F.col("way"), F.lit(n)).cast("int"))  # noqa: E741
        return l.join(F.broadcast(r.withColumn("way", F.pmod(F.col("right_batch"), F.lit(ways)).cast("int"))), "way").drop("way")
    place = lambda name: F.pmod(F.xxhash64(name), F.lit(tiles)).cast("int")
    spread = F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))
    l = l.withColumn("tile_row", place("left_batch")).withColumn("tile_col", spread)  # noqa: E741
    r = r.withColumn("tile_col", place("right_batch")).withColumn("tile_row", spread)
    return l.join(r, ["tile_row", "tile_col"]).drop("tile_row", "tile_col")
