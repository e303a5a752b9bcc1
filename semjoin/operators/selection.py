"""What is done to the sides before a model is asked, self joins, as-of joins, and a semantic aggregate."""

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semjoin.functions.tokens import count_column
from semjoin.types import JoinRun


def candidates_of(rows: DataFrame, pre_filter: Column | str | None = None, min_tokens: int = 1, max_tokens: int | None = None, counter: str = "words") -> DataFrame:
    """Rows that are worth a call: those that the relational filter keeps (null counts as false) and whose text has so many tokens.

    All of it is ordinary predicates, so it reaches the scan; null and empty texts go with ``min_tokens`` 1.
    """
    if pre_filter is not None:
        rows = rows.where(pre_filter)
    if min_tokens < 1 and max_tokens is None:
        return rows
    n = count_column(F.col("text"), counter)
    keep = F.col("text").isNotNull() & (n >= min_tokens)
    return rows.where(keep if max_tokens is None else keep & (n <= max_tokens))


def filtered_join(join, left: DataFrame, right: DataFrame, *args, pre_filter_left: Column | str | None = None, pre_filter_right: Column | str | None = None, min_tokens: int = 1, max_tokens: int | None = None, **options) -> JoinRun:
    """Any of the joins on the rows that pass the filters of their side."""
    return join(candidates_of(left, pre_filter_left, min_tokens, max_tokens), candidates_of(right, pre_filter_right, min_tokens, max_tokens), *args, **options)


def self_join(rows: DataFrame, predicate, model, size: int, style=None, on_overflow: str = "fail", parallelism: int | None = None) -> JoinRun:
    """Every unordered pair of rows of one table, each asked about once: (left_id, right_id) with left_id < right_id.

    Batches meet only batches from their own number on; the pairs of a batch with itself that are reported
    twice, or with the row itself, are dropped.  The condition must be symmetric.
    """
    import time

    from semjoin.functions import parse
    from semjoin.operators import joins
    from semjoin.operators.ask import ask, ledger_of
    from semjoin.operators.batching import buckets_for, make_batches, make_cells
    from semjoin.plans.profile import profile_tables
    from semjoin.prompts import PromptStyle
    from semjoin.state import Scratch

    began, style, run_id = time.perf_counter(), style or PromptStyle(), joins._new_run("self")
    scratch = Scratch(rows.sparkSession, run_id)
    p, _ = profile_tables(rows, rows.limit(0), style.counter)
    b = scratch.table(make_batches(rows, size, style.counter, buckets_for(p.rows)), "batches")
    n = -(-p.rows // size)
    cells = make_cells(b, b, joins._bytes_bound(p), parallelism=joins.tasks_for(rows, model, parallelism), counts=(n, n)).where("left_batch <= right_batch")
    answers = scratch.table(ask(cells, model, predicate.text, style, "block"), "answers")
    complete = parse.is_complete(F.col("answer"), F.col("stopped"), "stop_reason" if model.profile.stop_word else "text")
    cut = answers.where(~complete).count()
    found = joins._resolve(answers.where(complete), style, rows, rows).where("left_id <> right_id")
    found = found.select(F.least("left_id", "right_id").alias("left_id"), F.greatest("left_id", "right_id").alias("right_id")).distinct()
    run = JoinRun(run_id, "self", found, ledger_of(answers, run_id, 0, ~complete), seconds=time.perf_counter() - began)
    if cut and on_overflow == "fail":
        raise joins.OverflowSignal(cut, run)
    return run


def as_of(left: DataFrame, right: DataFrame, on: str, left_time: str, right_time: str, right_id: str = "row_id") -> DataFrame:
    """(all of left, right_id): the last right row of an equal ``on`` whose time isn't after the left row's; null if there is none.

    One sort of both sides together, by key and time, not a range join: a right row is carried to the left rows behind it.
    """
    marks = right.select(F.col(on).alias("__on"), F.col(right_time).alias("__at"), F.col(right_id).alias("__right"), F.lit(None).alias("__row"))
    rows = left.select(F.col(on).alias("__on"), F.col(left_time).alias("__at"), F.lit(None).cast(right.schema[right_id].dataType).alias("__right"), F.struct(*left.columns).alias("__row"))
    both = marks.withColumn("__row", F.col("__row").cast(rows.schema["__row"].dataType)).unionByName(rows)
    order = W.partitionBy("__on").orderBy("__at", F.col("__row").isNotNull(), "__right").rowsBetween(W.unboundedPreceding, W.currentRow)
    carried = both.withColumn("__last", F.last("__right", ignorenulls=True).over(order)).where("__row is not null")
    return carried.select("__row.*", F.when(F.col("__on").isNotNull(), F.col("__last")).alias("right_id"))


def register_aggregates(spark) -> None:
    """``fee_sum(read, written, price_read, price_write)`` and ``f1_of(hits, reported, truth)`` as grouped functions in SQL."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("double")
    def fee_sum(read: pd.Series, written: pd.Series, price_read: pd.Series, price_write: pd.Series) -> float:
        return float((read * price_read + written * price_write).sum() / 1000)

    @pandas_udf("double")
    def f1_of(hits: pd.Series, reported: pd.Series, truth: pd.Series) -> float:
        both = reported.sum() + truth.sum()
        return float(2 * hits.sum() / both) if both else 0.0

    spark.udf.register("fee_sum", fee_sum)
    spark.udf.register("f1_of", f1_of)
