"""Recall, precision, F1, selectivity and comparisons of runs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semjoin.functions.tokens import count_column


def _ratio(a: Column, b: Column) -> Column:
    return F.coalesce(F.try_divide(a.cast("double"), b.cast("double")), F.lit(0.0))


def quality(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """truth, reported, hits, recall, precision, f1; a ratio with nothing below is 0, as is F1 of two zeros."""
    flag = lambda df, t, r: df.select("left_id", "right_id").distinct().select("left_id", "right_id", F.lit(t).alias("t"), F.lit(r).alias("r"))
    both = flag(truth, 1, 0).union(flag(pairs, 0, 1)).groupBy("left_id", "right_id").agg(F.max("t").alias("t"), F.max("r").alias("r"))
    n = both.agg(*(F.coalesce(F.sum(x), F.lit(0)).alias(name) for x, name in ((F.col("t"), "truth"), (F.col("r"), "reported"), (F.col("t") * F.col("r"), "hits"))))
    n = n.select("*", _ratio(F.col("hits"), F.col("truth")).alias("recall"), _ratio(F.col("hits"), F.col("reported")).alias("precision"))
    return n.withColumn("f1", _ratio(2 * F.col("recall") * F.col("precision"), F.col("recall") + F.col("precision")))


def true_selectivity(truth: DataFrame, rows_left: int, rows_right: int) -> DataFrame:
    return truth.agg((F.count("*") / F.lit(float(rows_left) * rows_right)).alias("selectivity"))


def benchmark_statistics(left: DataFrame, right: DataFrame, truth: DataFrame) -> DataFrame:
    side = lambda df, name: df.agg(F.count("*").alias(f"rows_{name}"), F.avg(count_column(F.col("text"))).alias(f"width_{name}"))
    s = side(left, "left").crossJoin(side(right, "right")).crossJoin(truth.agg(F.count("*").alias("true_pairs")))
    return s.withColumn("selectivity", F.col("true_pairs") / (F.col("rows_left").cast("double") * F.col("rows_right")))


def compare(summary: DataFrame, method: str, baseline: str, measure: str = "fee") -> DataFrame:
    """(workload, ratio): how many times the baseline's measure exceeds the method's."""
    one = lambda m, name: summary.where(F.col("method") == m).select("workload", F.col(measure).alias(name))
    return one(baseline, "b").join(one(method, "m"), "workload").select("workload", F.try_divide(F.col("b").cast("double"), F.col("m").cast("double")).alias("ratio"))
