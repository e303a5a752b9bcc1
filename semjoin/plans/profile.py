"""Table statistics that the planner needs: one aggregate over both sides."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semjoin.functions.tokens import count_column
from semjoin.types import TableProfile


def profile_table(side: str, rows: DataFrame, counter: str = "words") -> DataFrame:
    w = rows.select(count_column(F.col("text"), counter).alias("w"))
    return w.agg(F.count("*").alias("n_rows"), F.avg("w").alias("width_mean"), F.max("w").alias("width_max"), F.percentile_approx("w", 0.95).alias("width_p95")).select(F.lit(side).alias("side"), "*")


def profile_tables(left: DataFrame, right: DataFrame, counter: str = "words", overhead: int = 0) -> tuple[TableProfile, TableProfile]:
    """Both profiles; ``overhead`` tokens a row are what its number costs in a prompt."""
    both = profile_table("left", left, counter).unionByName(profile_table("right", right, counter))
    got = {r["side"]: r for r in both.collect()}
    made = lambda r: TableProfile(r["n_rows"], (r["width_mean"] or 0.0) + overhead, (r["width_max"] or 0) + overhead, (r["width_p95"] or 0) + overhead)
    return made(got["left"]), made(got["right"])
