"""A simulator of joins call by call, without a model.

Sizes are floored, batches are whole, and a call whose expected output exceeds what its prompt
leaves of the budget is void: its prompt and the output up to the limit are paid for.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semjoin.functions import costs


@dataclass(frozen=True)
class Setting:
    """Defaults of the simulated experiments; prices are dollars per 1,000 tokens."""

    rows_left: int = 5000
    rows_right: int = 5000
    width_left: int = 30
    width_right: int = 30
    width_match: int = 2
    selectivity: float = 0.001
    instruction_tokens: int = 50
    context_tokens: int = 8192
    read_price: float = 0.03
    write_price: float = 0.06
    growth: float = 4.0
    start_share: float = 0.01  # of the true selectivity, where the adaptive join starts

    @property
    def budget(self) -> int:
        return self.context_tokens - self.instruction_tokens


METHODS = ("pairwise", "conservative", "informed", "adaptive")


def floored_sizes(s: Setting, estimate: float) -> tuple[int, int]:
    """The floored left size, then the most right rows that fit beside it."""
    a = max(1, min(s.rows_left, math.floor(costs.left_size(s.width_left, s.width_right, s.width_match, estimate, s.budget) + 1e-9)))
    b = costs.right_size_for(a, s.width_left, s.width_right, s.width_match, estimate, s.budget)
    return a, max(1, min(s.rows_right, math.floor(b + 1e-9)))


def overflows(s: Setting, a: int, b: int) -> bool:
    return costs.expected_output(a, b, s.width_match, s.selectivity) > s.budget - a * s.width_left - b * s.width_right + 1e-9


def void_calls(s: Setting, start: float | None = None) -> tuple[list[tuple[float, int, int]], tuple[float, int, int]]:
    """(estimate, sizes) of the calls that overflow, and of the round that doesn't."""
    estimate = start if start is not None else s.selectivity * s.start_share
    void = []
    while True:
        a, b = floored_sizes(s, estimate)
        if estimate >= 1 or not overflows(s, a, b):
            return void, (estimate, a, b)
        void.append((estimate, a, b))
        estimate = min(1.0, estimate * s.growth)


def plans_of(s: Setting, method: str) -> tuple[list[tuple[int, int]], tuple[int, int]]:
    if method == "pairwise":
        return [], (1, 1)
    if method == "conservative":
        return [], floored_sizes(s, 1.0)
    if method == "informed":
        return [], floored_sizes(s, s.selectivity)
    if method == "adaptive":
        void, (_, a, b) = void_calls(s)
        return [(x, y) for _, x, y in void], (a, b)
    raise ValueError(f"unknown method {method!r}")


def simulate(spark: SparkSession, settings: list[tuple[float, Setting]], methods: tuple[str, ...] = METHODS) -> DataFrame:
    """(x, method, calls, tokens_read, tokens_written, fee): one row a setting and method.

    Calls are rows of classes: the inner ones, and the ragged ones of the last batch of
    either side, each with how often it occurs; so a sweep over any table size is small.
    """
    rows = []
    for x, s in settings:
        for m in methods:
            void, (a, b) = plans_of(s, m)
            rows.append((float(x), m, s.rows_left, s.rows_right, a, b, s.width_left, s.width_right, s.width_match, float(s.selectivity), s.instruction_tokens, s.budget, m == "pairwise", False, float(s.read_price), float(s.write_price)))
            rows += [(float(x), m, p, q, p, q, s.width_left, s.width_right, s.width_match, float(s.selectivity), s.instruction_tokens, s.budget, False, True, float(s.read_price), float(s.write_price)) for p, q in void]
    schema = "x double, method string, rows_left long, rows_right long, a long, b long, w1 long, w2 long, w3 long, sigma double, p long, budget long, pairwise boolean, void boolean, read_price double, write_price double"
    return replay(spark.createDataFrame(rows, schema))


def replay(plans: DataFrame) -> DataFrame:
    """Plays the calls of planned runs; see ``simulate`` for the columns."""
    ragged = lambda n, size: F.array(F.struct(F.floor(F.col(n) / F.col(size)).alias("times"), F.col(size).alias("rows")), F.struct(F.when(F.col(n) % F.col(size) > 0, 1).otherwise(0).cast("long").alias("times"), (F.col(n) % F.col(size)).alias("rows")))
    calls = plans.withColumn("l", F.explode(ragged("rows_left", "a"))).withColumn("r", F.explode(ragged("rows_right", "b")))
    n = F.col("l.times") * F.col("r.times")
    read = F.col("p") + F.col("l.rows") * F.col("w1") + F.col("r.rows") * F.col("w2")
    room = F.col("budget") + F.col("p") - read
    out = F.when(F.col("pairwise"), F.lit(1.0)).otherwise(F.least(F.col("l.rows") * F.col("r.rows") * F.col("sigma") * F.col("w3"), F.col("void").cast("int") * room + (1 - F.col("void").cast("int")) * F.lit(1e18)))
    calls = calls.where("l.times > 0 and r.times > 0").select("x", "method", n.alias("n"), (n * read).alias("read"), (n * out).alias("written"), "read_price", "write_price")
    g = calls.groupBy("x", "method").agg(F.sum("n").alias("calls"), F.sum("read").alias("tokens_read"), F.sum("written").alias("written"), F.first("read_price").alias("rp"), F.first("write_price").alias("wp"))
    return g.select("x", "method", "calls", "tokens_read", F.round("written", 3).alias("tokens_written"), F.round((F.col("tokens_read") * F.col("rp") + F.col("written") * F.col("wp")) / 1000, 2).alias("fee"))


def sweep(base: Setting, name: str, values) -> list[tuple[float, Setting]]:
    return [(float(v), replace(base, **{name: v})) for v in values]
