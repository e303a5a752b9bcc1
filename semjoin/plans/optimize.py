"""Batch sizes under a token budget: the closed form, whole numbers, and exhaustive search."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semjoin.functions import costs
from semjoin.types import BatchPlan, BudgetTooSmall, TableProfile


def continuous(left: TableProfile, right: TableProfile, width_match: float, estimate: float, budget: float) -> tuple[float, float]:
    a = costs.left_size(left.width_mean, right.width_mean, width_match, estimate, budget)
    return a, costs.right_size_for(a, left.width_mean, right.width_mean, width_match, estimate, budget)


def _right_most(size: int, left: TableProfile, right: TableProfile, width_match: float, estimate: float, budget: float) -> int:
    return math.floor(costs.right_size_for(size, left.width_mean, right.width_mean, width_match, estimate, budget) + 1e-9)


def optimal_batches(left: TableProfile, right: TableProfile, estimate: float, budget: float, instruction_tokens: float, width_match: float = 4, write_ratio: float = 2.0, clamp: bool = True) -> BatchPlan:
    """The cheapest whole batches under the budget.

    With ``clamp`` tables have ends: batches are at most the table, the last one is ragged, and
    every left size is tried (at most budget / width of them) with the most right rows that fit.
    Of sizes with as many calls the smallest is taken, which leaves the answer more room.
    Without it, the whole neighbours of the closed form compete as if tables went on for ever.
    """
    if estimate < 0:
        raise ValueError("the estimate must not be negative")
    a, b = continuous(left, right, width_match, estimate, budget)
    args = (left, right, width_match, estimate, budget)
    n, m = max(1, left.rows), max(1, right.rows)
    money = (instruction_tokens, left.width_mean, right.width_mean, width_match, estimate, write_ratio)
    options = []
    if clamp:
        for x in range(1, min(n, max(1, int(budget / left.width_mean))) + 1):
            y = min(m, _right_most(x, *args))
            if y < 1:
                break
            nl, nr = -(-n // x), -(-m // y)
            x_, y_ = -(-n // nl), -(-m // nr)
            options.append((costs.ragged_cost(n, m, x_, y_, *money), x_ * y_, x_, y_))
    else:
        for x in {max(1, math.floor(a)), max(1, math.ceil(a))}:
            y = _right_most(x, *args)
            if y >= 1:
                options.append((costs.block_cost(n, m, x, y, *money), x * y, x, y))
    if not options:
        raise BudgetTooSmall(f"{budget} tokens don't hold one row of {left.width_mean:.1f} and one of {right.width_mean:.1f} tokens with their answer")
    cost, _, x, y = min(options)
    return BatchPlan(x, y, estimate, budget, math.ceil(left.rows / x) * math.ceil(right.rows / y), cost, a, b)


def search_space(spark: SparkSession, rows_left: int, rows_right: int) -> DataFrame:
    l = spark.range(1, rows_left + 1).select(F.col("id").alias("b_left"))  # noqa: E741
    r = spark.range(1, rows_right + 1).select(F.col("id").alias("b_right"))
    return l.crossJoin(r)


def best_batches_by_search(spark: SparkSession, rows_left: int, rows_right: int, instruction_tokens: float, width_left: float, width_right: float, width_match: float, selectivity: float, write_ratio: float, budget: float, rounding: str = "ceil") -> DataFrame:
    """The cheapest feasible sizes of all: an oracle for small settings."""
    grid = search_space(spark, rows_left, rows_right)
    a, b = F.col("b_left"), F.col("b_right")
    grid = grid.where(costs.fits(a, b, width_left, width_right, width_match, selectivity, budget))
    cost = costs.block_cost(F.lit(float(rows_left)), F.lit(float(rows_right)), a, b, instruction_tokens, width_left, width_right, width_match, selectivity, write_ratio, rounding)
    best = grid.select("b_left", "b_right", F.round(cost, 6).alias("cost"))
    return best.agg(F.min_by(F.struct("b_left", "b_right", "cost"), F.struct("cost", -F.col("b_left"), -F.col("b_right"))).alias("x")).select("x.*")
