"""Cost formulas; every argument is a number or a column, and so is the result.

Costs are in units of one token read; ``write_ratio`` is what a written token costs in them.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def _is_column(*xs) -> bool:
    return any(isinstance(x, Column) for x in xs)


def root(x):
    return F.sqrt(x) if _is_column(x) else math.sqrt(x)


def up(x):
    return F.ceil(x) if _is_column(x) else math.ceil(x)


def pair_cost(instruction_tokens, width_left, width_right, write_ratio):
    """One comparison: everything is read, one token is written."""
    return instruction_tokens + width_left + width_right + write_ratio


def pairwise_cost(rows_left, rows_right, instruction_tokens, width_left, width_right, write_ratio):
    return pair_cost(instruction_tokens, width_left, width_right, write_ratio) * rows_left * rows_right


def expected_output(batch_left, batch_right, width_match, selectivity):
    return batch_left * batch_right * selectivity * width_match


def call_tokens(batch_left, batch_right, instruction_tokens, width_left, width_right, width_match, selectivity):
    return instruction_tokens + batch_left * width_left + batch_right * width_right + expected_output(batch_left, batch_right, width_match, selectivity)


def call_cost(batch_left, batch_right, instruction_tokens, width_left, width_right, width_match, selectivity, write_ratio):
    return instruction_tokens + batch_left * width_left + batch_right * width_right + expected_output(batch_left, batch_right, width_match, selectivity) * write_ratio


def call_count(rows_left, rows_right, batch_left, batch_right, rounding: str = "none"):
    a, b = rows_left / batch_left, rows_right / batch_right
    return up(a) * up(b) if rounding == "ceil" else a * b


def block_cost(rows_left, rows_right, batch_left, batch_right, instruction_tokens, width_left, width_right, width_match, selectivity, write_ratio, rounding: str = "none"):
    return call_count(rows_left, rows_right, batch_left, batch_right, rounding) * call_cost(batch_left, batch_right, instruction_tokens, width_left, width_right, width_match, selectivity, write_ratio)


def ragged_cost(rows_left, rows_right, batch_left, batch_right, instruction_tokens, width_left, width_right, width_match, selectivity, write_ratio):
    """Block total of whole calls whose last batches are ragged: a row is read once per batch of the other side."""
    nl, nr = up(rows_left / batch_left), up(rows_right / batch_right)
    return nl * nr * instruction_tokens + nr * rows_left * width_left + nl * rows_right * width_right + rows_left * rows_right * selectivity * width_match * write_ratio


def fits(batch_left, batch_right, width_left, width_right, width_match, selectivity, budget):
    return call_tokens(batch_left, batch_right, 0, width_left, width_right, width_match, selectivity) <= budget


def right_size_for(left_size, width_left, width_right, width_match, selectivity, budget):
    """The right batch that uses up the budget."""
    return (budget - left_size * width_left) / (width_right + left_size * width_match * selectivity)


def left_size(width_left, width_right, width_match, selectivity, budget):
    """The left batch of least cost on the budget curve, in the form that also holds at selectivity 0."""
    both = width_left * width_right
    return width_right * budget / (root(both * both + both * width_match * selectivity * budget) + both)


def cost_on_curve(left, rows_left, rows_right, instruction_tokens, width_left, width_right, width_match, selectivity, write_ratio, budget):
    right = right_size_for(left, width_left, width_right, width_match, selectivity, budget)
    return block_cost(rows_left, rows_right, left, right, instruction_tokens, width_left, width_right, width_match, selectivity, write_ratio)


def slope_on_curve(left, rows_left, rows_right, instruction_tokens, width_left, width_right, width_match, selectivity, budget):
    """Derivative of ``cost_on_curve``; written tokens per pair don't depend on the batches, so their price drops out."""
    above = left * left * width_left * width_match * selectivity + 2 * left * width_left * width_right - width_right * budget
    free = budget - left * width_left
    return rows_left * rows_right * (budget + instruction_tokens) * above / (free * free * left * left)


def cost_when_planned_for(estimate, selectivity, rows_left, rows_right, instruction_tokens, width_left, width_right, width_match, write_ratio, budget):
    left = left_size(width_left, width_right, width_match, estimate, budget)
    right = right_size_for(left, width_left, width_right, width_match, estimate, budget)
    return block_cost(rows_left, rows_right, left, right, instruction_tokens, width_left, width_right, width_match, selectivity, write_ratio)


def regret(estimate, selectivity, *table_and_model):
    return cost_when_planned_for(estimate, selectivity, *table_and_model) / cost_when_planned_for(selectivity, selectivity, *table_and_model)


def regret_bound(growth, write_ratio):
    """With written tokens cheaper than read ones only the growth counts."""
    if _is_column(growth, write_ratio):
        return growth * F.greatest(write_ratio if isinstance(write_ratio, Column) else F.lit(float(write_ratio)), F.lit(1.0))
    return growth * max(1.0, write_ratio)


def expected_rounds(estimate, selectivity, growth):
    """Least number of raises after which the estimate is not below the selectivity."""
    if _is_column(estimate, selectivity, growth):
        c = lambda x: x if isinstance(x, Column) else F.lit(float(x))
        return F.greatest(F.lit(0), F.ceil(F.round(F.log(c(selectivity) / c(estimate)) / F.log(c(growth)), 9))).cast("long")
    return max(0, math.ceil(round(math.log(selectivity / estimate) / math.log(growth), 9)))


def token_split(width_left, width_right, width_match, selectivity, budget):
    """Tokens of a call for the left rows, the right rows and the answer, at the optimum."""
    left = left_size(width_left, width_right, width_match, selectivity, budget)
    right = right_size_for(left, width_left, width_right, width_match, selectivity, budget)
    return left * width_left, right * width_right, expected_output(left, right, width_match, selectivity)


def fee_cents(tokens_read, tokens_written, read_price=3.0, write_price=6.0):
    return (tokens_read * read_price + tokens_written * write_price) / 1000
