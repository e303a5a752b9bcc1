"""Reading answers, with built-in functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PAIR = r"(\d+)\s*,\s*(\d+)\s*;"
TERMINATOR = "DONE"


def verdict_word(answer: Column) -> Column:
    """The answer without case, quotes, blanks and closing dots."""
    return F.regexp_replace(F.lower(F.trim(F.coalesce(answer, F.lit("")))), "^[\\s\"'`*]+|[\\s\"'`*.!]+$", "")


def read_verdict(answer: Column) -> Column:
    return verdict_word(answer).isin("yes", "y", "true")


def is_malformed(answer: Column) -> Column:
    return ~verdict_word(answer).isin("yes", "y", "true", "no", "n", "false")


def is_complete(answer: Column, stopped: Column, completion_check: str = "stop_reason") -> Column:
    """By finish reason, where the terminator is a stop word; else by the last word of the text."""
    if completion_check == "stop_reason":
        return stopped
    if completion_check == "text":
        return F.rtrim(F.coalesce(answer, F.lit(""))).endswith(TERMINATOR)
    raise ValueError(f"unknown completion check {completion_check!r}")


def complete_value(completion_check: str = "stop_reason"):
    """``is_complete`` for values."""
    if completion_check == "stop_reason":
        return lambda answer, stopped: bool(stopped)
    if completion_check == "text":
        return lambda answer, stopped: (answer or "").rstrip(" ").endswith(TERMINATOR)
    raise ValueError(f"unknown completion check {completion_check!r}")


def index_pairs(answer: Column) -> Column:
    """Distinct (x, y) positions of an answer; a pair cut off before its semicolon is not one."""
    text = F.concat(F.regexp_replace(F.coalesce(answer, F.lit("")), rf"{TERMINATOR}\s*$", ";"), F.lit(""))
    get = lambda k: F.transform(F.regexp_extract_all(text, F.lit(PAIR), F.lit(k)), lambda s: s.try_cast("int"))
    return F.array_distinct(F.arrays_zip(get(1).alias("x"), get(2).alias("y")))


def parse_pairs(answers: DataFrame) -> DataFrame:
    """(left_id, right_id) of complete answers; positions out of range are dropped."""
    p = answers.select("left_ids", "right_ids", F.explode(index_pairs(F.col("answer"))).alias("p"))
    p = p.where("p.x >= 1 and p.y >= 1").select(F.try_element_at("left_ids", F.col("p.x")).alias("left_id"), F.try_element_at("right_ids", F.col("p.y")).alias("right_id"))
    return p.where("left_id is not null and right_id is not null")


class BadPositions(ValueError):
    """An answer names rows that its prompt doesn't have, or says something that is no pair."""


def strict_parse(answers: DataFrame) -> DataFrame:
    """As ``parse_pairs``, but positions out of range and any other text raise ``BadPositions``."""
    rest = F.trim(F.regexp_replace(F.regexp_replace(F.coalesce("answer", F.lit("")), PAIR, ""), rf"{TERMINATOR}\s*$", ""))
    odd = answers.where(rest != "").count()
    bad = count_bad_positions(answers).first()[0]
    if odd or bad:
        raise BadPositions(f"{odd} answers hold other text, {bad} positions are out of range")
    return parse_pairs(answers)


def count_bad_positions(answers: DataFrame) -> DataFrame:
    """How many reported positions are out of range."""
    p = answers.select(F.size("left_ids").alias("n"), F.size("right_ids").alias("m"), F.explode(index_pairs(F.col("answer"))).alias("p"))
    return p.agg(F.count_if((F.col("p.x") < 1) | (F.col("p.x") > F.col("n")) | (F.col("p.y") < 1) | (F.col("p.y") > F.col("m")) | F.col("p.x").isNull() | F.col("p.y").isNull()).alias("bad_positions"))
