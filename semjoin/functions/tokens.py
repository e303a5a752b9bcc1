"""Token counters: the same count as a Spark column and in Python."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORDS = r"[A-Za-z0-9]+|[^A-Za-z0-9 \t\r\n]"
_WORDS = re.compile(WORDS)


def count_column(text: Column, counter: str = "words") -> Column:
    text = F.coalesce(text, F.lit(""))
    if counter == "words":
        return F.size(F.regexp_extract_all(text, F.lit(WORDS), F.lit(0)))
    if counter == "chars4":
        return F.ceil(F.length(text) / 4).cast("int")
    raise ValueError(f"unknown counter {counter!r}")


def count(text: str, counter: str = "words") -> int:
    if counter == "words":
        return sum(1 for _ in _WORDS.finditer(text))
    if counter == "chars4":
        return -(-len(text) // 4)
    raise ValueError(f"unknown counter {counter!r}")


def with_tokens(df: DataFrame, counter: str = "words", text_col: str = "text", name: str = "tokens") -> DataFrame:
    return df.withColumn(name, count_column(F.col(text_col), counter))


def cut_column(text: Column, n: int) -> Column:
    """The text up to the end of its n-th token, spacing kept."""
    return F.regexp_extract(F.coalesce(text, F.lit("")), rf"^(?:[ \t\r\n]*(?:{WORDS})){{0,{n}}}", 0)


def first_tokens(text: Column, n: int) -> Column:
    """The first n tokens joined by one space."""
    return F.array_join(F.slice(F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(WORDS), F.lit(0)), 1, n), " ")


def chunks(df: DataFrame, size: int, overlap: int, id_col: str = "row_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, columns to keep, chunk, text): windows of ``size`` tokens, ``overlap`` shared with the one before; short texts stay whole."""
    if not 0 <= overlap < size:
        raise ValueError("overlap must be below size")
    step = size - overlap
    parts = F.regexp_extract_all(F.coalesce(F.col(text_col), F.lit("")), F.lit(rf"(?:{WORDS})[ \t\r\n]*"), F.lit(0))
    t = df.select(F.col(id_col), *keep, parts.alias("p"))
    last = F.greatest(F.lit(0), F.ceil((F.size("p") - size) / step)).cast("int")
    t = t.select(id_col, *keep, "p", F.explode(F.sequence(F.lit(0), last)).alias("chunk"))
    return t.select(id_col, *keep, "chunk", F.array_join(F.slice("p", F.col("chunk") * step + 1, size), "").alias("text"))
