"""A bounded filter of keys, broadcast: rows whose key is surely absent are dropped early.

The keys set bits in a table that has ``PER_KEY`` bits a key, but ``MOST`` at most (a million rows of
16 bytes), so the broadcast has a fixed bound whatever the number of keys.  Beyond ``MOST / PER_KEY`` keys
(eight million) more and more rows pass by chance: that costs their shuffle and changes no result, for a
row that passes by chance must be harmless to what follows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PER_KEY = 8
LEAST, MOST = 1 << 20, 1 << 26


@dataclass(frozen=True)
class BitTable:
    words: DataFrame
    bits: int


def _place(key: Column, bits: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(bits))


def bit_table(keys: DataFrame, key: str, bits: int | None = None) -> BitTable:
    """``keys`` should be a written table: it is counted first."""
    if bits is None:
        bits = min(MOST, max(LEAST, 1 << (PER_KEY * keys.count()).bit_length()))
    p = keys.select(_place(F.col(key), bits).alias("p"))
    return BitTable(p.groupBy(F.floor(F.col("p") / 64).cast("int").alias("__bit_word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(p % 64 as int))")).alias("__bit_bits")), bits)


def _placed(df: DataFrame, key: str, table: BitTable) -> DataFrame:
    return df.withColumn("__bit_p", _place(F.col(key), table.bits)).withColumn("__bit_word", F.floor(F.col("__bit_p") / 64).cast("int"))


def may_contain(df: DataFrame, key: str, table: BitTable) -> DataFrame:
    hit = _placed(df, key, table).join(F.broadcast(table.words), "__bit_word")
    return hit.where(F.expr("(shiftright(__bit_bits, cast(__bit_p % 64 as int)) & 1L) = 1L")).select(*df.columns)


def lacks(df: DataFrame, key: str, table: BitTable) -> DataFrame:
    """The complement of ``may_contain``: rows whose key is surely not among the keys."""
    hit = _placed(df, key, table).join(F.broadcast(table.words), "__bit_word", "left")
    return hit.where(F.expr("coalesce(shiftright(__bit_bits, cast(__bit_p % 64 as int)) & 1L, 0L) = 0L")).select(*df.columns)


def without(df: DataFrame, key: str, drop: DataFrame) -> DataFrame:
    """``df`` less the rows whose key is in ``drop``: only rows that may be dropped are shuffled."""
    table = bit_table(drop, key)
    return lacks(df, key, table).union(may_contain(df, key, table).join(drop.select(key), key, "left_anti").select(df.columns))


def one_each(df: DataFrame, keys: list[str]) -> DataFrame:
    """Of rows with equal ``keys`` the first in the order of all columns; combined before the shuffle, so no key is hot."""
    return df.groupBy(*[F.col(k).alias(f"__key_{i}") for i, k in enumerate(keys)]).agg(F.min(F.struct(*df.columns)).alias("__row")).select("__row.*")
