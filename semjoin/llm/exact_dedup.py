"""Exact deduplication by a 128-bit content hash, with byte comparison inside groups.

Texts are equal when identical after every run of ``[\\x20\\x09-\\x0D]`` became one
space; null counts as empty.  Of equal texts the row with the smallest id stays.

Defined cases: an empty table gives an empty result; rows that repeat an id are
separate members of their group, of which one stays; null ids sort before all others and stay first;
other columns of the input, whatever their names, are not touched (of rows that repeat
both id and text the first in the order of all columns stays, which must be orderable).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .bitmap import bit_table, lacks, may_contain, one_each
from .scratch import Scratch

SPACES = "[\\x20\\x09-\\x0D]+"


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACES, " ")


def content_hash(norm: Column) -> tuple[Column, Column]:
    """128 bits as two longs."""
    d = F.md5(norm)
    half = lambda at: F.expr("0L") + F.conv(F.substring(d, at, 16), 16, -10).cast("long")
    return half(1), half(17)


def _grouped(docs: DataFrame, id_col: str, text_col: str, hash_of: Callable[[Column], tuple[Column, Column]]) -> DataFrame:
    """(id, keep, n, kept, sha, hi, lo) of every row.

    Plan: one pass writes the signatures (id, hash, digest).  Groups are counted on
    them with a map-side combine, so a hot group costs one row per task.  Texts whose
    hash occurs again (and the few that pass the bounded filter by chance) are read a
    second time and grouped by (hash, text), again combined before the shuffle, which
    compares their bytes.  Should texts differ under one hash, the rows of that hash
    are grouped by their text itself.
    """
    scratch = Scratch(docs.sparkSession, "exact")
    base = docs.select(F.col(id_col).alias("id"), normalised(F.col(text_col)).alias("norm"))
    hi, lo = hash_of(F.col("norm"))
    sig = scratch.table(base.select("id", F.monotonically_increasing_id().alias("row"), hi.alias("hi"), lo.alias("lo"), F.unhex(F.sha2("norm", 256)).alias("sha")), "signatures")
    groups = sig.groupBy("hi", "lo").agg(F.min(F.struct("id", "row")).alias("first"), F.count("*").alias("n")).where("n > 1")
    groups = scratch.table(groups.select("hi", "lo", F.col("first.id").alias("keep"), F.col("first.row").alias("keep_row"), "n"), "groups")
    hashed = base.select("id", hi.alias("hi"), lo.alias("lo"), "norm")
    again = may_contain(hashed, "lo", bit_table(groups, "lo"))
    texts = again.groupBy("hi", "lo", "norm").agg(F.count("*").alias("c")).select("hi", "lo")
    clashing = scratch.table(texts.groupBy("hi", "lo").agg(F.count("*").alias("k")).where("k > 1").select("hi", "lo"), "clashing")
    own = sig
    odd = None
    if not clashing.isEmpty():
        own = sig.join(clashing, ["hi", "lo"], "left_anti")
        rows = hashed.join(clashing, ["hi", "lo"], "left_semi")
        by_text = rows.groupBy("norm").agg(F.min("id").alias("keep"), F.count("*").alias("n"))
        again = F.row_number().over(W.partitionBy("norm", "id").orderBy("hi"))  # rows that repeat an id and a text are alike
        odd = rows.withColumn("again", again).join(by_text, "norm").select("id", "keep", "n", (F.col("id").eqNullSafe(F.col("keep")) & (F.col("again") == 1)).alias("kept"), F.unhex(F.sha2("norm", 256)).alias("sha"), "hi", "lo")
    lone = F.col("n").isNull()
    out = own.join(groups, ["hi", "lo"], "left").select("id", F.when(lone, F.col("id")).otherwise(F.col("keep")).alias("keep"), F.coalesce("n", F.lit(1).cast("long")).alias("n"), (lone | (F.col("row") == F.col("keep_row"))).alias("kept"), "sha", "hi", "lo")
    return out if odd is None else out.union(odd)


def group_equal(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hash_of: Callable[[Column], tuple[Column, Column]] = content_hash) -> DataFrame:
    """One row per document: id, keep_id, group_size, kept, text_sha256."""
    out = _grouped(docs, id_col, text_col, hash_of)
    return out.select(F.col("id").alias(id_col), F.col("keep").alias("keep_id"), F.col("n").alias("group_size"), "kept", F.lower(F.hex("sha")).alias("text_sha256"))


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hash_of: Callable[[Column], tuple[Column, Column]] = content_hash) -> DataFrame:
    """The rows that stay, with all their columns.

    Only rows whose id is that of a dropped row are hashed again and shuffled; an id may
    stand for several texts, of which one goes and another stays.
    """
    drop = _grouped(docs, id_col, text_col, hash_of).where("not kept").select(F.col("id").alias("__id"), F.col("sha").alias("__sha"), F.col("id").eqNullSafe(F.col("keep")).alias("__again")).distinct()
    drop = Scratch(docs.sparkSession, "exact").table(drop, "drop")
    table = bit_table(drop, "__id")
    some = may_contain(docs.withColumn("__doc", F.col(id_col)), "__doc", table).withColumn("__hash", F.unhex(F.sha2(normalised(F.col(text_col)), 256)))
    same = lambda gone: F.col("__doc").eqNullSafe(F.col("__id")) & (F.col("__hash") == F.col("__sha")) & gone
    stay = some.join(drop, same(F.lit(True)), "left_anti")
    again = some.join(drop.where("__again"), same(F.lit(True)), "left_semi")  # repeated id and text: one stays
    more = one_each(again, ["__doc", "__hash"])
    cols = [F.col(f"`{c}`") for c in docs.columns]
    return lacks(docs.withColumn("__doc", F.col(id_col)), "__doc", table).select(cols).union(stay.select(cols)).union(more.select(cols))
