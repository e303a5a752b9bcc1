"""The experiments' workloads on the given tables: two collections, a condition and the true pairs."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from semjoin.functions.tokens import chunks, count_column, first_tokens
from semjoin.lm.base import EachPair, SameFeature, SemanticPredicate
from semjoin.sources import load


@dataclass
class Workload:
    name: str
    left: DataFrame
    right: DataFrame
    truth: DataFrame
    predicate: SemanticPredicate
    stride: int = 1000  # row ids of parts are id * stride + part


_MONTH = re.compile(r"(Customer#\d+).*?(\d{4}-\d{2})")


def _contradicts(a, b) -> bool:
    x, y = _MONTH.search(a[0]), _MONTH.search(b[0])
    return x[1] == y[1] and x[2] < y[2]


def contradiction(spark: SparkSession, d: str, customers: int | None = 10) -> Workload:
    """Orders of so many customers (null: all) against what those claim their first month was; even keys claim wrongly."""
    m = load(spark, d, "orders").select("o_orderkey", "o_custkey", F.date_format("o_orderdate", "yyyy-MM").alias("mon"))
    chosen = m.groupBy("o_custkey").agg(F.countDistinct("mon").alias("n")).where("n >= 2").select("o_custkey")
    m = m.join(F.broadcast(chosen.orderBy("o_custkey").limit(customers)) if customers else chosen, "o_custkey")
    tag = F.format_string("Customer#%09d", "o_custkey")
    months = m.groupBy("o_custkey").agg(F.sort_array(F.collect_set("mon")).alias("mons"))
    claims = months.select("o_custkey", F.element_at("mons", F.when(F.col("o_custkey") % 2 == 0, 2).otherwise(1)).alias("said"))
    left = m.select(F.col("o_orderkey").alias("row_id"), F.concat(F.lit("Order taken from "), tag, F.lit(" in "), "mon", F.lit(".")).alias("text"), F.lit(None).cast("string").alias("key"), "o_custkey")
    right = claims.select(F.col("o_custkey").alias("row_id"), F.concat(tag, F.lit(": my first order was in "), "said", F.lit(".")).alias("text"), F.lit(None).cast("string").alias("key"), "o_custkey")
    truth = m.join(claims, "o_custkey").where("mon < said").select(F.col("o_orderkey").alias("left_id"), F.col("o_custkey").alias("right_id"))
    return Workload("contradiction", left, right, truth, SemanticPredicate("the two notes contradict each other on when the customer first ordered", EachPair(_contradicts)))


def _key(text, key):
    return key


def sentiment(spark: SparkSession, d: str) -> Workload:
    """Labelled documents, cut to 100 tokens: of each quality class the first n and the next n."""
    docs = load(spark, d, "documents").select("doc_id", "text").join(load(spark, d, "labels").select("doc_id", "quality"), "doc_id")
    n = docs.groupBy("quality").count().agg(F.least(F.lit(25), F.floor(F.min("count") / 2)).alias("n"))
    ranked = docs.withColumn("rank", F.row_number().over(W.partitionBy("quality").orderBy("doc_id"))).crossJoin(F.broadcast(n))
    rows = ranked.select(F.col("doc_id").alias("row_id"), first_tokens(F.col("text"), 100).alias("text"), F.col("quality").cast("string").alias("key"), "rank", "n")
    left, right = rows.where("rank <= n").drop("rank", "n"), rows.where("rank > n and rank <= 2 * n").drop("rank", "n")
    truth = left.select(F.col("row_id").alias("left_id"), "key").join(right.select(F.col("row_id").alias("right_id"), "key"), "key").drop("key")
    return Workload("sentiment", left, right, truth, SemanticPredicate("both texts are well written, or both are poor", SameFeature(_key, _key)))


def toxic(spark: SparkSession, d: str, label: str = "toxic") -> Workload:
    """The first 50 labelled documents against the next 50, same label (an expression over quality and toxic); the published size."""
    first = load(spark, d, "labels").select("doc_id", F.expr(label).alias("label")).join(load(spark, d, "documents").select("doc_id", "text"), "doc_id").orderBy("doc_id").limit(100)
    rows = first.withColumn("rank", F.row_number().over(W.orderBy("doc_id")))
    rows = rows.select(F.col("doc_id").alias("row_id"), first_tokens(F.col("text"), 100).alias("text"), F.col("label").cast("string").alias("key"), "rank")
    left, right = rows.where("rank <= 50").drop("rank"), rows.where("rank > 50").drop("rank")
    truth = left.select(F.col("row_id").alias("left_id"), "key").join(right.select(F.col("row_id").alias("right_id"), "key"), "key").drop("key")
    return Workload("toxic", left, right, truth, SemanticPredicate("both texts are toxic, or neither is", SameFeature(_key, _key)))


_OFFER, _REQUEST = re.compile(r"For sale: a (\w+), (\w+)\."), re.compile(r"Wanted: a (\w+) in (\w+)\.")


def _offer(text, key):
    m = _OFFER.search(text)
    return (m[1], m[2]) if m else None


def _request(text, key):
    m = _REQUEST.search(text)
    return (m[1], m[2]) if m else None


def offers(spark: SparkSession, d: str) -> Workload:
    """Four adjectives by four nouns of the part names, each combination offered and wanted once."""
    words = load(spark, d, "part").select(F.split_part("p_name", F.lit(" "), F.lit(1)).alias("a"), F.split_part("p_name", F.lit(" "), F.lit(2)).alias("n"))
    four = lambda c: words.select(c).distinct().orderBy(c).limit(4).withColumn(f"i_{c}", F.row_number().over(W.orderBy(c)) - 1)
    grid = four("a").crossJoin(four("n")).withColumn("row_id", (F.col("i_a") * 4 + F.col("i_n")).cast("long"))
    none = F.lit(None).cast("string").alias("key")
    left = grid.select("row_id", F.concat(F.lit("For sale: a "), "n", F.lit(", "), "a", F.lit(".")).alias("text"), none)
    right = grid.select("row_id", F.concat(F.lit("Wanted: a "), "n", F.lit(" in "), "a", F.lit(".")).alias("text"), none)
    truth = grid.select(F.col("row_id").alias("left_id"), F.col("row_id").alias("right_id"))
    return Workload("offers", left, right, truth, SemanticPredicate("the offer meets the request", SameFeature(_offer, _request)))


_KIND = re.compile(r"(\w+), type (\w+)\.")


def _kind(text, key):
    m = _KIND.search(text)
    return (m[1], m[2]) if m else None


def offers_large(spark: SparkSession, d: str) -> Workload:
    """All parts against the distinct combinations of adjective and type."""
    p = load(spark, d, "part").select("p_partkey", F.split_part("p_name", F.lit(" "), F.lit(1)).alias("a"), F.col("p_type").alias("t"))
    kinds = p.select("a", "t").distinct().withColumn("row_id", (F.row_number().over(W.orderBy("a", "t")) - 1).cast("long"))
    none = F.lit(None).cast("string").alias("key")
    left = p.select(F.col("p_partkey").alias("row_id"), F.concat(F.lit("For sale: something "), "a", F.lit(", type "), "t", F.lit(".")).alias("text"), none)
    right = kinds.select("row_id", F.concat(F.lit("Wanted: "), "a", F.lit(", type "), "t", F.lit(".")).alias("text"), none)
    truth = p.join(kinds, ["a", "t"]).select(F.col("p_partkey").alias("left_id"), F.col("row_id").alias("right_id"))
    return Workload("offers_large", left, right, truth, SemanticPredicate("the offer meets the request", SameFeature(_kind, _kind)))


CHUNK, OVERLAP = 400, 120  # tokens at least; both grow with the longest passage


def stride_of(parts: DataFrame, part: str) -> int:
    """Above every part number, so that no two ids meet; 1000 where that is enough."""
    return max(Workload.stride, (parts.agg(F.max(part)).first()[0] or 0) + 1)


def _quotes(a, b) -> bool:
    return b[0] in a[0]


def quotes(spark: SparkSession, d: str) -> Workload:
    """Document chunks against benchmark passages; ids of chunks are resolved by ``documents_of``."""
    docs = load(spark, d, "documents").select(F.col("doc_id").alias("row_id"), "text")
    marks = load(spark, d, "benchmark").select(F.col("item_id").alias("row_id"), "text", F.lit(None).cast("string").alias("key"))
    widest = marks.agg(F.max(count_column(F.col("text")))).first()[0] or 0
    overlap = max(OVERLAP, widest)  # a passage that begins with a space also takes the end of the token before
    parts = chunks(docs, CHUNK - OVERLAP + overlap, overlap)
    stride = stride_of(parts, "chunk")
    parts = parts.select((F.col("row_id") * stride + F.col("chunk")).alias("row_id"), "text", F.lit(None).cast("string").alias("key"))
    truth = docs.alias("d").join(F.broadcast(marks.alias("m")), F.contains(F.col("d.text"), F.col("m.text"))).select(F.col("d.row_id").alias("left_id"), F.col("m.row_id").alias("right_id"))
    return Workload("quotes", parts, marks, truth, SemanticPredicate("the document quotes the passage", EachPair(_quotes)), stride)


def document_of(row_id: Column, stride: int) -> Column:
    return F.call_function("div", row_id - F.pmod(row_id, F.lit(stride)), F.lit(stride))


def documents_of(pairs: DataFrame, stride: int = Workload.stride) -> DataFrame:
    return pairs.select(document_of(F.col("left_id"), stride).alias("doc_id"), F.col("right_id").alias("item_id")).distinct()


def _next_turn(text, key):
    conv, turn = key.split(":")
    return f"{conv}:{int(turn) + 1}"


def replies(spark: SparkSession, d: str) -> Workload:
    """User turns against assistant turns of their conversation (``conv_id``): the second answers the first."""
    c = load(spark, d, "conversations")
    stride = stride_of(c, "turn")
    row = [(F.col("conv_id") * stride + F.col("turn")).alias("row_id"), "text", F.concat_ws(":", "conv_id", "turn").alias("key"), "conv_id"]
    left, right = c.where("role = 'user'").select(*row), c.where("role = 'assistant'").select(*row)
    u, a = c.where("role = 'user'").alias("u"), c.where("role = 'assistant'").alias("a")
    same = (F.col("u.conv_id") == F.col("a.conv_id")) & (F.col("a.turn") == F.col("u.turn") + 1)
    truth = u.join(a, same).select((F.col("u.conv_id") * stride + F.col("u.turn")).alias("left_id"), (F.col("a.conv_id") * stride + F.col("a.turn")).alias("right_id"))
    return Workload("replies", left, right, truth, SemanticPredicate("the second turn answers the first", SameFeature(_next_turn, _key)), stride)


def language(spark: SparkSession, d: str) -> Workload:
    """Addresses of web pages against whole documents, in chunks, in the same language; ``document_of`` takes chunks back."""
    pages = load(spark, d, "pages").select(F.col("page_id").alias("row_id"), F.col("url").alias("text"), F.regexp_extract("url", "://[^/]+/([a-z]+)/", 1).alias("key"))
    docs = load(spark, d, "documents").select(F.col("doc_id").alias("row_id"), "text", F.col("lang").alias("key"))
    longest = docs.agg(F.max(F.length("text"))).first()[0] or 0
    stride = max(Workload.stride, longest // CHUNK + 1)  # a token has a character at least
    rows = chunks(docs, CHUNK, 0, keep=("key",)).select((F.col("row_id") * stride + F.col("chunk")).alias("row_id"), "text", "key")
    truth = pages.select(F.col("row_id").alias("left_id"), "key").join(docs.select(F.col("row_id").alias("right_id"), "key"), "key").drop("key")
    return Workload("language", pages, rows, truth, SemanticPredicate("both are in the same language", SameFeature(_key, _key)), stride)


def clusters(spark: SparkSession, d: str) -> Workload:
    """Even against odd vectors with the same label; the sides have vectors instead of texts."""
    e = load(spark, d, "embeddings")
    side = lambda k: e.where(F.col("vec_id") % 2 == k).select(F.col("vec_id").alias("row_id"), F.col("embedding").alias("vector"), "label")
    truth = side(0).select(F.col("row_id").alias("left_id"), "label").join(side(1).select(F.col("row_id").alias("right_id"), "label"), "label").drop("label")
    return Workload("clusters", side(0).drop("label"), side(1).drop("label"), truth, SemanticPredicate("same label", None))
