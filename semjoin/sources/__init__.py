"""Tables and texts from anywhere Spark reads, as (row_id, text, key)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semjoin.functions.render import texts


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def from_lists(spark: SparkSession, values: list[str]) -> DataFrame:
    return spark.createDataFrame([(i, v, None) for i, v in enumerate(values)], "row_id bigint, text string, key string")


def read_texts(spark: SparkSession, fmt: str, path: str, id_col: str | None = None, text_col: str = "text", **options) -> DataFrame:
    """parquet, json, csv, orc, text (a row a line, or a file with ``wholetext``) or binaryFile (UTF-8 documents).

    Without an id column the rows are numbered by the hash of their text and path.
    """
    from semjoin.operators.batching import with_row_index

    if fmt == "binaryFile":
        df = spark.read.format(fmt).options(**options).load(path).select("path", F.decode("content", "UTF-8").alias("text"))
        text_col = "text"
    elif fmt == "text":
        df = spark.read.text(path, **options).select(F.col("value").alias("text"), F.col("_metadata.file_path").alias("path"))
        text_col = "text"
    else:
        df = spark.read.format(fmt).options(**options).load(path)
    if id_col:
        return texts(df, id_col, text_col)
    keyed = df.select(F.col(text_col).alias("text"), F.xxhash64(*df.columns).alias("h"))
    return texts(with_row_index(keyed, "h"), "row_index", "text")


def write_pairs(pairs: DataFrame, path: str, run_id: str, number: int = 0) -> None:
    """Pairs of a run, partitioned by run and round."""
    pairs.withColumn("run_id", F.lit(run_id)).withColumn("round", F.lit(number)).write.mode("append").partitionBy("run_id", "round").parquet(path)


def from_table(spark: SparkSession, name: str, id_col: str, text_col: str = "text") -> DataFrame:
    """A catalogue table or view as (row_id, text, key)."""
    return texts(spark.table(name), id_col, text_col)


def write_table(pairs: DataFrame, name: str, run_id: str, number: int = 0) -> None:
    """Pairs of a run appended to a catalogue table, partitioned by run and round."""
    rows = pairs.select("left_id", "right_id", F.lit(run_id).alias("run_id"), F.lit(number).alias("round"))
    if pairs.sparkSession.catalog.tableExists(name):
        rows.write.mode("append").insertInto(name)
    else:
        rows.write.partitionBy("run_id", "round").saveAsTable(name)
