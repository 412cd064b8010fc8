"""Transactions from files and results to files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefpat.operators.encode import LONG_SCHEMA


def read_item_lines(spark: SparkSession, path: str) -> DataFrame:
    """One transaction a line, items separated by white space; the line is the id.

    Lines are numbered by their place in the file, so equal lines are two rows.
    """
    lines = spark.read.text(path).select(F.xxhash64(F.col("_metadata.file_path"), F.monotonically_increasing_id()).alias("tid"), "value")
    words = F.filter(F.split(F.trim("value"), r"\s+"), lambda x: x != "")
    return lines.select("tid", F.explode_outer(F.array_distinct(words)).alias("item"), F.lit(None).cast("int").alias("label"))


def read_long(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """The long form ``(tid, item, label)`` from parquet, csv or json, under its schema."""
    if fmt == "parquet":
        return spark.read.parquet(path)
    reader = spark.read.schema(LONG_SCHEMA)
    return reader.csv(path, header=True) if fmt == "csv" else reader.json(path)


def write_patterns(patterns: DataFrame, path: str, dataset: str) -> None:
    """Partitioned by dataset and length, which prunes reads by length."""
    patterns.withColumn("dataset", F.lit(dataset)).write.mode("append").partitionBy("dataset", "len").parquet(path)


def append_rows(rows: DataFrame, path: str) -> None:
    """Append-only logs: feedback, weights, queries, regret."""
    rows.write.mode("append").parquet(path)


def write_table(rows: DataFrame, path: str) -> None:
    """A result table as one csv with a header; result tables are small."""
    rows.coalesce(1).write.mode("overwrite").csv(path, header=True)
