"""Matrices in files: text with one entry a line, CSV and JSON entries, and tiles as Parquet."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankgrid.schema import BLOCKS, COO


def read_text_matrix(spark: SparkSession, path: str) -> DataFrame:
    """Entries from lines 'i j v'; blank lines and lines that start with % are left out."""
    lines = spark.read.text(path).where("trim(value) <> '' AND NOT startswith(value, '%')")
    f = F.split(F.trim("value"), r"\s+")
    return lines.select(F.element_at(f, 1).cast("long").alias("i"), F.element_at(f, 2).cast("long").alias("j"), F.element_at(f, 3).cast("double").alias("v"))


def write_text_matrix(entries: DataFrame, path: str) -> None:
    entries.select(F.concat_ws(" ", "i", "j", "v").alias("value")).write.text(path)


def read_entries(spark: SparkSession, path: str, kind: str = "csv") -> DataFrame:
    return spark.read.schema(COO).format(kind).load(path)


def write_entries(entries: DataFrame, path: str, kind: str = "csv") -> None:
    entries.write.format(kind).save(path)


def write_blocks(blocks: DataFrame, path: str, group: int = 16) -> None:
    """Tiles in folders of `group` block rows, sorted within files, so that a slice reads few files and row groups."""
    blocks.withColumn("bi_group", F.floor(F.col("bi") / group).cast("int")).repartition("bi_group").sortWithinPartitions("bi_group", "bi", "bj").write.partitionBy("bi_group").parquet(path)


def read_blocks(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(BLOCKS + ", bi_group int").parquet(path)


def write_bucketed(entries: DataFrame, name: str, by: str, buckets: int = 8) -> DataFrame:
    """Entries as a table bucketed by one index, so that products over it need no exchange of this side."""
    entries.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(name)
    return entries.sparkSession.table(name)
