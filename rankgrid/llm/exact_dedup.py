"""Exact duplicates by a 128-bit content hash with a comparison of the bytes, in DataFrame operations only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rankgrid.llm.skew import left_join

#: The characters that do not count when texts are compared.
IGNORED = (" ", "\t", "\n", "\x0b", "\x0c", "\r")


def without_white(text: Column) -> Column:
    """text without the characters of IGNORED; null counts as empty."""
    out = F.coalesce(text.cast("string"), F.lit(""))
    for c in IGNORED:
        out = F.replace(out, F.lit(c), F.lit(""))
    return out


def duplicate_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256, n_chars_original.

    Texts are equal when they are equal without white space. Of a group the row with the most code points stays, then
    the smallest id (a null id is the smallest). Null texts count as empty, and all empty texts form one group. Rows
    that repeat an id and its text count each in group_size and share one decision. An empty table gives no rows, and
    other columns of docs are not read.

    Rows first collapse within each map task on (hash, normalised bytes), so that a group of any size sends one row a
    task, and two texts of one hash stay apart because the key has the bytes. Only the narrow digest travels after that,
    and groups that hold a large share of all rows are broadcast, so that no task gets a whole one.
    """
    norm = without_white(F.col(text_col))
    rows = docs.select(F.col(id_col).alias("doc_id"), F.char_length(F.coalesce(F.col(text_col).cast("string"), F.lit(""))).alias("n_chars_original"), norm.alias("norm"))
    rows = rows.withColumns({"h1": F.xxhash64("norm"), "h2": F.xxhash64(F.lit(128), F.col("norm"))})
    same_bytes = rows.groupBy("h1", "h2", "norm", "n_chars_original").agg(F.count("*").alias("n"), F.min("doc_id").alias("low"), F.max(F.col("doc_id").isNull()).alias("has_null"))
    digests = same_bytes.select("h1", "h2", F.sha2("norm", 256).alias("sha"), "n", "n_chars_original", F.when(~F.col("has_null"), F.col("low")).alias("low"))
    groups = (
        digests.groupBy("h1", "h2", "sha")
        .agg(F.sum("n").alias("group_size"), F.min(F.struct((-F.col("n_chars_original")).alias("longest"), F.col("low"))).alias("best"))
        .where("group_size > 1")
        .select("h1", "h2", "sha", "group_size", F.col("best.low").alias("keep_id"), (-F.col("best.longest")).alias("keep_chars"))
    )
    each = rows.select("doc_id", "n_chars_original", "h1", "h2", F.sha2("norm", 256).alias("text_sha256"))
    on = {"h1": "h1", "h2": "h2", "text_sha256": "sha"}
    joined = left_join(each, groups, on, ["group_size", "keep_id", "keep_chars"], "group_size", docs.count(), F.xxhash64("doc_id"))
    alone = F.col("group_size").isNull()
    keep = F.when(alone, F.col("doc_id")).otherwise(F.col("keep_id"))
    return joined.select(
        "doc_id",
        keep.alias("keep_id"),
        F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"),
        (alone | (F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("n_chars_original") == F.col("keep_chars")))).alias("kept"),
        "text_sha256",
        "n_chars_original",
    )


def drop_exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the rows that duplicate_groups drops; columns and other rows stay as they are.

    A dropped row is found by its id, so an id that is dropped in one row and kept in another (a repeated id with two
    texts) leaves only by the row whose digest was dropped. Of rows that repeat an id and its text one stays.
    """
    columns = docs.columns
    rows = duplicate_groups(docs, id_col, text_col).groupBy(F.col("doc_id").alias("__id"), F.col("text_sha256").alias("__sha"), F.col("n_chars_original").alias("__chars"))
    decided = rows.agg(F.min("kept").alias("__kept"), F.count("*").alias("__times")).where("NOT __kept OR __times > 1")
    sha = F.sha2(without_white(F.col(text_col)), 256)
    length = F.char_length(F.coalesce(F.col(text_col).cast("string"), F.lit("")))
    same = F.col(id_col).eqNullSafe(F.col("__id")) & (sha == F.col("__sha")) & (length == F.col("__chars"))
    # rows that repeat are few or none: they come back once
    again = docs.join(decided.where("__kept"), same, "inner").dropDuplicates(["__id", "__sha", "__chars"]).select(*columns)
    return docs.join(decided, same, "left_anti").unionByName(again)
