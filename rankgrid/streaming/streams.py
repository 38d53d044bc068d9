"""Matrices fed by a stream of events: windows, late data, products kept up to date, state per user, joins of streams."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from rankgrid.session import shared_dir, table


def event_stream(spark: SparkSession, sf_dir: str, delay: str | None = "2 hours", files: str = "events.parquet") -> DataFrame:
    """The events as a stream of files, timestamps with a zone, and a watermark on request."""
    schema = table(spark, sf_dir, "events").schema
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("pathGlobFilter", files).parquet(sf_dir)
    s = s.withColumn("ts", F.col("ts").cast("timestamp"))
    return s.withWatermark("ts", delay) if delay else s


def ran(stream: DataFrame, mode: str = "append", sink: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Run a stream over what is there to a Parquet table in the shared folder, and open the table.

    Each batch writes a folder of its own by overwriting it, so that a batch that is replayed changes nothing. In complete
    mode the last batch's folder is the result.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    schema, seen = stream.schema, []

    def put(batch: DataFrame, n: int) -> None:
        seen.append(n)
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={n}")
        if sink:
            sink(batch, n)

    q = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    if not seen:
        return spark.createDataFrame([], schema)
    return spark.read.schema(schema).parquet(*([f"{base}/out/batch={max(seen)}"] if mode == "complete" else [f"{base}/out/batch={n}" for n in sorted(set(seen))]))


def user_windows(stream: DataFrame, kind: str = "tumbling") -> DataFrame:
    """Entries (user, window start) with counts: days that follow each other, days that overlap, or sessions of six hours."""
    w = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "1 day", "6 hours"), "session": F.session_window("ts", "6 hours")}[kind]
    return stream.groupBy("user_id", w.alias("w")).agg(F.count("*").alias("n")).select("user_id", F.unix_timestamp(F.col("w.start")).alias("start"), "n")


def incremental_product(stream: DataFrame, b: DataFrame) -> DataFrame:
    """The product of a growing matrix (user, type) with a static b (i = type, j, v): each batch adds its part, and the
    parts are summed when read. A replayed batch overwrites its own part."""
    joined = stream.select("user_id", "event_type").join(b.withColumnRenamed("i", "t"), F.col("event_type") == F.col("t")).select(F.col("user_id").alias("i"), "j", "v")
    parts = ran(joined)
    return parts.groupBy("i", "j").agg(F.sum("v").alias("v"))


def _add(key: tuple, rows: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    n, cents = state.get if state.exists else (0, 0)
    for r in rows:
        n += len(r)
        cents += int((r["value"] * 100).round().sum())
    state.update((n, cents))
    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "cents": [cents]})


def running_totals(stream: DataFrame) -> DataFrame:
    """user_id, n, cents (events and cents so far) after each batch a user has events in; the state is kept per user."""
    return stream.select("user_id", "value").groupBy("user_id").applyInPandasWithState(_add, "user_id long, n long, cents long", "n long, cents long", "update", GroupStateTimeout.NoTimeout)


def signups_after_clicks(stream: DataFrame, other: DataFrame, within: str = "1 day") -> DataFrame:
    """Signups with each click of the user up to a day before: a join of two streams with watermarks."""
    s = stream.where("event_type = 'signup'").select(F.col("user_id").alias("u"), F.col("ts").alias("signup"), F.col("event_id").alias("signup_id"))
    c = other.where("event_type = 'click'").select("user_id", F.col("ts").alias("click"), F.col("event_id").alias("click_id"))
    return s.join(c, (F.col("u") == F.col("user_id")) & (F.col("click") <= F.col("signup")) & (F.col("click") >= F.col("signup") - F.expr(f"INTERVAL {within}"))).select("signup_id", "click_id")


def first_of_day(stream: DataFrame) -> DataFrame:
    """Rows without repeats of (user, type) as far as the watermark can tell."""
    return stream.dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
