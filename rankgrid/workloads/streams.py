"""Streaming queries; each is run over the files that are there and compared with the batch form in SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from rankgrid.registry import query
from rankgrid.streaming import streams as st

_SEC = "CAST(epoch_us(ts) // 1000000 AS BIGINT)"


@query(f"SELECT user_id, CAST(({_SEC} // 86400) * 86400 AS BIGINT) AS start, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    return st.ran(st.user_windows(st.event_stream(spark, sf_dir)), "complete")


@query(f"SELECT user_id, CAST(({_SEC} // 21600 - k) * 21600 AS BIGINT) AS start, count(*) AS n FROM events, (SELECT unnest([0, 1, 2, 3]) AS k) GROUP BY 1, 2")
def stream_sliding(spark, sf_dir):
    return st.ran(st.user_windows(st.event_stream(spark, sf_dir), "sliding"), "complete")


@query("""
WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, SUM(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, CAST(epoch_us(MIN(ts)) // 1000000 AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_session(spark, sf_dir):
    return st.ran(st.user_windows(st.event_stream(spark, sf_dir), "session"), "complete")


@query(f"SELECT user_id, CAST(({_SEC} // 86400) * 86400 AS BIGINT) AS start, count(*) AS n FROM events GROUP BY 1, 2 HAVING ({_SEC.replace('ts', 'MIN(ts)')} // 86400 + 1) * 86400 <= (SELECT CAST(epoch_us(MAX(ts)) // 1000000 AS BIGINT) - 7200 FROM events)")
def stream_watermark(spark, sf_dir):
    """Append mode: only the days that the last watermark has closed come out."""
    return st.ran(st.user_windows(st.event_stream(spark, sf_dir)), "append")


_WEIGHTS = [("click", 0, 1.0), ("click", 1, 2.0), ("purchase", 1, 5.0), ("view", 0, 3.0)]


@query("SELECT e.user_id AS i, CAST(w.j AS BIGINT) AS j, SUM(w.v) AS v FROM events e JOIN (VALUES " + ", ".join(f"('{t}', {j}, CAST({v} AS DOUBLE))" for t, j, v in _WEIGHTS) + ") AS w(t, j, v) ON e.event_type = w.t GROUP BY 1, 2")
def stream_product(spark, sf_dir):
    b = spark.createDataFrame(_WEIGHTS, "i string, j long, v double")
    return st.incremental_product(st.event_stream(spark, sf_dir, None), b)


@query("SELECT user_id, count(*) AS n, CAST(SUM(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY 1")
def stream_state(spark, sf_dir):
    """A user's totals after the last batch."""
    rows = st.ran(st.running_totals(st.event_stream(spark, sf_dir, None)), "update")
    return rows.groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("cents", "n").alias("cents"))


@query("SELECT s.event_id AS signup_id, c.event_id AS click_id FROM events s JOIN events c ON s.user_id = c.user_id AND c.ts <= s.ts AND c.ts >= s.ts - INTERVAL 1 DAY WHERE s.event_type = 'signup' AND c.event_type = 'click'")
def stream_join(spark, sf_dir):
    return st.ran(st.signups_after_clicks(st.event_stream(spark, sf_dir), st.event_stream(spark, sf_dir)))


@query()
def stream_dedup(spark, sf_dir):
    return st.ran(st.first_of_day(st.event_stream(spark, sf_dir)))
