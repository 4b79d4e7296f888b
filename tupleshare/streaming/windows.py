"""Tuple values of windowed sums over an event stream.

A sum is additive, so the values of a window's events add up as they come: each purchase is shared in halves by its
event and its user. The same expressions run on a stream and on a table.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def _cents():
    return F.round(F.col("value") * 100).cast("long")


def purchase_values(events: DataFrame, length: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """(day, user_id, value, n): each user's share of the window's revenue, half of what the user bought."""
    some = events.where("event_type = 'purchase'")
    if late:
        some = some.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)  # a watermark needs a zoned time
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    grouped = some.groupBy(w.alias("w"), "user_id").agg(F.sum(_cents()).alias("cents"), F.count("*").alias("n"))
    return grouped.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "user_id", F.round(F.col("cents") / 200.0, 4).alias("value"), "n")


def sessions(events: DataFrame, gap: str, late: str | None = None) -> DataFrame:
    """(user_id, start, n, value) of runs of events that are at most the gap apart."""
    some = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late) if late else events
    grouped = some.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum(_cents()).alias("cents"))
    return grouped.select("user_id", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", F.round(F.col("cents") / 100.0, 2).alias("value"))


def running_stats(deltas: DataFrame) -> DataFrame:
    """(stratum, k, mean, m2) of a stream of marginals (stratum, delta), kept as state and merged batch by batch."""

    def merge(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        k, mean, m2 = state.get if state.exists else (0, 0.0, 0.0)
        for f in frames:
            for x in f["delta"]:
                k += 1
                step = x - mean
                mean += step / k
                m2 += step * (x - mean)
        state.update((k, mean, m2))
        yield pd.DataFrame({"stratum": [key[0]], "k": [k], "mean": [mean], "m2": [m2]})

    return deltas.groupBy("stratum").applyInPandasWithState(merge, "stratum long, k long, mean double, m2 double", "k long, mean double, m2 double", "update", GroupStateTimeout.NoTimeout)


ORACLES = {
    "window_events_tumbling": "SELECT strftime(CAST(ts AS DATE), '%Y-%m-%d') AS day, user_id, round(CAST(sum(CAST(round(value * 100) AS BIGINT)) AS DOUBLE) / 200.0, 4) AS value, count(*) AS n FROM events WHERE event_type = 'purchase' GROUP BY 1, 2",
    "window_events_sliding": "SELECT strftime(day, '%Y-%m-%d') AS day, user_id, round(CAST(sum(c) AS DOUBLE) / 200.0, 4) AS value, count(*) AS n FROM (SELECT unnest([CAST(ts AS DATE), CAST(ts AS DATE) - INTERVAL 1 DAY]) AS day, user_id, CAST(round(value * 100) AS BIGINT) AS c FROM events WHERE event_type = 'purchase') GROUP BY day, user_id",
    "window_events_session": "WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS no FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(CAST(sum(CAST(round(value * 100) AS BIGINT)) AS DOUBLE) / 100.0, 2) AS value FROM s GROUP BY user_id, no",
}
