"""Reports over tuple values, and operators that Spark has no single word for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def contribution_rollup(values: DataFrame) -> DataFrame:
    """Values summed by answer and relation, by answer, and in all."""
    return values.rollup("answer", "rel").agg(F.round(F.sum("value"), 6).alias("value"), F.count("*").alias("n"))


def contribution_cube(values: DataFrame) -> DataFrame:
    return values.withColumn("positive", F.col("value") > 10000).cube("rel", "positive").agg(F.round(F.sum("value"), 2).alias("value"), F.count("*").alias("n"))


def latest_before(events: DataFrame, of: str, before: str) -> DataFrame:
    """For each event of one type the latest one of another by the same user, not after it: one window, no range join."""
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == before, 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    some = events.where(F.col("event_type").isin(of, before)).select("event_id", "user_id", "event_type", "ts")
    marked = some.withColumn("prior", F.last(F.when(F.col("event_type") == before, F.struct("ts", "event_id")), ignorenulls=True).over(w))
    return marked.where(F.col("event_type") == of).select("event_id", "user_id", F.col("prior.event_id").alias("prior_id"))


def json_props(events: DataFrame) -> DataFrame:
    """How many events have which properties."""
    keys = F.json_object_keys("props")
    return events.select("event_type", F.explode(keys).alias("key")).groupBy("event_type", "key").agg(F.count("*").alias("n"))


ORACLES = {
    "asof_events": """SELECT event_id, user_id, prior_id FROM (SELECT event_id, user_id, event_type,
 last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, CASE WHEN event_type = 'click' THEN 0 ELSE 1 END, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS prior_id
 FROM events WHERE event_type IN ('purchase', 'click')) WHERE event_type = 'purchase'""",
    "json_props": "SELECT event_type, key, count(*) AS n FROM (SELECT event_type, unnest(json_keys(props)) AS key FROM events) GROUP BY event_type, key",
}
