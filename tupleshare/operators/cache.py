"""A store of coalition values that outlives a run, shared by all targets, methods and seeds of an answer."""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.workloads import Workload
from .evaluate import value

SCHEMA = "answer string, s long, v long"


def stored(spark: SparkSession, path: str) -> DataFrame:
    """What the store has; empty if there is none yet."""
    try:
        return spark.read.schema(SCHEMA).parquet(path)
    except AnalysisException as e:
        if e.getCondition() != "PATH_NOT_FOUND":
            raise
        return spark.createDataFrame([], SCHEMA)


def extend(draws: DataFrame, workload: Workload, path: str) -> int:
    """Evaluates the coalitions of the draws (answer, view, bit, mask) that the store lacks and appends them; says how many.

    The misses are an anti-join on (answer, coalition), so the work is that of the new coalitions only."""
    spark = draws.sparkSession
    asked = draws.select("answer", F.explode(F.array("mask", F.col("mask").bitwiseOR(F.col("bit")))).alias("s")).distinct()
    views = draws.select("answer", "view").dropDuplicates(["answer"])
    before = stored(spark, path)
    missing = asked.join(before, ["answer", "s"], "left_anti").join(views, "answer")
    had = before.count()
    missing.select("answer", "s", value(F.col("view"), F.col("s"), workload).alias("v")).write.mode("append").parquet(path)
    return stored(spark, path).count() - had


def marginals_from(draws: DataFrame, workload: Workload, path: str) -> DataFrame:
    """Adds `delta` to draws (answer, view, bit, mask) from stored values; what the store lacks is evaluated."""
    store = stored(draws.sparkSession, path)
    low = store.select("answer", F.col("s").alias("mask"), F.col("v").alias("__v0"))
    high = store.select("answer", F.col("s").alias("__s1"), F.col("v").alias("__v1"))
    both = draws.withColumn("__s1", F.col("mask").bitwiseOR(F.col("bit"))).join(low, ["answer", "mask"], "left").join(high, ["answer", "__s1"], "left")
    v1, v0 = (F.coalesce(v, value(F.col("view"), F.col(s), workload)) for v, s in (("__v1", "__s1"), ("__v0", "mask")))
    return both.withColumn("delta", v1 - v0).drop("__s1", "__v0", "__v1")
