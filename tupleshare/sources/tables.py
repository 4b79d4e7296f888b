"""The given tables, and SQL text over them that Spark and DuckDB both run."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "labels")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def run_sql(spark: SparkSession, sf_dir: str, text: str, **frames: DataFrame) -> DataFrame:
    """Runs SQL in which `{name}` stands for a table or one of the frames."""
    named = {n: frames[n] if n in frames else load(spark, sf_dir, n) for n in dict.fromkeys(re.findall(r"\{(\w+)\}", text))}
    return spark.sql(text, **named)


def duck_sql(text: str) -> str:
    """The same SQL for DuckDB, whose lists have other function names."""
    text = re.sub(r"\{(\w+)\}", r"\1", text)
    for spark_name, duck_name in (("collect_list", "list"), ("sort_array", "list_sort"), ("array", "list_value"), ("size", "len")):
        text = re.sub(rf"\b{spark_name}\(", f"{duck_name}(", text)
    return text
