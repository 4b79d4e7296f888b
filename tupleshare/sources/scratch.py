"""Tables between steps, in the folder that driver and executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    d = spark.conf.get("spark.checkpoint.dir", None)
    if d:
        return d.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    d = "file://" + tempfile.mkdtemp(prefix="tupleshare-")
    spark.conf.set("spark.checkpoint.dir", d)
    return d


def _delete(spark: SparkSession, path: str) -> None:
    try:
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session may have gone; the folder is scratch
        pass


def write_and_read(df: DataFrame) -> DataFrame:
    """Cuts the lineage: survives lost executors, and is computed once."""
    spark, schema = df.sparkSession, df.schema
    path = f"{shared_dir(spark)}/tupleshare-{uuid.uuid4().hex}"
    df.write.parquet(path)
    atexit.register(_delete, spark, path)
    return spark.read.schema(schema).parquet(path)


def file_sizes(spark: SparkSession, df: DataFrame) -> list[int]:
    """Bytes of each file that a written table is read from."""
    conf, path = spark.sparkContext._jsc.hadoopConfiguration(), spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    return [path(f).getFileSystem(conf).getFileStatus(path(f)).getLen() for f in df.inputFiles()]
