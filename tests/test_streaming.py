"""The same values from a stream as from a table; state merged over batches; queries without the optional parts."""

import subprocess
import sys
from pathlib import Path

import numpy as np
from pyspark.sql import functions as F

from tupleshare.streaming import windows

SF = "/root/testdata/sf0.001"
ROOT = Path(__file__).resolve().parent.parent


def test_windows_on_a_stream(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    values = windows.purchase_values(stream, "1 day", late="40 days")
    query = values.writeStream.outputMode("complete").format("memory").queryName("daily").option("checkpointLocation", str(tmp_path / "state")).start()
    query.processAllAvailable()
    query.stop()
    assert sorted(map(tuple, spark.table("daily").collect())) == sorted(map(tuple, windows.purchase_values(events, "1 day").collect()))


def test_running_statistics(spark, tmp_path):
    rng = np.random.default_rng(1)
    rows = [(int(i % 3), float(x)) for i, x in enumerate(rng.standard_normal(300))]
    df = spark.createDataFrame(rows, "stratum long, delta double")
    df.repartition(4).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    query = windows.running_stats(stream).writeStream.outputMode("update").format("memory").queryName("strata_state").option("checkpointLocation", str(tmp_path / "state")).start()
    query.processAllAvailable()
    query.stop()
    last = spark.table("strata_state").groupBy("stratum").agg(F.max_by(F.struct("k", "mean", "m2"), "k").alias("s")).collect()
    for r in last:
        x = np.array([v for s, v in rows if s == r.stratum])
        assert r.s.k == len(x) and np.allclose([r.s.mean, r.s.m2], [x.mean(), ((x - x.mean()) ** 2).sum()])


def test_entry_without_optional_parts(tmp_path):
    """With the training-data operators deleted the rest still imports and lists its queries."""
    import shutil

    shutil.copytree(ROOT / "tupleshare", tmp_path / "tupleshare", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    said = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; q = e.queries(); print(len(q), 'pipeline' in q, set(e.oracle_sql()) <= set(q))"], cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)})
    assert said.returncode == 0, said.stderr
    assert said.stdout.split()[1:] == ["False", "True"] and int(said.stdout.split()[0]) > 100
