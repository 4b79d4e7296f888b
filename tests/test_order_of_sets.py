import random

from pyspark.sql import functions as F

from tupleshare.functions.semivalue import Semivalue
from tupleshare.operators import evaluate, exact, lineage
from tupleshare.operators import estimate as est
from tupleshare.plans.workloads import Workload

ROWS = [("a", 1, [f"o|{k}"], [[f"l|{k}|{j}"] for j in range(5)], []) for k in range(40)]
SCHEMA = "answer string, x long, need array<string>, any_of array<array<string>>, none_of array<array<string>>"


def test_rows_come_with_their_sets_in_order(spark):
    w = Workload("u", "SELECT 'a' AS answer, CAST(1 AS BIGINT) AS x, array('o|1') AS need, array(array('l|2'), array('l|1')) AS any_of", "sum", 0, 1.0, False)
    assert lineage.rows_of(spark, "", w).first().any_of == [["l|1"], ["l|2"]]


def test_row_games_whose_lists_come_in_another_order_each_time(spark):
    """As lists gathered over a shuffle do where executors fetch from each other."""
    mix = F.udf(lambda s: random.sample(s, len(s)), "array<array<string>>").asNondeterministic()
    rows = spark.createDataFrame(ROWS, SCHEMA).repartition(4).withColumn("any_of", mix("any_of"))
    w = Workload("u", "", "sum", 0, 1.0, False)
    got = {r.tid: r.value for r in exact.by_rows(rows, w, Semivalue.shapley()).collect()}
    assert len(got) == 240 and abs(sum(got.values()) - 40) < 1e-9
    assert all(abs(v - (5 / 6 if t[0] == "o" else 1 / 30)) < 1e-9 for t, v in got.items())


def test_joined_values_whose_lists_come_in_another_order_each_time(spark):
    mix = F.udf(lambda s: random.sample(s, len(s)), "array<array<string>>").asNondeterministic()
    rows = spark.createDataFrame(ROWS[:4], SCHEMA).repartition(4)
    w = Workload("u", "", "sum", 0, 1.0, False)
    draws = est._plain_draws(lineage.settings(lineage.compile_view(rows)), 3, 1).withColumn("coalition", F.concat_ws("/", "tid", "draw"))
    everyone = draws.withColumns({"mask": F.lit((1 << 24) - 1).cast("long"), "players": F.concat("others", F.array(F.struct("rel", "tid", "bit")))})
    mixed = rows.withColumn("any_of", mix("any_of"))
    assert {r.v for r in evaluate.tagged(mixed, evaluate.memberships(everyone, False), everyone, w).collect()} == {4}
