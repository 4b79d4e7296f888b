"""Exact values: closed form, enumeration of coalitions, permutations, groups."""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.semivalue import Semivalue, of_relation, shapley_weight, shl, with_weights
from ..plans.workloads import Workload
from .evaluate import marginal, value
from .lineage import compile_view, in_order, relation, settings

#: Others of a target whose coalitions are enumerated, 2^26 at most.
MAX_OTHERS = 26


#: Tuples that one row of a closed form may need.
MAX_NEED = 64


def closed_form(rows: DataFrame, semivalue: Semivalue, unit: float = 1.0) -> DataFrame:
    """(answer, rel, tid, value) for every tuple of sums over joins, however large the answer: each row is shared by the
    tuples it needs, as a unanimity game. Linear in the rows; one shuffle after a partial sum by (answer, tuple, size).

    Sums are kept in two whole numbers, high and low bits, so that they stay exact and can't overflow. Rows that need more
    than 64 tuples raise an error."""
    shares = F.array(F.lit(0.0), *(F.lit(float(semivalue.chance(m))) for m in range(MAX_NEED)))
    share = F.when(F.col("m") <= MAX_NEED, F.get(shares, F.col("m"))).otherwise(F.raise_error(F.lit(f"a row needs more than {MAX_NEED} tuples")).cast("double"))
    each = rows.select("answer", "x", F.size("need").alias("m"), F.explode("need").alias("tid"))
    by_size = each.groupBy("answer", "tid", "m").agg(F.sum(F.shiftright("x", 24)).alias("high"), F.sum(F.col("x").bitwiseAND(F.lit((1 << 24) - 1))).alias("low"))
    x = F.col("high") * F.lit(float(1 << 24)) + F.col("low")
    return by_size.groupBy("answer", "tid").agg((F.sum(x * share) / F.lit(unit)).alias("value")).select("answer", relation(F.col("tid")).alias("rel"), "tid", "value")


def by_rows(rows: DataFrame, workload: Workload, semivalue: Semivalue) -> DataFrame:
    """(answer, rel, tid, value) for every tuple of sums whose rows have alternatives or blockers, however large the answer.

    A sum is a sum of games, one for each row, and tuples that a row doesn't mention have no part in its game; so each is
    enumerated by itself, over the few tuples of its row, and the values add up. Rows that mention the same are one game;
    one that mentions over 27 tuples raises an error."""
    if workload.agg != "sum":
        raise ValueError("only sums fall apart into rows")
    rows = rows.withColumns({c: in_order(c) for c in ("any_of", "none_of")})
    alike = rows.groupBy("answer", "need", "any_of", "none_of").agg(F.sum("x").alias("x"))
    size = F.size(F.array_distinct(F.flatten(F.concat(F.array("need"), "any_of", "none_of"))))
    named = F.concat_ws("#", "answer", F.xxhash64("need", "any_of", "none_of").cast("string"))
    named = F.when(size <= MAX_OTHERS + 1, named).otherwise(F.raise_error(F.concat(F.lit(f"a row of more than {MAX_OTHERS + 1} tuples in answer "), F.col("answer"))).cast("string"))
    games = alike.withColumns({"whole": F.col("answer"), "answer": named})
    names = games.select("answer", "whole")
    each = by_subset(settings(compile_view(games, MAX_OTHERS + 1)), workload, semivalue)
    return each.join(names, "answer").groupBy(F.col("whole").alias("answer"), "rel", "tid").agg(F.sum("value").alias("value"))


def coalitions(settings: DataFrame) -> DataFrame:
    """Every coalition of the others, as `mask`, for each setting. Blocks of 1024 are dealt to the tasks before they are
    spelled out, so that a setting with many coalitions is shared by all. Settings of more than 26 others raise an error."""
    others = F.col("n") - 1
    blocks = F.sequence(F.lit(0).cast("long"), shl(F.lit(1).cast("long"), F.greatest(others - 10, F.lit(0))) - 1)
    refuse = F.raise_error(F.concat(F.lit(f"more than {MAX_OTHERS} others to enumerate in answer "), F.col("answer"))).cast("array<bigint>")
    high = settings.select("*", F.explode(F.when(others <= MAX_OTHERS, blocks).otherwise(refuse)).alias("hi")).repartition("answer", "tid", "hi")
    low = high.select("*", F.explode(F.sequence(F.lit(0).cast("long"), shl(F.lit(1).cast("long"), F.least(others, F.lit(10))) - 1)).alias("lo"))
    dense = shl(F.col("hi"), 10) + F.col("lo")
    below = F.col("bit") - 1  # bits of players before the target stay, those behind move up by one
    return low.withColumn("mask", dense.bitwiseAND(below).bitwiseOR(shl(dense.bitwiseAND(F.bitwise_not(below)), 1))).drop("hi", "lo")


def by_subset(settings: DataFrame, workload: Workload, semivalue: Semivalue) -> DataFrame:
    """(answer, rel, tid, value) by all coalitions: the ground truth, 2^(n-1) evaluations."""
    weight = F.get("omega", F.bit_count("mask"))
    deltas = coalitions(with_weights(settings, semivalue)).select("answer", "rel", "tid", F.bit_count("mask").alias("k"), weight.alias("w"), marginal(F.col("view"), F.col("mask"), F.col("bit"), workload).alias("d"))
    by_size = deltas.groupBy("answer", "rel", "tid", "k", "w").agg(F.sum("d").alias("d"))
    return by_size.groupBy("answer", "rel", "tid").agg((F.sum(F.col("w") * F.col("d")) / F.lit(workload.unit)).alias("value"))


def stratum_table(settings: DataFrame, workload: Workload, semivalue: Semivalue, letters: str) -> DataFrame:
    """By relation vector of the others: coalitions, value weight, mean and deviation of the marginals, share of zeros."""
    counted = [F.bit_count(F.col("mask").bitwiseAND(F.aggregate(F.filter("others", of_relation(r)), F.lit(0).cast("long"), lambda a, p: a.bitwiseOR(p["bit"])))) for r in letters]
    weight = F.get("omega", F.bit_count("mask"))
    deltas = coalitions(with_weights(settings, semivalue)).select("answer", "tid", F.array(*counted).alias("vec"), weight.alias("w"), marginal(F.col("view"), F.col("mask"), F.col("bit"), workload).cast("double").alias("d"))
    return deltas.groupBy("answer", "tid", "vec", "w").agg(
        F.count("*").alias("n_coal"), F.avg("d").alias("mean"), F.stddev_pop("d").alias("sigma"), F.min("d").alias("least"), F.max("d").alias("most"), F.avg((F.col("d") == 0).cast("int")).alias("zeros")
    ).withColumn("w_value", F.col("w") * F.col("n_coal")).drop("w")


def by_permutation(settings: DataFrame, workload: Workload) -> DataFrame:
    """Shapley values by all orders of at most 8 players; for tests and examples. Larger settings raise an error."""
    orders = settings.sparkSession.createDataFrame([(n, list(p)) for n in range(1, 9) for p in permutations(range(n))], "n int, order array<int>")
    each = settings.join(F.broadcast(orders), "n", "left").withColumn("everyone", F.sort_array(F.concat(F.transform("others", lambda p: p["bit"]), F.array("bit"))))
    turn = F.transform("order", lambda i: F.get(F.col("everyone"), i))
    before = F.slice(turn, F.lit(1), F.array_position(turn, F.col("bit")).cast("int") - 1)
    known = F.aggregate(before, F.lit(0).cast("long"), lambda a, b: a.bitwiseOR(b))
    mask = F.when(F.col("order").isNotNull(), known).otherwise(F.raise_error(F.lit("more than 8 players to order")).cast("long"))
    return each.withColumn("mask", mask).groupBy("answer", "rel", "tid").agg((F.avg(marginal(F.col("view"), F.col("mask"), F.col("bit"), workload)) / F.lit(workload.unit)).alias("value"))


def owen(settings: DataFrame, workload: Workload, letters: str) -> DataFrame:
    """Owen values with the relations as groups: coalitions of whole other groups, then of members of the target's own."""
    group = {r: F.aggregate(F.filter("others", of_relation(r)), F.lit(0).cast("long"), lambda a, p: a.bitwiseOR(p["bit"])) for r in letters}
    foreign = F.filter(F.array(*(F.when(F.col("rel") != r, group[r]).otherwise(F.lit(0).cast("long")) for r in letters)), lambda m: m != 0)
    own = F.transform(F.filter("others", lambda p: p["rel"] == F.col("rel")), lambda p: p["bit"])
    one = F.lit(1).cast("long")

    def chosen(masks: str, pick: str):
        return F.aggregate(F.transform(masks, lambda m, i: F.when(F.col(pick).bitwiseAND(shl(one, i)) != 0, m).otherwise(F.lit(0).cast("long"))), F.lit(0).cast("long"), lambda a, m: a.bitwiseOR(m))

    base = settings.withColumns({"foreign": foreign, "own": own})
    picks = base.select("*", F.explode(F.sequence(F.lit(0).cast("long"), shl(one, F.size("foreign")) - 1)).alias("g")).select(
        "*", F.explode(F.sequence(F.lit(0).cast("long"), shl(one, F.size("own")) - 1)).alias("m")
    )
    weight = shapley_weight(F.size("foreign") + 1, F.bit_count("g")) * shapley_weight(F.size("own") + 1, F.bit_count("m"))
    mask = chosen("foreign", "g").bitwiseOR(chosen("own", "m"))
    return picks.withColumns({"w": weight, "mask": mask}).groupBy("answer", "rel", "tid").agg(
        (F.sum(F.col("w") * marginal(F.col("view"), F.col("mask"), F.col("bit"), workload)) / F.lit(workload.unit)).alias("value")
    )


def totals(view: DataFrame, workload: Workload) -> DataFrame:
    """(answer, whole, empty): the value of all players and of none."""
    everyone = F.aggregate("players", F.lit(0).cast("long"), lambda a, p: a.bitwiseOR(p["bit"]))
    return view.select("answer", (value(F.col("view"), everyone, workload) / F.lit(workload.unit)).alias("whole"), (value(F.col("view"), F.lit(0).cast("long"), workload) / F.lit(workload.unit)).alias("empty"))
