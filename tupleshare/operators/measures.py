"""Accuracy and cost of estimates."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.semivalue import Semivalue
from ..plans.workloads import Workload
from ..sources.scratch import file_sizes, write_and_read
from . import estimate
from .evaluate import marginals
from .exact import totals
from .strata import SETTING, allocate, share_of


def errors(runs: DataFrame, exact: DataFrame, by: tuple[str, ...] = ("method", "budget")) -> DataFrame:
    """By method, budget and setting over the runs: mean relative error (null where the exact value is 0; the mean
    absolute error stands beside it), mean estimate, bias, variance, root mean square error, coverage."""
    joined = runs.join(exact.select(*SETTING, F.col("value").alias("exact")), list(SETTING))
    off = F.col("estimate") - F.col("exact")
    return joined.groupBy(*by, *SETTING).agg(
        F.count("*").alias("runs"), F.first("exact").alias("exact"), F.avg("estimate").alias("mean_estimate"),
        F.avg(F.when(F.col("exact") != 0, F.abs(off) / F.abs("exact"))).alias("mre"), F.avg(F.abs(off)).alias("mean_abs_error"),
        F.avg(off).alias("bias"), F.var_samp("estimate").alias("variance"), F.sqrt(F.avg(off * off)).alias("rmse"), F.avg("starved_weight").alias("starved_weight"), F.avg("draws").alias("draws"),
    )


def rank_methods(measured: DataFrame, by: tuple[str, ...] = ("budget", *SETTING), measure: str = "mre") -> DataFrame:
    """Place of each method by the measure, the best first; ties share a place."""
    return measured.withColumn("place", F.dense_rank().over(Window.partitionBy(*by).orderBy(F.col(measure).asc_nulls_last())))


def method_table(measured: DataFrame, methods: list[str], measure: str = "mre") -> DataFrame:
    """A row for each setting and budget, a column for each method."""
    return measured.groupBy(*SETTING, "budget").pivot("method", methods).agg(F.first(measure))


def axioms(values: DataFrame, view: DataFrame, workload: Workload) -> DataFrame:
    """(answer, total, whole, gap): efficiency, that the values of an answer add up to that of all its players."""
    summed = values.groupBy("answer").agg(F.sum("value").alias("total"))
    ends = totals(view, workload)
    return summed.join(ends, "answer").select("answer", "total", (F.col("whole") - F.col("empty")).alias("whole"), (F.col("total") - F.col("whole") + F.col("empty")).alias("gap"))


def coverage(strata: DataFrame) -> DataFrame:
    """Of allocated strata: how many, how many live and drawn from, and the live weight that gets no draw."""
    starved = F.col("live") & (F.col("m") == 0)
    return strata.groupBy(*SETTING).agg(
        F.count("*").alias("strata"), F.sum(F.col("live").cast("int")).alias("live"), F.sum((F.col("m") > 0).cast("int")).alias("drawn"),
        F.sum("m").cast("long").alias("draws"), F.sum(F.when(starved, F.col("w_value")).otherwise(0.0)).alias("starved_weight"),
    )


def predicted_variance(strata: DataFrame, table: DataFrame, rule: str, budget: int, floor: int = 1) -> DataFrame:
    """Of the estimate under a rule, from the exact deviations of a stratum table: the sum of W^2 sigma^2 / m; Neyman
    rules use those deviations too, which makes them the ceiling of what adapting can reach."""
    known = strata.join(table.select(*SETTING, "vec", "sigma"), [*SETTING, "vec"])
    dealt = allocate(known, share_of(rule, F.col("sigma")), budget, floor)
    part = F.pow("w_value", F.lit(2.0)) * F.pow("sigma", F.lit(2.0)) / F.col("m")
    return dealt.groupBy(*SETTING).agg(F.sum(F.when(F.col("m") > 0, part).otherwise(0.0)).alias("variance"), F.sum(F.when((F.col("m") == 0) & F.col("live"), F.col("w_value")).otherwise(0.0)).alias("starved_weight"))


def convergence(deltas: DataFrame, checkpoints: list[int]) -> DataFrame:
    """(setting, run, checkpoint, estimate) of plain means after the first draws: one sum for each step between
    checkpoints, then a running sum over these few rows."""
    step = F.lit(len(checkpoints))
    for k in reversed(range(len(checkpoints))):
        step = F.when(F.col("draw") < checkpoints[k], F.lit(k)).otherwise(step)
    steps = deltas.withColumn("step", step).where(F.col("step") < len(checkpoints)).groupBy(*SETTING, "run", "step").agg(F.sum("delta").alias("s"), F.count("*").alias("k"))
    w = Window.partitionBy(*SETTING, "run").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    at = F.get(F.array(*map(F.lit, checkpoints)), F.col("step"))
    return steps.select(*SETTING, "run", at.alias("checkpoint"), (F.sum("s").over(w) / F.sum("k").over(w)).alias("estimate"))


def top_k(values: DataFrame, k: int, value: str = "value") -> DataFrame:
    w = Window.partitionBy("answer").orderBy(F.desc(F.round(value, 6)), "tid")
    return values.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)


def ranking_quality(values: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """By answer: share of the exact top k that the estimates' top k has, and Kendall's tau over all pairs of tuples."""
    both = values.select("answer", "tid", F.col("estimate").alias("e")).join(exact.select("answer", "tid", F.col("value").alias("x")), ["answer", "tid"])
    w = Window.partitionBy("answer")
    placed = both.withColumns({"pe": F.row_number().over(w.orderBy(F.desc(F.round("e", 6)), "tid")), "px": F.row_number().over(w.orderBy(F.desc(F.round("x", 6)), "tid"))})
    overlap = placed.groupBy("answer").agg((F.sum(((F.col("pe") <= k) & (F.col("px") <= k)).cast("int")) / F.least(F.lit(k), F.count("*"))).alias("overlap"))
    listed = placed.groupBy("answer").agg(F.collect_list(F.struct("e", "x")).alias("l"))  # at most as many as an answer has players
    sign = lambda a, b: F.signum(F.round(a - b, 6))
    pairs = F.aggregate("l", F.lit(0.0), lambda acc, p: acc + F.aggregate("l", F.lit(0.0), lambda in_, q: in_ + sign(p["e"], q["e"]) * sign(p["x"], q["x"])))
    return overlap.join(listed.select("answer", (pairs / (F.size("l") * (F.size("l") - 1))).alias("tau")), "answer")


def timed(action: Callable[[], object]) -> tuple[object, float]:
    t = time.perf_counter()
    out = action()
    return out, time.perf_counter() - t


def _run(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def view_size(view: DataFrame) -> DataFrame:
    """Of a compiled view: answers, rows, players."""
    return view.agg(F.count("*").alias("answers"), F.coalesce(F.sum(F.size("view")), F.lit(0)).cast("long").alias("rows"), F.coalesce(F.sum(F.size("players")), F.lit(0)).cast("long").alias("players"))


def compile_report(spark: SparkSession, items: dict[str, tuple[Callable[[], DataFrame], Callable[[], DataFrame], Workload]]) -> DataFrame:
    """(workload, original_s, build_s, compiled_s, bytes): seconds of the query on the tables, of writing its joined and
    filtered rows with tuple ids, and of the query on these, with the bytes written. By name: the query, the rows."""
    out = []
    for name, (query, rows, _) in items.items():
        original = timed(lambda q=query: _run(q()))[1]
        view, build = timed(lambda r=rows: write_and_read(r()))
        compiled = timed(lambda v=view: _run(v.groupBy("answer").agg(F.sum("x"))))[1]
        size = sum(file_sizes(spark, view))
        out.append((name, round(original, 3), round(build, 3), round(compiled, 3), size))
    return spark.createDataFrame(out, "workload string, original_s double, build_s double, compiled_s double, bytes long")


def grid(settings: DataFrame, workload: Workload, exact: DataFrame, letters: str, methods: tuple[str, ...], budgets: tuple[int, ...], runs: int, profile: str) -> DataFrame:
    """By method, budget and setting the errors over the runs, with the seconds of the whole estimate, of the evaluation of
    as many drawn coalitions alone, and of the enumeration that gives the exact values."""
    truth, exact_s = timed(lambda: write_and_read(exact))
    out = None
    for b in budgets:
        pooled, strata, width = estimate.prepare(settings, estimate.Plan(b, letters), Semivalue.shapley())
        dealt = allocate(estimate.with_runs(strata, runs), share_of("value"), b, 1, by=estimate.RUN)
        draws = write_and_read(estimate.draw(dealt, pooled, estimate.Plan(b, letters), 0, width).select(*SETTING, "view", "bit", "mask"))
        evaluate_s = timed(lambda d=draws: _run(marginals(d, workload, False).agg(F.sum("delta"))))[1]
        for m in methods:
            est, end_to_end_s = timed(lambda m=m, b=b: write_and_read(estimate.estimate(settings, workload, m, b, letters, runs, profile)))
            df = errors(est, truth).withColumns({"end_to_end_s": F.lit(round(end_to_end_s, 3)), "evaluate_s": F.lit(round(evaluate_s, 3)), "exact_s": F.lit(round(exact_s, 3))})
            out = df if out is None else out.unionByName(df)
    return out
