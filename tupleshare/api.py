"""One call for all methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.semivalue import MAX_PLAYERS, Semivalue
from .operators import estimate, exact, lineage
from .plans.workloads import WORKLOADS, Workload


#: Tuples of the largest answers of sums that are enumerated whole; the closed form and row games are as exact and linear.
ENUMERATED = 12


def attribute(
    spark: SparkSession, sf_dir: str, workload: Workload | str, method: str = "relvec_adaptive", targets: DataFrame | None = None, where: str = "TRUE",
    budget: int = 1000, runs: int = 1, semivalue: Semivalue | None = None, seed: int = 42, **more,
) -> DataFrame:
    """(answer, tid, estimate, se, ...) of the targets (answer, tid), or of all tuples.

    method: closed_form (sums over joins, any number of players), exact, or one of estimate.METHODS. Answers with more
    players than the method can take get the closed form, or sums with alternatives and blockers their row games, which
    are exact, with nulls in the columns of the sampling; a ValueError tells where there are none. Ratios, and other answers
    than sums that masks can't take, are sampled on their rows by mc_multilinear. A target that no answer depends on has the value 0. `where` selects answers;
    `more` goes to the method."""
    w = WORKLOADS[workload] if isinstance(workload, str) else workload
    semivalue = semivalue or Semivalue.shapley()
    rows = lineage.rows_of(spark, sf_dir, w).where(where)
    closed = w.agg == "sum" and "any_of" not in w.rows and "none_of" not in w.rows
    if method == "closed_form":
        if not closed:
            raise ValueError("the closed form is for sums over joins")
        out = exact.closed_form(rows, semivalue, w.unit).select("answer", "tid", F.col("value").alias("estimate"))
    else:
        lin = lineage.lineage(rows)
        most = (ENUMERATED if w.agg == "sum" else exact.MAX_OTHERS + 1) if method == "exact" else MAX_PLAYERS
        large = lin.groupBy("answer").count().where(F.col("count") > most).select("answer")
        if targets is not None:
            large = large.join(targets.select("answer").distinct(), "answer", "left_semi")
        if w.agg == "ratio" and method != "mc_multilinear":
            raise ValueError("ratios are for mc_multilinear, which samples on rows")
        any_large = w.agg != "ratio" and not large.isEmpty()
        on_rows = method == "mc_multilinear" and w.agg != "sum"
        if any_large and w.agg != "sum" and not on_rows:
            raise ValueError(f"{w.name} has answers of more than {most} tuples, which {method} can't take")
        if on_rows and (any_large or w.agg == "ratio"):
            if runs != 1 or semivalue.name != "shapley" or more:
                raise ValueError("sampling on rows gives one run of Shapley values, without options")
            out = estimate.multilinear_totals(rows, lin.select("answer", "tid") if targets is None else targets, w, budget, seed)
            return out if targets is None else targets.join(out, ["answer", "tid"], "left").withColumn("estimate", F.coalesce("estimate", F.lit(0.0)))
        settings = lineage.settings(lineage.compile_view(rows.join(large, "answer", "left_anti") if any_large else rows), targets)
        if method == "exact":
            out = exact.by_subset(settings, w, semivalue).select("answer", "tid", F.col("value").alias("estimate"))
        else:
            letters = "".join(sorted(r["rel"] for r in lin.select("rel").distinct().collect()))
            out = estimate.estimate(settings, w, method, budget, letters, runs, seed=seed, semivalue=semivalue, **more)
        if any_large:
            rest = rows.join(large, "answer", "left_semi")
            whole = (exact.closed_form(rest, semivalue, w.unit) if closed else exact.by_rows(rest, w, semivalue)).select("answer", "tid", F.col("value").alias("estimate"))
            whole = whole if targets is None else whole.join(targets, ["answer", "tid"], "left_semi")
            out = out.unionByName(whole, allowMissingColumns=True)
    if targets is None:
        return out
    return targets.join(out, ["answer", "tid"], "left").withColumn("estimate", F.coalesce("estimate", F.lit(0.0)))
