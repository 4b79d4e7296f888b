"""Named queries over the given tables, one or more for each method, variant, baseline, measure and workload."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..api import attribute
from ..functions.semivalue import MAX_PLAYERS, Semivalue
from ..operators import evaluate, exact, lineage, measures, relational, within
from ..operators import estimate as est
from ..operators import strata as st
from ..sources.tables import duck_sql, load, run_sql
from ..streaming import windows
from . import oracles, tpch
from .workloads import FROZEN, LINE, RATIOS, SPJ, WORKLOADS, Workload

Query = Callable[[SparkSession, str], DataFrame]
SHAPLEY, BANZHAF = Semivalue.shapley(), Semivalue.banzhaf()
CLOSED = [w for w in [*SPJ, *FROZEN] if w.agg == "sum"]
#: Tuples of the largest answers that queries enumerate. Larger ones are left to the closed form, row games and sampling.
ENUMERATED = 12
LETTERS = {"w2": "npqrs", "w2_second": "npqrs", "w3_late": "clo", "w3": "clo", "w10": "clno", "w10_wide": "clno", "w18": "clo", "w18_low": "clo", "w21": "lnos"}
#: Tuples of the largest answers that the queries of the stratified methods sample; w18 has no larger one.
SAMPLED = {"w18": MAX_PLAYERS}
#: Draws for each tuple of each answer, and those of the queries that repeat runs or grow budgets.
BUDGET, RUNS, BUDGETS = 100, 5, (1000, 10_000, 100_000)


def rows(spark: SparkSession, sf: str, name: str, where: str = "TRUE") -> DataFrame:
    return lineage.rows_of(spark, sf, WORKLOADS[name]).where(where)


def settings_of(spark: SparkSession, sf: str, name: str, most: int = MAX_PLAYERS) -> DataFrame:
    """All tuples of all answers of at most `most` tuples, on the stored view."""
    return lineage.settings(lineage.compiled(spark, sf, WORKLOADS[name], most))


def small_settings(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return settings_of(spark, sf, name, ENUMERATED)


def whole_view(spark: SparkSession, sf: str, name: str) -> DataFrame:
    """All answers, whatever their size."""
    return lineage.compiled(spark, sf, WORKLOADS[name], None)


def sampled_view(spark: SparkSession, sf: str, name: str, whole: bool = False) -> DataFrame:
    return whole_view(spark, sf, name) if whole else lineage.compiled(spark, sf, WORKLOADS[name], SAMPLED.get(name, ENUMERATED))


def sampled_settings(spark: SparkSession, sf: str, name: str, whole: bool = False) -> DataFrame:
    return lineage.settings(sampled_view(spark, sf, name, whole))


def rounded(df: DataFrame, digits: int, *names: str) -> DataFrame:
    return df.withColumns({n: F.round(n, digits) + F.lit(0.0) for n in names})  # no negative zero


def _plain(spark, sf, name):
    return run_sql(spark, sf, tpch.QUERIES[name])


def _lineage(spark, sf, name):
    return lineage.lineage(rows(spark, sf, name))


def _vectors(spark, sf, name):
    wide = lineage.size_vectors(_lineage(spark, sf, name))
    return wide.select("answer", *LETTERS[name], "players")


def _stats(spark, sf, name):
    return lineage.provenance_stats(_lineage(spark, sf, name))


def _split(spark, sf):
    return lineage.split(load(spark, sf, "lineitem"), F.expr(LINE), _lineage(spark, sf, "w3")).groupBy("endogenous").agg(F.count("*").alias("n"))


def _selected_settings(spark, sf):
    """Of the wide workload the targets whose answers have 16 to 20 lines: the costly ones."""
    vec = lineage.size_vectors(_lineage(spark, sf, "w10_wide")).where("l BETWEEN 16 AND 20 AND o = 5")
    return vec.select("answer", "l", "o", "players")


def _closed(spark, sf, name, semivalue=SHAPLEY):
    w = WORKLOADS[name]
    return rounded(exact.closed_form(rows(spark, sf, name), semivalue, w.unit), 7, "value")


def _subset(spark, sf, name, semivalue=SHAPLEY):
    return rounded(exact.by_subset(small_settings(spark, sf, name), WORKLOADS[name], semivalue), 6, "value")


def _by_rows(spark, sf, name):
    return rounded(exact.by_rows(rows(spark, sf, name), WORKLOADS[name], SHAPLEY), 7, "value")


def _attributed(spark, sf, name, method="exact"):
    """All answers through the one call, whatever their size."""
    out = attribute(spark, sf, name, method)
    return out.select("answer", "tid", F.round("estimate", 6).alias("estimate"))


def _permutation(spark, sf):
    few = settings_of(spark, sf, "w3", 5)
    return rounded(exact.by_permutation(few, WORKLOADS["w3"]), 7, "value")


def _owen(spark, sf, name):
    return rounded(exact.owen(small_settings(spark, sf, name), WORKLOADS[name], LETTERS[name]), 6, "value")


def _axioms(spark, sf, name):
    w, view = WORKLOADS[name], lineage.compiled(spark, sf, WORKLOADS[name])
    return rounded(measures.axioms(exact.closed_form(rows(spark, sf, name), SHAPLEY, w.unit), view, w), 4, "total", "whole").drop("gap")


def _stratum_table(spark, sf, name, by_vector=True):
    settings, w = small_settings(spark, sf, name), WORKLOADS[name]
    if not by_vector:
        settings = settings.withColumn("others", F.transform("others", lambda p: F.struct(F.lit("*").alias("rel"), p["tid"].alias("tid"), p["bit"].alias("bit"))))
    table = exact.stratum_table(settings, w, SHAPLEY, LETTERS[name] if by_vector else "*")
    return table.select("answer", "tid", F.concat_ws(",", F.transform("vec", lambda x: x.cast("string"))).alias("vec"), F.col("n_coal").cast("double").alias("n_coal"), F.round("w_value", 9).alias("w_value"), F.round(F.col("mean") / F.lit(w.unit), 9).alias("mean"))


def _strata(spark, sf, name, letters=True, most=None, **more):
    most = most or SAMPLED.get(name, ENUMERATED)
    pooled = st.pools(settings_of(spark, sf, name, most), LETTERS[name] if letters else None)
    return pooled, st.vectors(pooled, SHAPLEY, len(LETTERS[name]) if letters else 1, **more)


def _weights(spark, sf, name, letters=True):
    """The same weights as in the stratum table, from counts alone."""
    df = _strata(spark, sf, name, letters, ENUMERATED)[1]
    return df.select("answer", "tid", F.concat_ws(",", F.transform("vec", lambda x: x.cast("string"))).alias("vec"), "n_coal", F.round("w_value", 9).alias("w_value"))


def _alloc(spark, sf, rule, floor):
    """What the draws of each tuple of w18 come to under a rule; Neyman rules need the enumerated deviations."""
    neyman = rule.startswith("neyman")
    strata = _strata(spark, sf, "w18", most=ENUMERATED if neyman else None)[1]
    if neyman:
        table = exact.stratum_table(small_settings(spark, sf, "w18"), WORKLOADS["w18"], SHAPLEY, LETTERS["w18"])
        strata = strata.join(table.select("answer", "tid", "vec", "sigma"), ["answer", "tid", "vec"])
    dealt = st.allocate(strata, st.share_of(rule, F.col("sigma") if neyman else None), BUDGET, floor)
    return rounded(measures.coverage(dealt), 9, "starved_weight")


def _coverage(spark, sf, name):
    return rounded(measures.coverage(st.allocate(_strata(spark, sf, name)[1], st.share_of("count"), BUDGET, 0)), 9, "starved_weight")


def _prune(spark, sf, name):
    df = _strata(spark, sf, name, prune=True)[1]
    return df.groupBy("answer", "tid").agg(F.count("*").alias("strata"), F.sum(F.col("live").cast("int")).alias("live"))


def _coarse(spark, sf, name, bins):
    return rounded(est.cells(_strata(spark, sf, name, bins=bins)[1]).select("answer", "tid", "stratum", F.size("inside").alias("vectors"), "w_value"), 9, "w_value")


def _attribute(spark, sf):
    return rounded(est.stratified(settings_of(spark, sf, "w18"), WORKLOADS["w18"], est.Plan(BUDGET, "clo", attribute_quantiles=2)), 4, "estimate", "se")


def _estimate(spark, sf, method, name, runs=1, budget=BUDGET, cycles=2, whole=False, **more):
    """whole: all answers, whatever their size."""
    out = est.estimate(sampled_settings(spark, sf, name, whole), WORKLOADS[name], method, budget, LETTERS[name], runs, cycles=cycles, view=sampled_view(spark, sf, name, whole), **more)
    return out.select("answer", "tid", "run", F.round("estimate", 6).alias("estimate"), F.round("se", 6).alias("se"), F.round("starved_weight", 9).alias("starved_weight"), "draws", "method", "budget")


def _sampled(spark, sf, method, name, budget, runs):
    out = est.estimate(small_settings(spark, sf, name), WORKLOADS[name], method, budget, LETTERS[name], runs)
    return rounded(out.select("answer", "tid", "run", "estimate"), 6, "estimate")


def _estimate_census(spark, sf, name):
    """Strata that get as many draws as they have coalitions are counted out, which enumerates: small answers only."""
    out = est.estimate(small_settings(spark, sf, name), WORKLOADS[name], "relvec", BUDGET, LETTERS[name], view=lineage.compiled(spark, sf, WORKLOADS[name], ENUMERATED), census=True)
    return rounded(out.select("answer", "tid", "run", "estimate", "se", "draws"), 6, "estimate", "se")


def _boolean(spark, sf, name):
    w = WORKLOADS[name].boolean()
    return rounded(exact.by_subset(lineage.settings(lineage.compiled(spark, sf, w, ENUMERATED)), w, SHAPLEY), 6, "value")


def _given(spark, sf, name, letters, closed=False):
    """Tuples of some relations are always there and no players."""
    fewer = lineage.with_given(rows(spark, sf, name), lambda t: lineage.relation(t).isin(*letters))
    if closed:
        return rounded(exact.closed_form(fewer, SHAPLEY, WORKLOADS[name].unit), 7, "value")
    return rounded(exact.by_subset(lineage.settings(lineage.compile_view(fewer, ENUMERATED)), WORKLOADS[name], SHAPLEY), 6, "value")


def _totals(spark, sf, name):
    """Any function of an answer's sums, on its rows: all tuples of all answers, whatever their size."""
    data = rows(spark, sf, name)
    view = None if "y" in data.columns else lineage.compiled(spark, sf, WORKLOADS[name])
    out = est.multilinear_totals(data, None, WORKLOADS[name], BUDGET, view=view)
    return rounded(out.select("answer", "tid", "estimate", "draws"), 8, "estimate")


def _pruning(spark, sf, name):
    return within.pruning(sampled_view(spark, sf, name), WORKLOADS[name], est.Plan(200, LETTERS[name]), SHAPLEY)


def _cache_hits(spark, sf, name):
    """Of the draws of all tuples of all answers, whatever their size."""
    return within.cache_hits(sampled_view(spark, sf, name, whole=True), WORKLOADS[name], est.Plan(200, LETTERS[name]), SHAPLEY)


def _tagged(spark, sf, name):
    """Coalitions whose value by joins differs from that by masks (none), beside how many were compared."""
    return within.tagged_differences(sampled_view(spark, sf, name), rows(spark, sf, name), WORKLOADS[name], est.Plan(20, LETTERS[name]), SHAPLEY)


def _compiled(spark, sf, name):
    """Builds the view anew: its answers, rows and players."""
    return measures.view_size(lineage.compile_view(rows(spark, sf, name)))


def _compile_report(spark, sf):
    """By workload: seconds of the original query, of building the view and of the query on the view, and the view's bytes."""
    return measures.compile_report(spark, {n: (partial(_plain, spark, sf, n.split("_")[0]), partial(rows, spark, sf, n), WORKLOADS[n]) for n in WORKLOADS if n.split("_")[0] in tpch.QUERIES})


def _naive(spark, sf):
    """The baseline of one query text for each coalition: the marginal of each order of most lines to three coalitions of
    its lines. Two jobs a marginal; so only orders with the greatest number of lines are worked on."""
    w, name = WORKLOADS["w3_late"], "w3_late"
    lin = _lineage(spark, sf, name)
    sizes = lin.where("rel = 'l'").groupBy("answer").agg(F.sort_array(F.collect_list("tid")).alias("lines"))
    top = sizes.orderBy(F.desc(F.size("lines")), F.col("answer").cast("long")).first()
    total = f"SELECT CAST(coalesce(sum(x), 0) AS BIGINT) FROM ({w.rows}) WHERE answer = '{top['answer']}'" if top else ""
    out = []
    for k in range(min(3, len(top["lines"])) if top else 0):
        kept = {"lineitem": (LINE, top["lines"][: k + 1])}
        with_order = evaluate.naive(spark, sf, total, kept)
        without = evaluate.naive(spark, sf, total, kept | {"orders": ("CAST(o_orderkey AS STRING)", [])})
        out.append((k + 1, (with_order - without) / w.unit))
    return rounded(spark.createDataFrame(out, "lines int, marginal double"), 4, "marginal")


def _costly(spark, sf, name):
    """One setting, as in the published tables: the first order of the answer that costs enumeration most among those of
    at most 12 tuples (w21: 19)."""
    settings = small_settings(spark, sf, name) if name != "w21" else settings_of(spark, sf, name, 19)
    return settings.join(F.broadcast(settings.where("rel = 'o'").orderBy(F.desc("n"), "answer", "tid").limit(1).select("answer", "tid")), ["answer", "tid"])


def _errors(spark, sf, name, methods=est.METHODS, budgets=(BUDGET,), runs=RUNS, settings=None, **more):
    view = lineage.compiled(spark, sf, WORKLOADS[name], ENUMERATED) if settings is None else None
    settings = small_settings(spark, sf, name) if settings is None else settings
    truth = exact.by_subset(settings, WORKLOADS[name], SHAPLEY)
    out = None
    for m in methods:
        for b in budgets:
            df = est.estimate(settings, WORKLOADS[name], m, b, LETTERS[name], runs, cycles=2, view=view, **more)
            out = df if out is None else out.unionByName(df)
    return rounded(measures.errors(out, truth), 6, "exact", "mean_estimate", "mre", "mean_abs_error", "bias", "variance", "rmse", "starved_weight")


def _costly_errors(spark, sf, name, **more):
    return _errors(spark, sf, name, settings=_costly(spark, sf, name), **more)


def _ablation(spark, sf):
    """{size, relvec} x {static, adaptive} x floor {0, 1}, shares by count."""
    settings = _costly(spark, sf, "w21")
    truth = exact.by_subset(settings, WORKLOADS["w21"], SHAPLEY)
    out = None
    for letters in (None, LETTERS["w21"]):
        for cycles in (1, 3):
            for floor in (0, 1):
                plan = est.Plan(1000, letters, "count", "neyman_count", cycles, floor, "largest" if floor else "nearest")
                df = est.stratified(settings, WORKLOADS["w21"], plan, RUNS).withColumn("method", F.lit(plan.named())).withColumn("floor", F.lit(floor))
                out = df if out is None else out.unionByName(df)
    return measures.errors(out, truth, ("method", "floor"))


def _rank(spark, sf):
    return measures.rank_methods(_costly_errors(spark, sf, "w21", budgets=(1000,))).select("method", "budget", "answer", "tid", "mre", "place")


def _convergence(spark, sf):
    """Plain means over random orders after the first 100, 200, 500 and 1000, of all tuples of all answers."""
    sums = within.orders(whole_view(spark, sf, "w18"), WORKLOADS["w18"], [100, 200, 500, 1000])
    return rounded(sums.select("answer", "tid", "run", "checkpoint", (F.col("total") / F.col("draws")).alias("estimate")), 6, "estimate")


def _method_convergence(spark, sf, name):
    """The estimates of the four stratified methods at growing budgets, in the profile that shares by count."""
    return _costly_errors(spark, sf, name, methods=("size", "size_adaptive", "relvec", "relvec_adaptive"), budgets=(100, 300, 1000, 3000), runs=3, profile="count").select(
        "method", "budget", "answer", "tid", "exact", "mean_estimate", "mre", "starved_weight"
    )


def _budgets(spark, sf, name, profile):
    """The published grid: methods and budgets; with the seconds of the whole and of the evaluation alone."""
    settings = _costly(spark, sf, name)
    truth = exact.by_subset(settings, WORKLOADS[name], SHAPLEY)
    return measures.grid(settings, WORKLOADS[name], truth, LETTERS[name], STRATIFIED, BUDGETS, 2, profile)


def _predicted(spark, sf):
    settings = _costly(spark, sf, "w21")
    w, letters = WORKLOADS["w21"], LETTERS["w21"]
    table = exact.stratum_table(settings, w, SHAPLEY, letters)
    strata = st.vectors(st.pools(settings, letters), SHAPLEY, len(letters))
    out = None
    for rule in st.RULES:
        df = measures.predicted_variance(strata, table, rule, BUDGET).withColumn("rule", F.lit(rule))
        out = df if out is None else out.unionByName(df)
    return out


def _ranking(spark, sf):
    settings = small_settings(spark, sf, "w18")
    w = WORKLOADS["w18"]
    return measures.ranking_quality(est.estimate(settings, w, "relvec", BUDGET, LETTERS["w18"]), exact.by_subset(settings, w, SHAPLEY), 3)


def _progress(spark, sf):
    """The anytime reading: estimate, error and draws after every cycle."""
    steps: list = []
    est.stratified(_costly(spark, sf, "w21"), WORKLOADS["w21"], est.Plan(4000, LETTERS["w21"], cycles=4), 1, progress=steps)
    out = None
    for cycle, df in steps:
        df = df.withColumn("cycle", F.lit(cycle))
        out = df if out is None else out.unionByName(df)
    return rounded(est.interval(out), 6, "estimate", "se", "low", "high")


def _huge(spark, sf, name="w14", rel="p"):
    """Sampling without masks, for answers of hundreds of tuples: all tuples of one relation."""
    data = rows(spark, sf, name)
    targets = lineage.lineage(data).where(F.col("rel") == rel).select("answer", "tid")
    return rounded(est.multilinear_rows(data, targets, BUDGET, unit=WORKLOADS[name].unit), 4, "estimate", "se")


def _all_targets(spark, sf):
    """One order of the players serves all targets of an answer, and each of its coalitions is evaluated once."""
    sums = within.orders(whole_view(spark, sf, "w18"), WORKLOADS["w18"], [100])
    return sums.select("answer", "tid", (F.col("total") / F.col("draws")).alias("estimate"))


def _with_totals(spark, sf):
    return relational.contribution_rollup(exact.closed_form(rows(spark, sf, "w10"), SHAPLEY, 1e4))


def _cube(spark, sf):
    return relational.contribution_cube(exact.closed_form(rows(spark, sf, "w10"), SHAPLEY, 1e4))


def _top(spark, sf):
    top = measures.top_k(exact.closed_form(rows(spark, sf, "w10"), SHAPLEY, 1e4), 3)
    return rounded(top.select("answer", "tid", "value", "place"), 7, "value")


STRATIFIED = ("size", "size_adaptive", "relvec", "relvec_adaptive")
WINDOWS = {"tumbling": ("1 day", None), "sliding": ("2 days", "1 day")}


def _window(spark, sf, kind):
    return windows.purchase_values(load(spark, sf, "events"), *WINDOWS[kind])


def _session(spark, sf):
    return windows.sessions(load(spark, sf, "events"), "6 hours")


def _asof(spark, sf):
    return relational.latest_before(load(spark, sf, "events"), "purchase", "click")


def _json(spark, sf):
    return relational.json_props(load(spark, sf, "events"))


def _wide_targets(spark, sf):
    """Tuples of an answer of hundreds of tuples, through the one call: what enumeration can't take gets the closed form."""
    return _attributed(spark, sf, "w14")


def _beta_custom(spark, sf):
    """A weighting given by size, for orders of just the players it is for: all weight on the emptiest coalitions."""
    few = settings_of(spark, sf, "w3", 5).where("n = 5")
    return rounded(exact.by_subset(few, WORKLOADS["w3"], Semivalue.custom("first", [1.0, 1.0, 0.0, 0.0, 0.0])), 6, "value")


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {f"query_{n}": partial(_plain, name=n) for n in tpch.QUERIES}
    out |= {f"lineage_{n}": partial(_lineage, name=n) for n in ("w3", "w21")}
    out |= {f"size_vectors_{n}": partial(_vectors, name=n) for n in ("w10", "w21")}
    out |= {f"provenance_stats_{w.name}": partial(_stats, name=w.name) for w in WORKLOADS.values()}
    out |= {"endogenous_split_w3": _split, "settings_select": _selected_settings}
    out |= {f"shapley_closed_{w.name}": partial(_closed, name=w.name) for w in CLOSED}
    out |= {f"banzhaf_closed_{n}": partial(_closed, name=n, semivalue=BANZHAF) for n in ("w3", "w10")}
    out |= {"beta_closed_w10": partial(_closed, name="w10", semivalue=Semivalue.beta(4, 1)), "shapley_permutation_w3": _permutation}
    out |= {f"shapley_subset_{n}": partial(_subset, name=n) for n in ("w2", "w2_second", "w3_late", "w10", "w18", "w21")}
    out |= {f"shapley_rows_{n}": partial(_by_rows, name=n) for n in ("w4", "w16", "w21")} | {f"attribute_{n}": partial(_attributed, name=n) for n in ("w10", "w21")} | {"attribute_w14": _wide_targets}
    out |= {f"banzhaf_subset_{n}": partial(_subset, name=n, semivalue=BANZHAF) for n in ("w2_second", "w18")} | {"custom_subset_w3": _beta_custom}
    out |= {f"owen_{n}": partial(_owen, name=n) for n in ("w10", "w18", "w2")}
    out |= {f"stratum_table_vector_{n}": partial(_stratum_table, name=n) for n in ("w10", "w18")} | {"stratum_table_size_w18": partial(_stratum_table, name="w18", by_vector=False)}
    out |= {"strata_vector_w10": partial(_weights, name="w10"), "strata_size_w10": partial(_weights, name="w10", letters=False)}
    out |= {f"alloc_{r}_w18": partial(_alloc, rule=r, floor=0) for r in st.RULES} | {"alloc_floor_w18": partial(_alloc, rule="value", floor=1), "coverage_w10": partial(_coverage, name="w10")}
    out |= {"prune_w10": partial(_prune, name="w10"), "prune_w21": partial(_prune, name="w21"), "coarsen_counts_w10": partial(_coarse, name="w10", bins=4), "coarsen_attr_w18": _attribute}
    out |= {f"{m}_{n}": partial(_estimate, method=m, name=n) for m in STRATIFIED for n in ("w2", "w10", "w18", "w21")}
    out |= {f"{m}_count_w18": partial(_estimate, method=m, name="w18", profile="count") for m in STRATIFIED}
    out |= {f"{m}_w18": partial(_sampled, method=m, name="w18", budget=BUDGET, runs=1) for m in ("mc", "mc_permutation", "mc_multilinear")}
    out |= {"relvec_collapse_w3": partial(_estimate, method="relvec", name="w3"), "relvec_cycle_mean_w10": partial(_estimate, method="relvec_adaptive", name="w10", pooling="cycle_mean", whole=True), "relvec_pruned_w21": partial(_estimate, method="relvec", name="w21", prune=True)}
    out |= {"relvec_binned_w10": partial(_estimate, method="relvec", name="w10", bins=4, whole=True), "relvec_binned_adaptive_w10": partial(_estimate, method="relvec_adaptive", name="w10", bins=4, whole=True), "census_w18": partial(_estimate_census, name="w18"), "all_targets_w18": _all_targets, "multilinear_rows_w14": _huge, "multilinear_rows_w20": partial(_huge, name="w20", rel="s")}
    out |= {f"prune_coalitions_{n}": partial(_pruning, name=n) for n in ("w2_second", "w10", "w18", "w21")} | {"relvec_pruned_draws_w21": partial(_estimate, method="relvec", name="w21", prune_draws=True)}
    out |= {f"{m}_structure_w21": partial(_estimate, method=m, name="w21", rule="structure") for m in ("relvec", "relvec_adaptive")} | {f"boolean_subset_{n}": partial(_boolean, name=n) for n in ("w10", "w21")}
    out |= {"given_closed_w10": partial(_given, name="w10", letters="n", closed=True), "given_subset_w2_second": partial(_given, name="w2_second", letters="nr")}
    out |= {f"totals_{w}": partial(_totals, name=w) for w in (*(r.name for r in RATIOS), "w2", "w18_low")}
    out |= {f"tagged_equals_bitset_{n}": partial(_tagged, name=n) for n in ("w2", "w10", "w18", "w21")} | {"cache_hits_w10": partial(_cache_hits, name="w10"), "naive_w3": _naive}
    out |= {f"compiled_view_{n}": partial(_compiled, name=n) for n in ("w2", "w3", "w10", "w13", "w16", "w18", "w20", "w21")} | {"compile_report": _compile_report, "axioms_w10": partial(_axioms, name="w10")}
    out |= {"mre_w18": partial(_errors, name="w18", methods=STRATIFIED), "mre_w21": partial(_costly_errors, name="w21"), "mre_count_profile_w21": partial(_costly_errors, name="w21", methods=STRATIFIED, profile="count", budgets=(1000,))}
    out |= {"ablation_w21": _ablation, "rank_methods_w21": _rank, "convergence_w18": _convergence, "convergence_methods_w21": partial(_method_convergence, name="w21"), "progress_w21": _progress, "predicted_variance_w21": _predicted, "ranking_w18": _ranking}
    out |= {f"budgets_{n}_{p}": partial(_budgets, name=n, profile=p) for n in ("w18", "w21") for p in ("default", "count")}
    out |= {"rollup_contrib": _with_totals, "cube_report": _cube, "top_contributors": _top, "asof_events": _asof, "json_props": _json, "window_events_session": _session}
    out |= {f"window_events_{k}": partial(_window, kind=k) for k in WINDOWS}
    return out


def oracle_sql() -> dict[str, str]:
    out = {f"query_{n}": duck_sql(q) for n, q in tpch.QUERIES.items()}
    w: dict[str, Workload] = WORKLOADS
    out |= {f"lineage_{n}": oracles.lineage(w[n]) for n in ("w3", "w21")}
    out |= {f"size_vectors_{n}": oracles.size_vectors(w[n], LETTERS[n]) for n in ("w10", "w21")}
    out |= {f"provenance_stats_{x.name}": oracles.stats(x) for x in w.values()}
    out["endogenous_split_w3"] = f"WITH {oracles.players(w['w3'])} SELECT {duck_sql(LINE)} IN (SELECT tid FROM pl) AS endogenous, count(*) AS n FROM lineitem GROUP BY 1"
    out["settings_select"] = f"WITH s AS ({oracles.size_vectors(w['w10_wide'], 'lo')}) SELECT answer, l, o, players FROM s WHERE l BETWEEN 16 AND 20 AND o = 5"
    out |= {f"shapley_closed_{x.name}": oracles.closed_form(x, SHAPLEY) for x in CLOSED}
    out |= {f"banzhaf_closed_{n}": oracles.closed_form(w[n], BANZHAF) for n in ("w3", "w10")}
    out["beta_closed_w10"] = oracles.closed_form(w["w10"], Semivalue.beta(4, 1))
    out["shapley_permutation_w3"] = f"WITH a AS ({oracles.closed_form(w['w3'], SHAPLEY)}) SELECT a.* FROM a WHERE (SELECT count(*) FROM a b WHERE b.answer = a.answer) <= 5"
    out |= {f"shapley_subset_{n}": oracles.by_subset(w[n], most=ENUMERATED) for n in ("w2", "w2_second", "w3_late", "w10", "w18", "w21")}
    out |= {f"shapley_rows_{n}": oracles.by_rows(w[n]) for n in ("w4", "w21")}
    out |= {f"attribute_{n}": f"SELECT answer, tid, round(value, 6) AS estimate FROM ({oracles.closed_form(w[n], SHAPLEY, 12)})" for n in ("w10", "w14")}
    out["attribute_w21"] = f"SELECT answer, tid, round(value, 6) AS estimate FROM ({oracles.by_rows(w['w21'], 12)})"
    out |= {f"banzhaf_subset_{n}": oracles.by_subset(w[n], semivalue="banzhaf", most=ENUMERATED) for n in ("w2_second", "w18")}
    out |= {f"owen_{n}": oracles.owen(w[n], LETTERS[n], ENUMERATED) for n in ("w10", "w18", "w2")}
    out |= {f"stratum_table_vector_{n}": oracles.strata(w[n], "TRUE", LETTERS[n], ENUMERATED) for n in ("w10", "w18")}
    out["stratum_table_size_w18"] = oracles.strata(w["w18"], "TRUE", None, ENUMERATED)
    for n, letters in (("vector", LETTERS["w10"]), ("size", None)):
        out[f"strata_{n}_w10"] = f"WITH z AS ({oracles.strata(w['w10'], 'TRUE', letters, ENUMERATED)}) SELECT answer, tid, vec, n_coal, w_value FROM z"
    out |= {f"alloc_{r}_w18": oracles.coverage(w["w18"], "clo", MAX_PLAYERS, r, BUDGET, 0) for r in ("count", "equal", "value", "structure")}
    out |= {"alloc_floor_w18": oracles.coverage(w["w18"], "clo", MAX_PLAYERS, "value", BUDGET, 1), "coverage_w10": oracles.coverage(w["w10"], "clno", ENUMERATED, "count", BUDGET, 0)}
    out |= {f"prune_{n}": f"{oracles.strata_of(w[n], LETTERS[n], ENUMERATED, True)} SELECT answer, tid, count(*) AS strata, CAST(sum(CASE WHEN live THEN 1 ELSE 0 END) AS BIGINT) AS live FROM z GROUP BY answer, tid" for n in ("w10", "w21")}

    def estimated(method: str, name: str, budget: int = BUDGET, count: bool = False, **more) -> str:
        floor = 0 if count and method != "relvec_adaptive" else 1
        profile = {"rule": "count", "later": "neyman_count", "floor": floor, "rounding": "largest" if floor else "nearest"} if count else {}
        sql = oracles.stratified(w[name], LETTERS[name] if method.startswith("relvec") else None, budget, cycles=2 if method.endswith("adaptive") else 1, **{"most": SAMPLED.get(name, ENUMERATED)} | profile | more)
        return f"SELECT *, '{method}' AS method, {budget} AS budget FROM ({sql})"

    out |= {f"{m}_{n}": estimated(m, n) for m in STRATIFIED for n in ("w2", "w10", "w18", "w21")}
    out |= {f"{m}_count_w18": estimated(m, "w18", count=True) for m in STRATIFIED}
    out |= {"relvec_collapse_w3": estimated("relvec", "w3"), "relvec_pruned_w21": estimated("relvec", "w21", prune=True)}
    out |= {"relvec_pruned_draws_w21": estimated("relvec", "w21")} | {f"{m}_structure_w21": estimated(m, "w21", rule="structure") for m in ("relvec", "relvec_adaptive")}
    out |= {f"prune_coalitions_{n}": oracles.pruning(w[n], LETTERS[n], 200, SAMPLED.get(n, ENUMERATED)) for n in ("w2_second", "w10", "w18", "w21")}
    out |= {f"boolean_subset_{n}": oracles.by_subset(w[n].boolean(), most=ENUMERATED) for n in ("w10", "w21")}
    out |= {"given_closed_w10": oracles.closed_form(oracles.given(w["w10"], "n"), SHAPLEY), "given_subset_w2_second": oracles.by_subset(oracles.given(w["w2_second"], "nr"), most=ENUMERATED)}
    out |= {f"totals_{n}": oracles.totals(w[n], BUDGET) for n in (*(r.name for r in RATIOS), "w2", "w18_low")}
    out |= {f"{m}_w18": oracles.sampled(w["w18"], "TRUE", m, BUDGET, 1, most=ENUMERATED) for m in ("mc", "mc_permutation", "mc_multilinear")}
    out["cache_hits_w10"] = oracles.cache_hits(w["w10"], "clno", 200)
    out |= {f"tagged_equals_bitset_{n}": f"WITH {oracles.players(w[n], 'TRUE', SAMPLED.get(n, ENUMERATED))} SELECT 20 * count(*) AS compared, CAST(0 AS BIGINT) AS different FROM pl" for n in ("w2", "w10", "w18", "w21")}
    out |= {f"compiled_view_{n}": oracles.view_size(w[n], MAX_PLAYERS) for n in ("w2", "w3", "w10", "w13", "w16", "w18", "w20", "w21")}
    out["custom_subset_w3"] = oracles.first_sizes(w["w3"])
    out["mre_w18"] = oracles.errors(w["w18"], {m: estimated(m, "w18", runs=RUNS, most=ENUMERATED, digits=None) for m in STRATIFIED}, BUDGET, ENUMERATED)
    out["axioms_w10"] = f"WITH {oracles.rows(w['w10'])} SELECT answer, round(sum(x) / 1e4, 4) AS total, round(sum(x) / 1e4, 4) AS whole FROM r GROUP BY answer"
    closed = oracles.closed_form(w["w10"], SHAPLEY, 12)
    out["rollup_contrib"] = f"WITH c AS ({closed}) SELECT answer, rel, round(sum(value), 6) AS value, count(*) AS n FROM c GROUP BY ROLLUP (answer, rel)"
    out["cube_report"] = f"WITH c AS ({closed}) SELECT rel, positive, round(sum(value), 2) AS value, count(*) AS n FROM (SELECT rel, value > 10000 AS positive, value FROM c) GROUP BY CUBE (rel, positive)"
    out["top_contributors"] = f"WITH c AS ({closed}), p AS (SELECT answer, tid, value, row_number() OVER (PARTITION BY answer ORDER BY round(value, 6) DESC, tid) AS place FROM c) SELECT answer, tid, round(value, 7) AS value, CAST(place AS INTEGER) AS place FROM p WHERE place <= 3"
    out |= windows.ORACLES | relational.ORACLES
    return out
