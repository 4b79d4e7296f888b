"""Sampled estimates of tuple values, for many answers, targets and repeated runs at once."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import key, uniform
from ..functions.semivalue import MAX_PLAYERS, Semivalue, with_weights
from ..plans.workloads import Workload
from ..sources.scratch import write_and_read
from . import lineage, within
from .evaluate import marginal, marginals
from .strata import SETTING, allocate, attribute_pools, pools, share_of, vectors

RUN = (*SETTING, "run")
EXACT = "decimal(38,0)"
#: Draws of one stratum that one row is exploded into; a large stratum spans several.
DRAW_BLOCK = 4096


def _long0() -> Column:
    return F.lit(0).cast("long")


@dataclass(frozen=True)
class Plan:
    """How to sample. letters: the relations of the vectors, or None for strata by size. rule: the shares of the first
    cycle and of static methods; later: those of later cycles. pooling: all draws of a stratum together, or the mean
    of the cycles' estimates, which stays unbiased."""

    budget: int = 1000
    letters: str | None = None
    rule: str = "value"
    later: str = "neyman_value"
    cycles: int = 1
    floor: int = 1
    rounding: str = "largest"
    pooling: str = "pooled"
    prune: bool = False
    bins: int | None = None
    attribute_quantiles: int | None = None
    cached: bool = False
    prune_draws: bool = False
    census: bool = False
    seed: int = 42

    def named(self) -> str:
        return ("relvec" if self.letters else "size") + ("_adaptive" if self.cycles > 1 else "")


def with_runs(df: DataFrame, runs: int) -> DataFrame:
    return df.select("*", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("run"))


def pick(players: Column, k: Column, *parts: Column | str | int) -> Column:
    """A uniform k-subset of the players, as a mask: those with the least hashes."""
    hashed = F.transform(players, lambda p: F.struct(key(*parts, p["tid"]).alias("h"), p["bit"].alias("bit")))
    return F.aggregate(F.slice(F.array_sort(hashed), F.lit(1), k), _long0(), lambda a, p: a.bitwiseOR(p["bit"]))


def draw(allocated: DataFrame, pooled: DataFrame, plan: Plan, cycle: int, width: int) -> DataFrame:
    """A row with `mask` for each draw: within its stratum every coalition is as likely. No shuffle beyond the join of
    strata to settings; the same draw comes out in any partition or retry."""
    some = allocated.where("m > 0").join(pooled.select(*SETTING, "bit", "n", "pools", "view"), list(SETTING))
    blocks = some.select("*", F.explode(F.sequence(F.lit(0), F.floor((F.col("m") - 1) / DRAW_BLOCK).cast("int"))).alias("block"))
    first = F.col("block") * DRAW_BLOCK
    each = blocks.select("*", F.explode(F.sequence(first, F.least(first + DRAW_BLOCK, F.col("m")) - 1)).alias("draw"))
    mask = _long0()
    for k in range(width):
        mask = mask.bitwiseOR(pick(F.get("pools", k), F.get("vec", k), plan.seed, F.col("answer"), F.col("tid"), F.col("run"), cycle, F.col("stratum"), F.col("draw")))
    return each.withColumn("mask", mask)


def stratum_stats(draws: DataFrame, workload: Workload, plan: Plan) -> DataFrame:
    """(setting, run, stratum, k, s1, s2): mergeable sums of the marginals, whole numbers, so that neither the order of
    rows nor the size of the sums matters."""
    valued = marginals(draws, workload, plan.cached, plan.prune_draws).withColumn("delta", F.col("delta").cast("decimal(19,0)"))
    return valued.groupBy(*RUN, "stratum").agg(F.count("*").alias("k"), F.sum("delta").cast(EXACT).alias("s1"), F.sum(F.col("delta") * F.col("delta")).cast(EXACT).alias("s2"))


def _spread(k: Column, s1: Column, s2: Column) -> Column:
    """k times the sum of squares about the mean, exact."""
    return F.greatest(F.lit(0.0), (k.cast("decimal(10,0)") * s2.cast("decimal(28,0)") - s1.cast("decimal(19,0)") * s1.cast("decimal(19,0)")).cast("double"))


def _sigma(strata: DataFrame, stats: DataFrame) -> DataFrame:
    """Strata of every run with sigma: sample deviations; with under 2 draws that of all the setting's draws, so that no
    single draw freezes a stratum."""
    from pyspark.sql import Window

    joined = strata.join(stats, [*RUN, "stratum"], "left")
    w = Window.partitionBy(*RUN)
    k, s1, s2 = F.col("k"), F.col("s1"), F.col("s2")
    all_k = F.sum(k).over(w)
    pooled = F.sqrt(_spread(all_k, F.sum(s1).over(w), F.sum(s2).over(w)) / (all_k.cast("double") * all_k))
    own = F.sqrt(_spread(k, s1, s2) / (k.cast("double") * (k - 1)))
    return joined.withColumn("sigma", F.when(F.col("n_coal") <= 1, 0.0).when(k >= 2, own).otherwise(F.coalesce(pooled, F.lit(0.0)))).drop("k", "s1", "s2")


def combine(strata: DataFrame, stats: DataFrame, unit: float) -> DataFrame:
    """(setting, run, estimate, se, starved_weight, draws): the weighted means, their standard error, and the weight of live strata without a draw, which contribute 0."""
    joined = strata.join(stats, [*RUN, "stratum"], "left")
    mean = F.col("s1").cast("double") / F.col("k")
    var = F.when(F.col("k") > 1, _spread(F.col("k"), F.col("s1"), F.col("s2")) / (F.col("k").cast("double") * (F.col("k") - 1))).otherwise(0.0)
    return joined.groupBy(*RUN).agg(
        (F.sum(F.coalesce(F.col("w_value") * mean, F.lit(0.0))) / F.lit(unit)).alias("estimate"),
        (F.sqrt(F.sum(F.coalesce(F.col("w_value") * F.col("w_value") * var / F.col("k"), F.lit(0.0)))) / F.lit(unit)).alias("se"),
        F.sum(F.when(F.col("live") & F.col("k").isNull(), F.col("w_value")).otherwise(0.0)).alias("starved_weight"),
        F.coalesce(F.sum("k"), F.lit(0)).cast("long").alias("draws"),
    )


def prepare(settings: DataFrame, plan: Plan, semivalue: Semivalue) -> tuple[DataFrame, DataFrame, int]:
    """Settings with pools, their strata, and the number of pools."""
    if plan.attribute_quantiles and plan.letters:
        pooled, width = attribute_pools(settings, plan.letters, plan.attribute_quantiles), len(plan.letters) * plan.attribute_quantiles
    else:
        pooled, width = pools(settings, plan.letters), len(plan.letters) if plan.letters else 1
    return pooled, vectors(pooled, semivalue, width, plan.bins, plan.prune), width


def cells(strata: DataFrame) -> DataFrame:
    """Coarse strata: the cells, with the vectors inside and their cumulated value weights."""
    inside = F.array_sort(F.collect_list(F.struct("stratum", "vec", "w_value")))
    grouped = strata.where("live").groupBy(*SETTING, "cell").agg(inside.alias("inside"), F.sum("w_value").alias("w_value"), F.sum("w_count").alias("w_count"), (F.sum(F.col("w_count") * F.col("joins")) / F.sum("w_count")).alias("joins"), F.sum("n_coal").alias("n_coal"))
    number = F.aggregate("cell", _long0(), lambda a, b: a * 1000 + b)
    return grouped.withColumn("stratum", number).withColumn("live", F.lit(True))


def _draw_cells(allocated: DataFrame, pooled: DataFrame, plan: Plan, cycle: int, width: int) -> DataFrame:
    """Within a cell first a vector by its value weight, then a coalition of it."""
    blocks = allocated.where("m > 0").select("*", F.explode(F.sequence(F.lit(0), F.col("m") - 1)).alias("draw"))
    u = uniform(plan.seed, "vec", F.col("answer"), F.col("tid"), F.col("run"), cycle, F.col("stratum"), F.col("draw")) * F.col("w_value")
    start = F.struct(u.alias("left"), F.lit(-1).alias("at"))
    walk = F.aggregate("inside", start, lambda a, v: F.struct((a["left"] - v["w_value"]).alias("left"), F.when(a["left"] >= 0, a["at"] + 1).otherwise(a["at"]).alias("at")))
    chosen = blocks.withColumn("vec", F.get(F.col("inside"), F.least(F.greatest(walk["at"], F.lit(0)), F.size("inside") - 1))["vec"]).drop("inside")
    some = chosen.join(pooled.select(*SETTING, "bit", "n", "pools", "view"), list(SETTING))
    mask = _long0()
    for k in range(width):
        mask = mask.bitwiseOR(pick(F.get("pools", k), F.get("vec", k), plan.seed, F.col("answer"), F.col("tid"), F.col("run"), cycle, F.col("stratum"), F.col("draw")))
    return some.withColumn("mask", mask)


def stratified(settings: DataFrame, workload: Workload, plan: Plan, runs: int = 1, semivalue: Semivalue | None = None, cut: Callable[[DataFrame], DataFrame] = write_and_read, progress: list | None = None, view: DataFrame | None = None) -> DataFrame:
    """(answer, tid, run, estimate, se, starved_weight, draws) of the stratified methods, static or adaptive.

    Each setting goes through its cycles within its own row (`within.stratified`), without a shuffle; given the compiled view that
    all the settings are of, those of an answer within the answer's row. A census of coarse or adaptive strata, the cache,
    pruned draws and the anytime reading work on tables of strata and draws, with the same draws (not of a view with answers
    whose rows are `listed`: these are refused): there all settings and
    runs go through the cycles in lockstep, and `cut` ends the lineage of the statistics after every cycle. If a cycle could
    not draw twice from every stratum there are fewer cycles, but two. progress: gets (cycle, estimates so far)."""
    semivalue = semivalue or Semivalue.shapley()
    pooled, fine, width = prepare(settings, plan, semivalue)
    by_tables = (plan.census and (plan.bins or plan.cycles > 1)) or plan.cached or plan.prune_draws or progress is not None
    if view is not None and "listed" in view.columns and (by_tables or plan.attribute_quantiles or plan.cycles > 2):
        raise ValueError(f"answers of more than {MAX_PLAYERS} tuples are sampled within rows only, in at most two cycles and without attributes")
    if not by_tables:
        cycles = plan.cycles
        if cycles > 2:
            most = pooled.agg(F.max(F.aggregate("c", F.lit(1).cast("long"), lambda a, k: a * (k + 1)))).first()[0] or 1
            cycles = min(cycles, max(2, plan.budget // (2 * most)))
        return within.stratified(pooled, workload, plan, runs, semivalue, cycles, None if plan.attribute_quantiles else view)
    strata = with_runs(cells(fine) if plan.bins else fine, runs)
    stats, means, cycles = None, [], plan.cycles
    if cycles > 1:
        most = fine.groupBy(*SETTING).count().agg(F.max("count")).first()[0] or 1
        cycles = min(cycles, max(2, plan.budget // (2 * most)))
        strata = cut(strata)
    for cycle in range(cycles):
        budget = plan.budget // cycles + (cycle < plan.budget % cycles)
        if cycle and stats is not None:
            ready = _sigma(strata, stats)
            allocated = allocate(ready, share_of(plan.later, F.col("sigma")), budget, plan.floor, by=RUN)
        else:
            allocated = allocate(strata, share_of(plan.rule), budget, plan.floor, plan.rounding, by=RUN)
        new = stratum_stats((_draw_cells if plan.bins else draw)(allocated, pooled, plan, cycle, width), workload, plan)
        if plan.pooling == "cycle_mean":
            means.append(combine(strata, new, workload.unit))
        stats = new if stats is None else stats.unionByName(new).groupBy(*RUN, "stratum").agg(F.sum("k").alias("k"), *(F.sum(c).cast(EXACT).alias(c) for c in ("s1", "s2")))
        if cycles > 1:
            stats = cut(stats)
        if progress is not None:
            progress.append((cycle, combine(strata, stats, workload.unit)))
    if plan.census:
        stats = _with_census(stats, pooled, strata, workload, plan)
    if means:
        out = means[0]
        for m in means[1:]:
            out = out.unionByName(m)
        k = len(means)
        return out.groupBy(*RUN).agg(F.avg("estimate").alias("estimate"), (F.sqrt(F.sum(F.col("se") * F.col("se"))) / k).alias("se"), F.avg("starved_weight").alias("starved_weight"), F.sum("draws").alias("draws"))
    return combine(strata, stats, workload.unit)


def _with_census(stats: DataFrame, pooled: DataFrame, strata: DataFrame, workload: Workload, plan: Plan) -> DataFrame:
    """Strata that got as many draws as they have coalitions are counted out instead: exact, without variance."""
    from .exact import coalitions

    small = strata.join(stats.select(*RUN, "stratum", "k"), [*RUN, "stratum"]).where("n_coal <= k").select(*RUN, "stratum", "vec")
    every = coalitions(pooled.select(*SETTING, "bit", "n", "view", "others", "pools"))
    counted = F.transform("pools", lambda g: F.bit_count(F.aggregate(g, _long0(), lambda a, p: a.bitwiseOR(p["bit"])).bitwiseAND(F.col("mask"))))
    valued = every.select(*SETTING, counted.alias("vec"), marginal(F.col("view"), F.col("mask"), F.col("bit"), workload).alias("d"))
    whole = valued.groupBy(*SETTING, "vec").agg(F.count("*").alias("k"), F.sum("d").cast(EXACT).alias("s1"))
    exact = small.join(whole, [*SETTING, "vec"]).select(*RUN, "stratum", "k", "s1", F.lit(0).cast(EXACT).alias("s2"))  # no spread
    return stats.join(exact.select(*RUN, "stratum"), [*RUN, "stratum"], "left_anti").unionByName(exact)


def _mean_of(draws: DataFrame, weight: Column, workload: Workload, budget: int) -> DataFrame:
    valued = draws.withColumn("y", weight * marginal(F.col("view"), F.col("mask"), F.col("bit"), workload) / F.lit(workload.unit))
    return valued.groupBy(*RUN).agg(F.avg("y").alias("estimate"), (F.stddev_samp("y") / F.sqrt(F.lit(float(budget)))).alias("se"), F.lit(0.0).alias("starved_weight"), F.count("*").alias("draws"))


def _plain_draws(settings: DataFrame, budget: int, runs: int) -> DataFrame:
    return with_runs(settings, runs).select("*", F.explode(F.sequence(F.lit(0), F.lit(budget - 1))).alias("draw"))


def _members(test: Callable[[Column], Column]) -> Column:
    return F.aggregate("others", _long0(), lambda a, p: F.when(test(p), a.bitwiseOR(p["bit"])).otherwise(a))


def monte_carlo(settings: DataFrame, workload: Workload, budget: int, runs: int = 1, seed: int = 42, semivalue: Semivalue | None = None) -> DataFrame:
    """Coalitions uniform over all subsets, each weighted by 2^(n-1) times its weight."""
    semivalue = semivalue or Semivalue.shapley()
    place = [seed, "mc", F.col("answer"), F.col("tid"), F.col("run"), F.col("draw")]
    mask = _members(lambda p: F.substring(key(*place, p["tid"]), 1, 1) < "8")
    draws = _plain_draws(with_weights(settings, semivalue), budget, runs).withColumn("mask", mask)
    weight = F.get("omega", F.bit_count("mask")) * F.pow(F.lit(2.0), F.col("n") - 1)
    return _mean_of(draws, weight, workload, budget)


def permutation_sampling(settings: DataFrame, workload: Workload, budget: int, runs: int = 1, seed: int = 42) -> DataFrame:
    """Random orders: the coalition is who stands before the target. Shapley values only."""
    place = [seed, "order", F.col("answer"), F.col("run"), F.col("draw")]  # one order for all targets of an answer
    mask = _members(lambda p: key(*place, p["tid"]) < key(*place, F.col("tid")))
    return _mean_of(_plain_draws(settings, budget, runs).withColumn("mask", mask), F.lit(1.0), workload, budget)


def multilinear(settings: DataFrame, workload: Workload, budget: int, runs: int = 1, seed: int = 42) -> DataFrame:
    """A random chance for each draw, then every other player joins with it: Shapley values without any ordering."""
    place = [seed, "chance", F.col("answer"), F.col("tid"), F.col("run"), F.col("draw")]
    draws = _plain_draws(settings, budget, runs).withColumn("chance", uniform(*place))
    mask = _members(lambda p: uniform(*place, p["tid"]) < F.col("chance"))
    return _mean_of(draws.withColumn("mask", mask), F.lit(1.0), workload, budget)


def multilinear_rows(rows: DataFrame, targets: DataFrame, budget: int, seed: int = 42, unit: float = 1.0) -> DataFrame:
    """(answer, tid, estimate, se, draws) for sums with any number of players: no masks, the rows themselves are tested.
    A row matters to a target that it mentions: all it needs must have joined, an alternative wholly, and no blocker
    wholly; its marginal is what the target's joining changes.

    Rows that mention a target are spread by (answer, target, row); each draw's sum is combined before the shuffle."""
    mentioned = F.array_distinct(F.flatten(F.concat(F.array("need"), "any_of", "none_of")))
    mine = rows.select("answer", "x", "need", "any_of", "none_of", F.explode(mentioned).alias("tid")).join(targets, ["answer", "tid"])
    draws = mine.select("*", F.explode(F.sequence(F.lit(0), F.lit(budget - 1))).alias("draw"))
    place = [seed, "rows", F.col("answer"), F.col("tid"), F.col("draw")]

    def holds(with_target: bool) -> Column:
        here = lambda t: F.when(t == F.col("tid"), F.lit(with_target)).otherwise(uniform(*place, t) < F.col("chance"))
        whole = lambda s: F.forall(s, here)
        return F.forall("need", here) & ((F.size("any_of") == 0) | F.exists("any_of", whole)) & ~F.exists("none_of", whole)

    change = F.col("x") * (holds(True).cast("int") - holds(False).cast("int"))
    by_draw = draws.withColumn("chance", uniform(*place)).groupBy("answer", "tid", "draw").agg(F.sum(change).alias("y"))
    y = F.col("y") / F.lit(unit)
    return by_draw.groupBy("answer", "tid").agg(F.avg(y).alias("estimate"), (F.stddev_samp(y) / F.sqrt(F.lit(float(budget)))).alias("se"), F.count("*").alias("draws"))


def finished(x: Column, y: Column, workload: Workload) -> Column:
    """What a workload makes of a coalition's sums; a ratio is rounded down to a whole number of its unit's parts, 0 where there is nothing to divide by."""
    if workload.agg == "ratio":
        return F.when(x != 0, F.floor(y.cast("double") / x.cast("double") * F.lit(workload.unit))).otherwise(0).cast("long")
    if workload.agg == "exists":
        return (x > 0).cast("long")
    return F.when(x > workload.above, x).otherwise(0) if workload.agg == "having" else x


def multilinear_totals(rows: DataFrame, targets: DataFrame | None, workload: Workload, budget: int, seed: int = 42, view: DataFrame | None = None) -> DataFrame:
    """(answer, tid, estimate, se, draws) for any function of an answer's sums (x, and y if rows have it) and any number of
    players: ratios, bounds on sums, existence.

    All targets of an answer share its draws. The sums of a drawn coalition are taken once; a target's joining or leaving
    changes those rows only that mention it, so the work is linear in what the rows mention, whatever the aggregate. Both
    sides are partial sums before a shuffle by draw. Answers of a compiled view, if one is given, are sampled in their rows
    with the same draws, and only those that it lacks on the rows of the query. Without targets all tuples are."""
    if view is not None:
        small = within.multilinear(view, workload, budget, seed)
        if targets is not None:
            small = small.join(targets.select("answer", "tid").distinct(), ["answer", "tid"], "left_semi")
        rest = rows.join(view.select("answer"), "answer", "left_anti")
        return small if rest.isEmpty() else small.unionByName(multilinear_totals(rest, targets, workload, budget, seed))
    targets = lineage.lineage(rows) if targets is None else targets
    data = rows if "y" in rows.columns else rows.withColumn("y", _long0())
    place = [seed, "totals", F.col("answer"), F.col("draw")]
    each_draw = F.explode(F.sequence(F.lit(0), F.lit(budget - 1))).alias("draw")

    def holds(here: Callable[[Column], Column]) -> Column:
        whole = lambda s: F.forall(s, here)
        return (F.forall("need", here) & ((F.size("any_of") == 0) | F.exists("any_of", whole)) & ~F.exists("none_of", whole)).cast("int")

    drawn = lambda t: uniform(*place, t) < F.col("chance")
    decided = lambda there: lambda t: F.when(t == F.col("tid"), F.lit(there)).otherwise(drawn(t))
    whole = lambda df: df.select("*", each_draw).withColumn("chance", uniform(*place))
    base = whole(data).withColumn("now", holds(drawn)).groupBy("answer", "draw").agg(*(F.sum(F.col(c) * F.col("now")).alias(c) for c in "xy"))
    mentioned = F.array_distinct(F.flatten(F.concat(F.array("need"), "any_of", "none_of")))
    mine = data.select("*", F.explode(mentioned).alias("tid")).join(targets.select("answer", "tid").distinct(), ["answer", "tid"])
    states = whole(mine).withColumns({"now": holds(drawn), "with": holds(decided(True)), "without": holds(decided(False))})
    change = [F.sum(F.col(c) * (F.col(s) - F.col("now"))).alias(f"{c}_{s}") for c in "xy" for s in ("with", "without")]
    both = states.groupBy("answer", "tid", "draw").agg(*change).join(base, ["answer", "draw"])
    value = lambda s: finished(F.col("x") + F.col(f"x_{s}"), F.col("y") + F.col(f"y_{s}"), workload)
    delta = (value("with") - value("without")) / F.lit(workload.unit)
    return both.groupBy("answer", "tid").agg(F.avg(delta).alias("estimate"), (F.stddev_samp(delta) / F.sqrt(F.lit(float(budget)))).alias("se"), F.count("*").alias("draws"))


def interval(estimates: DataFrame, z: float = 1.96) -> DataFrame:
    """Adds low and high, the estimate less and plus z standard errors."""
    return estimates.withColumns({"low": F.col("estimate") - z * F.col("se"), "high": F.col("estimate") + z * F.col("se")})


METHODS = ("mc", "mc_permutation", "mc_multilinear", "size", "size_adaptive", "relvec", "relvec_adaptive")


def estimate(settings: DataFrame, workload: Workload, method: str, budget: int, letters: str, runs: int = 1, profile: str = "default", cycles: int = 5, seed: int = 42, semivalue: Semivalue | None = None, view: DataFrame | None = None, **more) -> DataFrame:
    """One method by name, with a `method` and a `budget` column. profile: "default" shares by value with a floor of 1;
    "count" shares by the number of coalitions, rounded to nearest, no floor but for relvec_adaptive."""
    if method == "mc":
        out = monte_carlo(settings, workload, budget, runs, seed, semivalue)
    elif method == "mc_permutation":
        out = permutation_sampling(settings, workload, budget, runs, seed)
    elif method == "mc_multilinear":
        out = multilinear(settings, workload, budget, runs, seed)
    else:
        plan = Plan(budget=budget, letters=letters if method.startswith("relvec") else None, cycles=cycles if method.endswith("adaptive") else 1, seed=seed)
        if profile == "count":
            floor = 1 if method == "relvec_adaptive" else 0
            plan = replace(plan, rule="count", later="neyman_count", floor=floor, rounding="largest" if floor else "nearest")
        out = stratified(settings, workload, replace(plan, **more), runs, semivalue, view=view)
    return out.withColumn("method", F.lit(method)).withColumn("budget", F.lit(budget))


