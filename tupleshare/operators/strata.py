"""Strata of coalitions: by size, by relation vector, pruned, coarsened; and their shares of a budget."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.semivalue import Semivalue, choose, of_relation, with_weights

SETTING = ("answer", "tid")
ONE_POOL = "*"


def pools(settings: DataFrame, letters: str | None) -> DataFrame:
    """Adds `pools`: the other players in the groups that vectors count, one for each relation (or one in all), and c,
    the groups' sizes, and own, whether a group is of the target's relation. Groups are taken from the players' `rel`."""
    if letters is None:
        groups, own = F.array("others"), F.array(F.lit(False))
    else:
        groups, own = F.array(*(F.filter("others", of_relation(r)) for r in letters)), F.array(*(F.col("rel") == r for r in letters))
    return settings.withColumn("pools", groups).withColumns({"c": F.transform("pools", lambda g: F.size(g)), "own": own})


def vectors(pooled: DataFrame, semivalue: Semivalue, width: int, bins: int | None = None, prune: bool = False) -> DataFrame:
    """(answer, tid, stratum, vec, size, n_coal, w_count, w_value, joins, live): every vector of counts of each setting.

    joins is the part of each relation that a coalition of the vector has, multiplied over all but the target's own: the
    chance that what a row needs beside the target is there. w_value is the stratum's share of the value, w_count that of all coalitions. A stratum is dead if no row of the view
    with the target (in what it needs, its witnesses or its blockers) can find what it needs; it keeps its weight, and
    its mean is 0. With `bins` counts are cut into quantile bins of each pool, a cell being a product of bins."""
    df = with_weights(pooled, semivalue).select(*SETTING, "n", "c", "own", "omega", *(("pools", "bit", "view") if prune else ()))
    for k in range(width):
        df = df.withColumn(f"s{k}", F.explode(F.sequence(F.lit(0), F.get("c", k))))
    vec = F.array(*(F.col(f"s{k}") for k in range(width)))
    count = F.lit(1.0)
    stratum, joins = F.lit(0).cast("long"), F.lit(1.0)
    for k in range(width):
        joins = joins * F.when((F.get("c", k) > 0) & ~F.get("own", k), F.col(f"s{k}") / F.get("c", k)).otherwise(1.0)
        count = count * choose(F.get("c", k), F.col(f"s{k}"))
        stratum = stratum * (F.get("c", k) + 1) + F.col(f"s{k}")
    df = df.withColumns({"vec": vec, "n_coal": count, "stratum": stratum, "joins": joins})
    df = df.withColumn("size", F.aggregate("vec", F.lit(0), lambda a, x: a + x))
    weight = F.get("omega", F.col("size"))
    df = df.withColumns({"w_value": weight * F.col("n_coal"), "w_count": F.col("n_coal") / F.pow(F.lit(2.0), F.col("n") - 1)})
    if prune:
        mask = F.transform("pools", lambda g: F.aggregate(g, F.lit(0).cast("long"), lambda a, p: a.bitwiseOR(p["bit"])))
        df = df.withColumn("pool_masks", mask)
        bit = F.col("bit")
        concerned = lambda r: (r["need"].bitwiseAND(bit) != 0) | F.exists(r["any_of"], lambda m: m.bitwiseAND(bit) != 0) | F.exists(r["none_of"], lambda m: m.bitwiseAND(bit) != 0)
        fits = lambda r: F.forall(F.arrays_zip("pool_masks", "vec"), lambda z: F.bit_count(r["need"].bitwiseAND(F.bitwise_not(bit)).bitwiseAND(z["pool_masks"])) <= z["vec"])
        df = df.withColumn("live", F.exists("view", lambda r: concerned(r) & fits(r)))
    else:
        df = df.withColumn("live", F.lit(True))
    if bins:
        bin_of = F.transform(F.arrays_zip("vec", "c"), lambda z: F.least(F.lit(bins - 1), F.floor(z["vec"] * bins / (z["c"] + 1)).cast("int")))
        df = df.withColumn("cell", bin_of)
    keep = [*SETTING, "stratum", "vec", "size", "n_coal", "w_count", "w_value", "joins", "live"] + (["cell"] if bins else [])
    return df.select(*keep)


def coarsen_by_attribute(settings: DataFrame, quantiles: int) -> DataFrame:
    """Cuts every relation into sub-relations by quantiles of a statistic of its tuples, the greatest measure of a row
    that needs them, so that strata count tuples of each. The players' `rel` becomes letter and quantile."""

    def score(p: Column) -> Column:
        return F.coalesce(F.array_max(F.transform(F.filter("view", lambda r: r["need"].bitwiseAND(p["bit"]) != 0), lambda r: F.abs(r["x"]))), F.lit(0).cast("long"))

    scored = settings.withColumn("scored", F.transform("others", lambda p: F.struct(p["rel"].alias("rel"), score(p).alias("score"), p["tid"].alias("tid"), p["bit"].alias("bit"))))
    peers = lambda p: F.filter("scored", lambda q: q["rel"] == p["rel"])
    before = lambda p: F.size(F.filter("scored", lambda q: (q["rel"] == p["rel"]) & ((q["score"] < p["score"]) | ((q["score"] == p["score"]) & (q["bit"] < p["bit"])))))
    named = F.transform("scored", lambda p: F.struct(F.concat(p["rel"], F.floor(before(p) * quantiles / F.size(peers(p))).cast("string")).alias("rel"), p["tid"].alias("tid"), p["bit"].alias("bit")))
    return scored.withColumn("others", named).drop("scored")


def attribute_pools(settings: DataFrame, letters: str, quantiles: int) -> DataFrame:
    """Pools of the sub-relations, in order of letter and quantile; some may be empty."""
    cut = coarsen_by_attribute(settings, quantiles)
    groups = F.array(*(F.filter("others", of_relation(f"{r}{q}")) for r in letters for q in range(quantiles)))
    own = F.array(*(F.col("rel") == r for r in letters for _ in range(quantiles)))
    return cut.withColumn("pools", groups).withColumns({"c": F.transform("pools", lambda g: F.size(g)), "own": own})


RULES = ("count", "equal", "value", "structure", "neyman_count", "neyman_value")


def share_of(rule: str, sigma: Column | None = None) -> Column:
    """The unscaled share of a stratum under a rule. "structure" shares by the coalitions that a row can be expected to
    join in: nothing to vectors that lack a relation, more to those that have much of each."""
    base = {"count": F.col("w_count"), "equal": F.lit(1.0), "value": F.col("w_value"), "structure": F.col("w_count") * F.col("joins"), "neyman_count": F.col("w_count"), "neyman_value": F.col("w_value")}[rule]
    return base * sigma if rule.startswith("neyman") else base


def allocate(strata: DataFrame, share: Column, budget: int, floor: int = 0, rounding: str = "largest", by: tuple[str, ...] = SETTING) -> DataFrame:
    """Adds m, the draws of each live stratum: whole numbers that sum to the budget.

    After the floor the rest is dealt in proportion to the share; largest remainders first, ties by stratum. With
    rounding="nearest" and no floor small shares get nothing and the sum may differ, as in a plain proportional rule."""
    w = Window.partitionBy(*by)
    live = F.col("live")
    share = F.when(live, F.greatest(share, F.lit(0.0))).otherwise(0.0)
    df = strata.withColumn("__share", share).withColumn("__total", F.sum("__share").over(w)).withColumn("__lives", F.sum(live.cast("int")).over(w))
    each = F.when(F.col("__lives") * floor <= budget, F.lit(floor)).otherwise(F.floor(F.lit(budget) / F.greatest("__lives", F.lit(1))))
    df = df.withColumn("__floor", F.when(live, each).otherwise(0))
    rest = F.lit(budget) - F.col("__lives") * each
    part = F.when(F.col("__total") > 0, F.col("__share") / F.col("__total")).otherwise(F.when(live, 1.0 / F.col("__lives")).otherwise(0.0))
    df = df.withColumn("__exact", rest * part)
    if rounding == "nearest":
        return df.withColumn("m", (F.col("__floor") + F.floor(F.col("__exact") + 0.5)).cast("int")).drop("__share", "__total", "__lives", "__floor", "__exact")
    df = df.withColumn("__base", F.floor(F.round("__exact", 9)))
    left = F.lit(budget) - F.sum(F.col("__base") + F.col("__floor")).over(w)
    order = Window.partitionBy(*by).orderBy(F.desc("live"), F.desc(F.round(F.col("__exact") - F.col("__base"), 9)), "stratum")
    df = df.withColumn("__left", left).withColumn("__nth", F.row_number().over(order))
    m = F.when(live, F.col("__floor") + F.col("__base") + (F.col("__nth") <= F.col("__left")).cast("int")).otherwise(0)
    return df.withColumn("m", m.cast("int")).drop("__share", "__total", "__lives", "__floor", "__exact", "__base", "__left", "__nth")
