"""The value of a coalition, on the compiled view and by other ways."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.workloads import Workload
from ..sources.tables import run_sql
from .lineage import in_order


def value(view: Column, coalition: Column, workload: Workload) -> Column:
    """Of the coalition as a mask: a row counts if all it needs is there, an alternative is, and no blocking set is."""
    if workload.agg == "ratio":
        raise ValueError("ratios are sampled on rows, by multilinear_totals")

    def holds(m: Column) -> Column:
        return coalition.bitwiseAND(m) == m

    def row(acc: Column, r: Column) -> Column:
        there = holds(r["need"]) & ((F.size(r["any_of"]) == 0) | F.exists(r["any_of"], holds)) & ~F.exists(r["none_of"], holds)
        return acc + F.when(there, r["x"]).otherwise(F.lit(0).cast("long"))

    total = F.aggregate(view, F.lit(0).cast("long"), row)
    if workload.agg == "exists":
        return (total > 0).cast("long")
    if workload.agg == "having":
        return F.when(total > workload.above, total).otherwise(F.lit(0).cast("long"))
    return total


def marginal(view: Column, coalition: Column, bit: Column, workload: Workload) -> Column:
    """Of the target, to a coalition without it."""
    return value(view, coalition.bitwiseOR(bit), workload) - value(view, coalition, workload)


def can_change(view: Column, coalition: Column, bit: Column) -> Column:
    """Whether the target can make a difference to the coalition: some row that the target has a part in finds all that it
    needs among the two. Where none does the marginal is 0, whatever the aggregate."""
    joined = coalition.bitwiseOR(bit)

    def has_part(m: Column) -> Column:
        return m.bitwiseAND(bit) != 0

    def row(r: Column) -> Column:
        return (has_part(r["need"]) | F.exists(r["any_of"], has_part) | F.exists(r["none_of"], has_part)) & (joined.bitwiseAND(r["need"]) == r["need"])

    return F.exists(view, row)


def marginals(draws: DataFrame, workload: Workload, cached: bool = True, pruned: bool = False) -> DataFrame:
    """Adds `delta` to draws (answer, view, bit, mask). With the cache each coalition of an answer is evaluated once,
    whatever targets and draws ask for it. With `pruned` coalitions that the target can't change are not evaluated."""
    if not cached:
        delta = marginal(F.col("view"), F.col("mask"), F.col("bit"), workload)
        return draws.withColumn("delta", F.when(can_change(F.col("view"), F.col("mask"), F.col("bit")), delta).otherwise(F.lit(0).cast("long")) if pruned else delta)
    if pruned:
        marked = draws.withColumn("__live", can_change(F.col("view"), F.col("mask"), F.col("bit")))
        dead = marked.where("NOT __live").drop("__live", "view").withColumn("delta", F.lit(0).cast("long"))
        return marginals(marked.where("__live").drop("__live"), workload).unionByName(dead)
    slim = draws.drop("view")
    asked = draws.select("answer", F.explode(F.array("mask", F.col("mask").bitwiseOR(F.col("bit")))).alias("s")).distinct()
    views = draws.select("answer", "view").dropDuplicates(["answer"])
    known = asked.join(views, "answer").select("answer", "s", value(F.col("view"), F.col("s"), workload).alias("v"))
    low = known.select("answer", F.col("s").alias("mask"), F.col("v").alias("v0"))
    high = known.select("answer", F.col("s").alias("mask1"), F.col("v").alias("v1"))
    both = slim.withColumn("mask1", F.col("mask").bitwiseOR(F.col("bit"))).join(low, ["answer", "mask"]).join(high, ["answer", "mask1"])
    return both.withColumn("delta", F.col("v1") - F.col("v0")).drop("mask1", "v0", "v1")


def cache_hits(draws: DataFrame) -> DataFrame:
    """(drawn, evaluations, distinct_evaluations, hits) of the two values that each draw asks for."""
    asked = draws.select("answer", F.explode(F.array("mask", F.col("mask").bitwiseOR(F.col("bit")))).alias("s"))
    counted = asked.groupBy("answer", "s").count()
    return counted.agg(
        (F.sum("count") / 2).cast("long").alias("drawn"), F.sum("count").alias("evaluations"), F.count("*").alias("distinct_evaluations"), (F.sum("count") - F.count("*")).alias("hits")
    )


def pruning(draws: DataFrame, workload: Workload) -> DataFrame:
    """(drawn, pruned, wrong): draws, those that pruning leaves out, and how many of these have a marginal other than 0 (none)."""
    view, mask, bit = F.col("view"), F.col("mask"), F.col("bit")
    marked = draws.select((~can_change(view, mask, bit)).alias("dead"), marginal(view, mask, bit, workload).alias("delta"))
    return marked.agg(F.count("*").alias("drawn"), F.sum(F.col("dead").cast("int")).alias("pruned"), F.sum((F.col("dead") & (F.col("delta") != 0)).cast("int")).alias("wrong"))


def memberships(draws: DataFrame, with_target: bool) -> DataFrame:
    """(coalition, answer, tid) of every drawn coalition, for the ways that work on tuples rather than masks."""
    inside = F.col("mask").bitwiseOR(F.col("bit")) if with_target else F.col("mask")
    everyone = draws.withColumn("m", inside)
    return everyone.select("coalition", "answer", F.explode(F.filter("players", lambda p: F.col("m").bitwiseAND(p["bit"]) == p["bit"])).alias("p")).select("coalition", "answer", "p.tid")


def tagged(rows: DataFrame, member: DataFrame, coalitions: DataFrame, workload: Workload) -> DataFrame:
    """(coalition, v) by joins: every row of the un-aggregated query with every coalition of its answer, as tuples.

    Works for any number of players and for rows with witnesses and blockers; costs a join on (answer, tuple)."""
    rows = rows.withColumns({c: in_order(c) for c in ("any_of", "none_of")})
    numbered = rows.withColumn("row", F.xxhash64("need", "any_of", "none_of"))
    parts = numbered.select("answer", "row", F.lit(0).alias("kind"), F.lit(0).alias("no"), "need").withColumnRenamed("need", "tids")
    for kind, c in ((1, "any_of"), (2, "none_of")):
        parts = parts.unionByName(numbered.select("answer", "row", F.posexplode(c).alias("no", "tids")).withColumn("kind", F.lit(kind)))
    size = parts.withColumn("size", F.size("tids")).select("answer", "row", "kind", "no", "size", F.explode("tids").alias("tid")).distinct()
    whole = size.join(member, ["answer", "tid"]).groupBy("coalition", "answer", "row", "kind", "no", "size").agg(F.count_distinct("tid").alias("k")).where("k = size")
    state = whole.groupBy("coalition", "answer", "row").agg(*(F.max((F.col("kind") == k).cast("int")).alias(n) for k, n in enumerate(("needs", "some", "blocked"))))
    asked = numbered.select("answer", "row", (F.size("any_of") > 0).alias("asks"), "x")
    alive = state.where("needs = 1 AND blocked = 0").join(asked, ["answer", "row"]).where("NOT asks OR some = 1")
    totals = alive.groupBy("coalition").agg(F.sum("x").alias("total"))
    v = {"exists": F.expr("CASE WHEN total > 0 THEN 1L ELSE 0L END"), "having": F.expr(f"CASE WHEN total > {workload.above} THEN total ELSE 0L END")}.get(workload.agg, F.coalesce("total", F.lit(0).cast("long")))
    return coalitions.select("coalition").join(totals, "coalition", "left").select("coalition", F.coalesce(v, F.lit(0).cast("long")).alias("v"))


def naive(spark: SparkSession, sf_dir: str, sql: str, kept: dict[str, tuple[str, list[str]]]) -> int:
    """The baseline: the query as text on base tables cut down by IN lists; one job for each coalition.

    kept: by table the expression of its tuple ids and the ids in the coalition."""
    frames = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet").where(F.expr(e).isin(ids) if ids else F.lit(False)) for t, (e, ids) in kept.items()}
    return run_sql(spark, sf_dir, sql, **frames).first()[0] or 0
