"""Lineage: the tuples that each answer depends on, and the compiled view that coalitions are evaluated on."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.semivalue import MAX_PLAYERS, of_relation, shl
from ..plans.workloads import Workload
from ..sources.scratch import write_and_read
from ..sources.tables import run_sql

SETS = T.ArrayType(T.ArrayType(T.StringType()))


def in_order(sets: str) -> Column:
    """Sets and their tuples in order of id. Lists gathered over a shuffle come in any order, another one at each evaluation,
    and rows are known by what they list."""
    return F.array_sort(F.transform(sets, lambda s: F.array_sort(s)))


def rows_of(spark: SparkSession, sf_dir: str, workload: Workload) -> DataFrame:
    """The un-aggregated query: answer, x, (y of ratios), need, any_of, none_of. Tuples used in two roles count once."""
    rows = run_sql(spark, sf_dir, workload.rows)
    for c in ("any_of", "none_of"):
        if c not in rows.columns:
            rows = rows.withColumn(c, F.array().cast(SETS))
    return rows.select("answer", "x", *(["y"] if "y" in rows.columns else []), F.array_sort(F.array_distinct("need")).alias("need"), in_order("any_of").alias("any_of"), in_order("none_of").alias("none_of"))


def with_given(rows: DataFrame, given: Callable[[Column], Column]) -> DataFrame:
    """The rows where tuples that `given`, a test of ids, picks are no players but always there: no row needs them, an
    alternative of such tuples alone frees the row from its alternatives, and a blocker of such tuples alone blocks for good."""
    left = lambda s: F.filter(s, lambda t: ~given(t))
    fewer = rows.withColumns({"need": left(F.col("need")), "any_of": F.transform("any_of", left), "none_of": F.transform("none_of", left)})
    free = F.exists("any_of", lambda s: F.size(s) == 0)
    return fewer.where(~F.exists("none_of", lambda s: F.size(s) == 0)).withColumn("any_of", F.when(free, F.array().cast(SETS)).otherwise(F.col("any_of")))


def relation(tid: Column) -> Column:
    return F.substring(tid, 1, 1)


def lineage(rows: DataFrame) -> DataFrame:
    """(answer, rel, tid), each once: what a row needs, its witnesses and its blockers."""
    tids = F.flatten(F.concat(F.array("need"), "any_of", "none_of"))
    return rows.select("answer", F.explode(F.array_distinct(tids)).alias("tid")).distinct().select("answer", relation(F.col("tid")).alias("rel"), "tid")


def size_vectors(lin: DataFrame) -> DataFrame:
    """Tuples of each relation by answer, in columns, and their sum."""
    wide = lin.groupBy("answer").pivot("rel", sorted("clnopqrseudk")).count().na.fill(0)
    kept = [c for c in wide.columns if c != "answer"]
    return wide.select("answer", *(F.col(c).cast("long").alias(c) for c in kept), sum((F.col(c) for c in kept), F.lit(0)).cast("long").alias("players"))


def split(table: DataFrame, tid: Column, lin: DataFrame) -> DataFrame:
    """The table's rows with `endogenous`: whether any answer depends on the tuple."""
    used = lin.select(F.col("tid").alias("__tid")).distinct().withColumn("__used", F.lit(True))
    return table.withColumn("__tid", tid).join(used, "__tid", "left").withColumn("endogenous", F.coalesce("__used", F.lit(False))).drop("__tid", "__used")


def provenance_stats(lin: DataFrame) -> DataFrame:
    per = lin.groupBy("answer").agg(F.count("*").alias("n"))
    rels = lin.agg(F.count_distinct("rel").alias("relations"))
    return per.agg(F.count("*").alias("answers"), F.min("n").alias("least"), F.max("n").alias("most"), F.sum("n").alias("total")).crossJoin(F.broadcast(rels))


def _bits(lin: DataFrame, most: int) -> DataFrame:
    """By answer its players in order of id, with a bit each, and a map from id to bit. Answers are counted before any
    of their tuples are listed."""
    small = lin.groupBy("answer").agg(F.count("*").alias("n")).where(F.col("n") <= most).select("answer")
    listed = lin.join(small, "answer", "left_semi").groupBy("answer").agg(F.array_sort(F.collect_list("tid")).alias("tids"))
    player = lambda t, i: F.struct(relation(t).alias("rel"), t.alias("tid"), shl(F.lit(1).cast("long"), i).alias("bit"))
    players = listed.select("answer", F.transform("tids", player).alias("players"))
    return players.withColumn("bits", F.map_from_entries(F.transform("players", lambda p: F.struct(p["tid"], p["bit"]))))


def mask(tids: Column, bits: Column) -> Column:
    return F.aggregate(tids, F.lit(0).cast("long"), lambda acc, t: acc.bitwiseOR(F.element_at(bits, t)))


def compile_view(rows: DataFrame, most: int | None = MAX_PLAYERS) -> DataFrame:
    """One row for each answer of at most `most` (62) players: players and view, an array of what each row needs, as masks.

    Larger answers are left to the closed form, to row games and to sampling by hash thresholds, which need no such masks.
    With `most` None none is left out: in a further column `listed` the rows of answers of more than 62 players stand
    with ids in place of masks, their players being the ids, and `within.of_answers` numbers them. The rows are
    grouped by answer once, so every later step works within a row, without a shuffle."""
    lin, whole = lineage(rows), most is None
    bits = _bits(lin, MAX_PLAYERS if whole else min(most, MAX_PLAYERS))
    joined = rows.where("answer IS NOT NULL").join(bits, "answer", "left") if whole else rows.join(bits, "answer")
    entry = F.struct(
        mask(F.col("need"), F.col("bits")).alias("need"),
        F.transform("any_of", lambda s: mask(s, F.col("bits"))).alias("any_of"),
        F.transform("none_of", lambda s: mask(s, F.col("bits"))).alias("none_of"),
        F.col("x").alias("x"),
    )
    if not whole:
        return joined.groupBy("answer").agg(F.first("players").alias("players"), F.array_sort(F.collect_list(entry)).alias("view"))
    wide, nobody = F.col("players").isNull(), F.array().cast(joined.schema["players"].dataType)
    return joined.groupBy("answer").agg(
        F.coalesce(F.first("players"), nobody).alias("players"),
        F.array_sort(F.collect_list(F.when(~wide, entry))).alias("view"),
        F.collect_list(F.when(wide, F.struct("need", "x", "any_of", "none_of"))).alias("listed"),
    )


def settings(view: DataFrame, targets: DataFrame | None = None) -> DataFrame:
    """One row for each target tuple: all players, or those listed in targets (answer, tid). Adds bit, n, rel, others.
    Answers whose rows are `listed` have no masks and make no settings."""
    each = view.select("answer", "view", "players", F.explode("players").alias("t")).select("answer", F.col("t.tid").alias("tid"), F.col("t.rel").alias("rel"), F.col("t.bit").alias("bit"), "players", "view")
    if targets is not None:
        each = each.join(targets, ["answer", "tid"])
    return each.select("answer", "tid", "rel", "bit", F.size("players").alias("n"), F.filter("players", lambda p: p["bit"] != F.col("bit")).alias("others"), "view")


def n_parts(df: DataFrame) -> int:
    """Of a table that is small for the work that its rows make."""
    return max(4 * df.sparkSession.sparkContext.defaultParallelism, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def spread(view: DataFrame) -> DataFrame:
    """Dealt over many files by answer: a view is small for the work that its rows make, and one file would be one task."""
    return view.repartition(n_parts(view), F.xxhash64("answer"))  # by the answer itself no files would be dealt out anew


_COMPILED: dict[tuple, DataFrame] = {}


def compiled(spark: SparkSession, sf_dir: str, workload: Workload, most: int | None = MAX_PLAYERS) -> DataFrame:
    """The compiled view of a workload, written to the shared folder when it is first asked for and read by all methods,
    cycles and queries of the session; the tables are taken not to change meanwhile."""
    key = (spark.sparkContext.applicationId, sf_dir, workload.rows, most)
    if key not in _COMPILED:
        _COMPILED[key] = write_and_read(spread(compile_view(rows_of(spark, sf_dir, workload), most)))
    return _COMPILED[key]


def relation_vectors(view: DataFrame, letters: str) -> DataFrame:
    """(answer, vector): players by relation, relations in order."""
    return view.select("answer", F.array(*(F.size(F.filter("players", of_relation(r))) for r in letters)).alias("vector"))
