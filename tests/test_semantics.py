"""Tuples that are always there, answers as Boolean games, frozen conditions, ratios, pruned coalitions, structural shares."""

import math
from dataclasses import replace
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from tupleshare.api import attribute
from tupleshare.functions.semivalue import Semivalue
from tupleshare.operators import estimate as est
from tupleshare.operators import evaluate, exact, lineage
from tupleshare.operators import strata as st
from tupleshare.plans.workloads import WORKLOADS, Workload

SF = "/root/testdata/sf0.001"
SHAPLEY = Semivalue.shapley()
SCHEMA = "answer string, x long, y long, need array<string>, any_of array<array<string>>, none_of array<array<string>>"
#: Two orders of one customer; a line of the second has an alternative, one of the first a blocker.
ROWS = [
    ("a", 40, 40, ["c|1", "l|1", "o|1"], [], [["l|3"]]),
    ("a", 20, 0, ["c|1", "l|2", "o|1"], [], []),
    ("a", 30, 30, ["c|1", "l|3", "o|2"], [["s|1"], ["s|2"]], []),
]
PLAYERS = sorted({t for r in ROWS for t in [*r[3], *(t for s in [*r[4], *r[5]] for t in s)]})


@pytest.fixture(scope="module")
def rows(spark):
    return spark.createDataFrame(ROWS, SCHEMA)


def sums(s, given=frozenset()):
    s = set(s) | given
    held = [r for r in ROWS if set(r[3]) <= s and (not r[4] or any(set(a) <= s for a in r[4])) and not any(set(b) <= s for b in r[5])]
    return sum(r[1] for r in held), sum(r[2] for r in held)


def brute(v, players=PLAYERS):
    out = {}
    for p in players:
        rest = [q for q in players if q != p]
        out[p] = sum((v({*s, p}) - v(s)) / (len(players) * math.comb(len(rest), k)) for k in range(len(players)) for s in map(set, combinations(rest, k)))
    return out


def values(df, column="value"):
    return {r["tid"]: r[column] for r in df.collect()}


@pytest.mark.parametrize("letters", ["c", "s", "l", "cos"])
def test_given_tuples_are_always_there(rows, letters):
    fewer = lineage.with_given(rows.drop("y"), lambda t: lineage.relation(t).isin(*letters))
    given = frozenset(t for t in PLAYERS if t[0] in letters)
    left = [t for t in PLAYERS if t not in given]
    want = brute(lambda s: sums(s, given)[0], left)
    got = values(exact.by_subset(lineage.settings(lineage.compile_view(fewer)), Workload("given", ""), SHAPLEY))
    assert {t: got.get(t, 0.0) for t in left} == pytest.approx(want)


def test_boolean_game(rows):
    got = values(exact.by_subset(lineage.settings(lineage.compile_view(rows.drop("y").withColumn("x", F.lit(1).cast("long")))), Workload("there", "", "exists"), SHAPLEY))
    assert got == pytest.approx(brute(lambda s: float(sums(s)[0] > 0)))


def test_boolean_workload_has_the_same_lineage(spark):
    for name in ("w10", "w21", "w2_second"):
        plain, there = (lineage.lineage(lineage.rows_of(spark, SF, w)) for w in (WORKLOADS[name], WORKLOADS[name].boolean()))
        assert plain.exceptAll(there).isEmpty() and there.exceptAll(plain).isEmpty()


RATIO = Workload("ratio", "", "ratio", 0, 1e6)
GAMES = [
    (RATIO, lambda x, y: math.floor(y / x * 1e6) / 1e6 if x else 0),
    (Workload("sum", ""), lambda x, y: x),
    (Workload("having", "", "having", 45), lambda x, y: x if x > 45 else 0),
    (Workload("exists", "", "exists"), lambda x, y: float(x > 0)),
]


@pytest.mark.parametrize("w, finish", GAMES, ids=[w.name for w, _ in GAMES])
def test_functions_of_sums_on_rows(rows, w, finish):
    want = brute(lambda s: finish(*sums(s)))
    targets = lineage.lineage(rows.drop("y")).select("answer", "tid")
    got = {r.tid: r for r in est.multilinear_totals(rows, targets, w, 3000).collect()}
    assert set(got) == set(PLAYERS)
    for t, r in got.items():
        assert abs(r.estimate - want[t]) < 5 * r.se + 1e-9, (t, r.estimate, want[t])


def test_ratios_through_the_one_call(spark):
    out = attribute(spark, SF, "w14_ratio", "mc_multilinear", budget=200).collect()
    whole = spark.sql("SELECT sum(y) / sum(x) FROM {r}", r=lineage.rows_of(spark, SF, WORKLOADS["w14_ratio"])).first()[0]
    spread = math.sqrt(sum(r.se**2 for r in out)) * math.sqrt(len(out))
    assert len(out) > 62 and abs(sum(r.estimate for r in out) - float(whole)) < 5 * spread
    with pytest.raises(ValueError, match="ratios"):
        attribute(spark, SF, "w14_ratio", "relvec")
    with pytest.raises(ValueError, match="without options"):
        attribute(spark, SF, "w14_ratio", "mc_multilinear", runs=2)
    with pytest.raises(ValueError, match="ratios"):
        evaluate.value(F.col("view"), F.col("mask"), RATIO)


def test_targets_outside_the_lineage_get_zero(spark):
    targets = spark.createDataFrame([("all", "l:none")], "answer string, tid string")
    assert [r.estimate for r in attribute(spark, SF, "w14_ratio", "mc_multilinear", targets, budget=10).collect()] == [0.0]


def test_frozen_conditions_are_plain_sums(spark):
    for name in ("w18_frozen", "w21_frozen"):
        data = lineage.rows_of(spark, SF, WORKLOADS[name])
        assert data.where(F.size("any_of") + F.size("none_of") > 0).isEmpty()
        total = data.agg(F.sum("x")).first()[0]
        assert exact.closed_form(data, SHAPLEY).agg(F.sum("value")).first()[0] == pytest.approx(total)


def test_pruned_coalitions_change_nothing(rows):
    settings = lineage.settings(lineage.compile_view(rows.drop("y")))
    for agg, above in (("sum", 0), ("having", 45), ("exists", 0)):
        w = Workload("game", "", agg, above)
        every = exact.coalitions(settings)
        got = evaluate.pruning(every, w).first()
        assert got.drawn == len(PLAYERS) * 2 ** (len(PLAYERS) - 1) and 0 < got.pruned < got.drawn and got.wrong == 0
        for cached in (False, True):
            totals = [evaluate.marginals(every, w, cached, pruned).groupBy("tid").agg(F.count("*").alias("n"), F.sum("delta").alias("d")).collect() for pruned in (False, True)]
            assert sorted(totals[0]) == sorted(totals[1])
    plan = est.Plan(200, "clos")
    a, b = (values(est.stratified(settings, Workload("game", ""), p), "estimate") for p in (plan, replace(plan, prune_draws=True)))
    assert a == pytest.approx(b)


def test_structural_shares(rows):
    settings = lineage.settings(lineage.compile_view(rows.drop("y"))).where("tid = 'o|1'")
    strata = st.vectors(st.pools(settings, "clos"), SHAPLEY, 4)
    for r in strata.collect():
        c, lines, _, s = r.vec
        assert r.joins == pytest.approx(c * lines / 3 * s / 2)  # the other order is of the target's own relation
    dealt = st.allocate(strata, st.share_of("structure"), 500, 1)
    assert dealt.agg(F.sum("m"), F.min("m")).first()[:] == (500, 1)
    bare = st.allocate(strata, st.share_of("structure"), 500, 0)
    assert bare.where("joins = 0 AND m > 0").isEmpty()
    by_size = st.vectors(st.pools(settings, None), SHAPLEY, 1)
    assert all(r.joins == pytest.approx(r.size / (len(PLAYERS) - 1)) for r in by_size.collect())
    truth = values(exact.by_subset(settings, Workload("game", ""), SHAPLEY))["o|1"]
    for more in ({}, {"bins": 2}, {"cycles": 2}):
        got = est.stratified(settings, Workload("game", ""), est.Plan(4000, "clos", "structure", **more)).first()
        assert abs(got.estimate - truth) < 5 * got.se + 1e-9


def test_interval(spark):
    df = est.interval(spark.createDataFrame([(2.0, 0.5)], "estimate double, se double")).first()
    assert (round(df.low, 9), round(df.high, 9)) == (1.02, 2.98)
