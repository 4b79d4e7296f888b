"""The worked example, fixtures with known values, and the properties of exact and sampled values."""

import math
from dataclasses import replace
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from tupleshare.functions.semivalue import Semivalue, choose
from tupleshare.operators import estimate as est
from tupleshare.operators import evaluate, exact, lineage, measures
from tupleshare.operators import strata as st
from tupleshare.plans.queries import LETTERS
from tupleshare.plans.workloads import WORKLOADS, Workload

SF = "/root/testdata/sf0.01"
SHAPLEY = Semivalue.shapley()
EXAMPLE = Workload("example", "", "sum", 0, 1.0)
LINES = {"l|1": 450.0, "l|2": 594.0, "l|3": 658.0, "l|4": 617.5}


@pytest.fixture(scope="module")
def example(spark):
    """One customer, one order, four lines; revenue in tenths so that it is whole."""
    rows = [("a", int(x * 10), ["c|1", t, "o|1"], [], []) for t, x in LINES.items()]
    df = spark.createDataFrame(rows, "answer string, x long, need array<string>, any_of array<array<string>>, none_of array<array<string>>")
    return df, lineage.compile_view(df).cache()


def values(df, scale=1.0):
    return {r.tid: r.value / scale for r in df.collect()}


def settings_of(spark, name, where):
    return lineage.settings(lineage.compile_view(lineage.rows_of(spark, SF, WORKLOADS[name]).where(where))).cache()


@pytest.mark.parametrize(
    "semivalue, shared, first",
    [(SHAPLEY, 773.166667, 150.0), (Semivalue.banzhaf(), 579.875, 112.5), (Semivalue.beta(4, 1), 154.633333, 30.0), (Semivalue.beta(1, 4), 1546.333333, 300.0)],
)
def test_example_by_closed_form_and_enumeration(example, semivalue, shared, first):
    rows, view = example
    for got in (values(exact.closed_form(rows, semivalue), 10), values(exact.by_subset(lineage.settings(view), EXAMPLE, semivalue), 10)):
        assert got["o|1"] == pytest.approx(shared, abs=1e-5) and got["c|1"] == pytest.approx(shared, abs=1e-5)
        assert got["l|1"] == pytest.approx(first, abs=1e-5)


def test_example_permutations_groups_and_marginal(example):
    _, view = example
    shapley = values(exact.by_subset(lineage.settings(view), EXAMPLE, SHAPLEY), 10)
    for other in (exact.by_permutation(lineage.settings(view), EXAMPLE), exact.owen(lineage.settings(view), EXAMPLE, "clo")):
        assert values(other, 10) == pytest.approx(shapley)
    assert sum(shapley.values()) == pytest.approx(2319.5)
    one = lineage.settings(view).where("tid = 'o|1'")
    mask = F.aggregate(F.filter("others", lambda p: p["tid"].isin("c|1", "l|1", "l|2", "l|3")), F.lit(0).cast("long"), lambda a, p: a.bitwiseOR(p["bit"]))
    assert one.select(evaluate.marginal(F.col("view"), mask, F.col("bit"), EXAMPLE)).first()[0] == 17020


def test_example_strata(example):
    _, view = example
    one = lineage.settings(view).where("tid = 'o|1'")
    got = {tuple(r.vec): (round(r.w_value, 6), r.n_coal) for r in st.vectors(st.pools(one, "clo"), SHAPLEY, 3).collect()}
    weights = {(0, 0): 1 / 6, (1, 0): 1 / 30, (0, 1): 2 / 15, (1, 1): 1 / 15, (0, 2): 0.1, (1, 2): 0.1, (0, 3): 1 / 15, (1, 3): 2 / 15, (0, 4): 1 / 30, (1, 4): 1 / 6}
    assert got == {(c, k, 0): (round(w, 6), math.comb(4, k)) for (c, k), w in weights.items()}
    sigma = {tuple(r.vec): r.sigma / 10 for r in exact.stratum_table(one, EXAMPLE, SHAPLEY, "clo").collect()}
    assert sigma[(1, 2, 0)] == pytest.approx(90.53, abs=0.01) and sigma[(1, 1, 0)] == pytest.approx(78.40, abs=0.01) and sigma[(0, 3, 0)] == 0


@pytest.mark.parametrize(
    "name, answer, want",
    [
        ("w2", "748", {"q|748|19": 0.040909, "p|748": 0.315909, "r|3": 0.315909}),
        ("w2_second", "748", {"q|748|19": 0.075, "q|748|83": -0.125}),
        ("w18_low", "102", {"c|227": 27.015873, "o|102": 27.015873}),
        ("w21", "17", {"s|17": 0.433333}),
        ("w10", "39", {"o|4321": 36245.634175}),
    ],
)
def test_fixtures(spark, name, answer, want):
    got = values(exact.by_subset(settings_of(spark, name, f"answer = '{answer}'"), WORKLOADS[name], SHAPLEY), 1)
    assert {k: got[k] for k in want} == pytest.approx(want, abs=1e-5)


def test_having_with_a_lower_bar(spark):
    w = replace(WORKLOADS["w18_low"], above=100)
    assert values(exact.by_subset(settings_of(spark, "w18_low", "answer = '64'"), w, SHAPLEY))["o|64"] == pytest.approx(36.934524, abs=1e-5)


def test_closed_form_equals_enumeration_and_is_efficient(spark):
    rows = lineage.rows_of(spark, SF, WORKLOADS["w10"]).where("answer IN ('39', '750', '12')")
    view = lineage.compile_view(rows)
    closed = exact.closed_form(rows, SHAPLEY, 1e4)
    assert values(closed) == pytest.approx(values(exact.by_subset(lineage.settings(view), WORKLOADS["w10"], SHAPLEY)))
    assert all(abs(r.gap) < 1e-5 for r in measures.axioms(closed, view, WORKLOADS["w10"]).collect())


def test_weights_sum_to_one():
    for s in (SHAPLEY, Semivalue.banzhaf(), Semivalue.beta(4, 1), Semivalue.beta(2, 3), Semivalue.custom("mid", [0, 1, 2, 1, 0])):
        n = 5
        assert sum(math.comb(n - 1, k) * s.weight(n, k) for k in range(n)) == 1
    for n in range(1, 9):
        assert all(SHAPLEY.weight(n, k) == Semivalue.beta(1, 1).weight(n, k) for k in range(n))


def test_choose(spark):
    df = spark.range(1).select(*(choose(F.lit(n), F.lit(k)).alias(f"c{n}_{k}") for n, k in ((0, 0), (5, 2), (61, 30), (4, 5), (3, 0), (20, 20))))
    assert list(df.first()) == pytest.approx([1, 10, math.comb(61, 30), 0, 1, 1], rel=1e-12)


@pytest.mark.parametrize("rule", ["count", "equal", "value"])
@pytest.mark.parametrize("floor", [0, 1])
def test_allocation_sums_and_floor(spark, rule, floor):
    strata = st.vectors(st.pools(settings_of(spark, "w18_low", "answer = '102'"), "clo"), SHAPLEY, 3)
    for budget in (7, 100, 1001):
        dealt = st.allocate(strata, st.share_of(rule), budget, floor)
        assert [r[0] for r in dealt.groupBy("answer", "tid").agg(F.sum("m")).select("sum(m)").distinct().collect()] == [budget]
        if floor and budget > 40:
            assert dealt.agg(F.min("m")).first()[0] >= 1


@pytest.mark.parametrize("method", est.METHODS)
def test_unbiased_within_error(spark, method):
    settings = settings_of(spark, "w18_low", "answer = '64'").where("rel <> 'c'")
    truth = exact.by_subset(settings, WORKLOADS["w18_low"], SHAPLEY)
    runs = est.estimate(settings, WORKLOADS["w18_low"], method, 300, "clo", 25)
    for r in measures.errors(runs, truth).collect():
        assert abs(r.bias) < 5 * math.sqrt(r.variance / r.runs) + 0.02 * abs(r.exact), (r.tid, r.bias)


def test_line_target_has_no_variance(spark):
    settings = settings_of(spark, "w3_late", "answer = '1181'").where("rel = 'l'")
    truth = values(exact.by_subset(settings, WORKLOADS["w3_late"], SHAPLEY))
    got = {r.tid: r.estimate for r in est.estimate(settings, WORKLOADS["w3_late"], "relvec", 100, "clo").collect()}
    assert got == pytest.approx(truth)


def test_variants_agree(spark):
    w, settings = WORKLOADS["w18_low"], settings_of(spark, "w18_low", "answer = '64'")
    plain = est.Plan(400, "clo")
    get = lambda plan: {r.tid: r.estimate for r in est.stratified(settings, w, plan).collect()}
    base = get(plain)
    assert get(replace(plain, cached=True)) == pytest.approx(base)
    truth = values(exact.by_subset(settings, w, SHAPLEY))
    assert get(replace(plain, budget=20000, census=True)) == pytest.approx(truth)
    for more in ({"prune": True}, {"bins": 3}, {"attribute_quantiles": 2}, {"budget": 2000, "cycles": 4}, {"cycles": 3, "pooling": "cycle_mean", "budget": 2000}):
        for t, x in get(replace(plain, **more)).items():
            assert x == pytest.approx(truth[t], rel=0.25, abs=1.5), (more, t)


def test_same_draws_in_any_partitioning(spark):
    settings = settings_of(spark, "w21", "answer = '17'")
    one = est.estimate(settings.coalesce(1), WORKLOADS["w21"], "relvec", 200, LETTERS["w21"])
    many = est.estimate(settings.repartition(13), WORKLOADS["w21"], "relvec", 200, LETTERS["w21"])
    assert sorted((r.tid, round(r.estimate, 9)) for r in one.collect()) == sorted((r.tid, round(r.estimate, 9)) for r in many.collect())


def test_stratification_beats_sizes_with_a_floor(spark):
    """The order of the methods on the setting of 18 other players; shares by count without a floor starve strata."""
    settings = settings_of(spark, "w21", "answer = '70'").where("tid = 'o|1'")
    truth = exact.by_subset(settings, WORKLOADS["w21"], SHAPLEY)
    assert truth.first()["value"] == pytest.approx(0.233333, abs=1e-5)

    def mre(method, profile, **more):
        return measures.errors(est.estimate(settings, WORKLOADS["w21"], method, 1000, "lnos", 10, profile, **more), truth).first()

    starved_size, starved_vector = mre("size", "count"), mre("relvec", "count")
    assert starved_size.mre > 0.3 and starved_vector.mre > 0.3 and starved_vector.starved_weight > 0.3
    fair_vector = mre("relvec", "default")
    assert fair_vector.mre < 0.06 and fair_vector.starved_weight == 0
    assert mre("relvec_adaptive", "default", cycles=2).mre < starved_vector.mre / 4


def test_null_player_and_split(spark):
    rows = lineage.rows_of(spark, SF, WORKLOADS["w3_late"])
    lin = lineage.lineage(rows)
    lines = spark.createDataFrame([("l|0|0|0|0|2000-01-01",), (lin.where("rel = 'l'").first()["tid"],)], "tid string")
    assert {r.tid: r.endogenous for r in lineage.split(lines, F.col("tid"), lin).collect()}["l|0|0|0|0|2000-01-01"] is False


def test_many_players_without_masks(spark):
    rows = lineage.rows_of(spark, SF, WORKLOADS["w14"])
    truth = values(exact.closed_form(rows, SHAPLEY, 1e4))
    targets = spark.createDataFrame([("all", t) for t in sorted(t for t in truth if t.startswith("p"))[:5]], "answer string, tid string")
    for r in est.multilinear_rows(rows, targets, 800, unit=1e4).collect():
        assert abs(r.estimate - truth[r.tid]) < 5 * r.se


def test_wide_answers_are_left_to_other_ways(spark):
    rows = lineage.rows_of(spark, SF, WORKLOADS["w14"])
    assert lineage.compile_view(rows).count() == 0


def test_brute_force_of_a_small_game(example):
    _, view = example
    got = values(exact.by_subset(lineage.settings(view), EXAMPLE, SHAPLEY), 10)
    players = ["c|1", "o|1", *LINES]

    def v(s):
        return sum(x for t, x in LINES.items() if t in s) if {"c|1", "o|1"} <= s else 0

    for p in players:
        rest = [q for q in players if q != p]
        want = sum((v(set(s) | {p}) - v(set(s))) / (6 * math.comb(5, k)) for k in range(6) for s in combinations(rest, k))
        assert got[p] == pytest.approx(want)
