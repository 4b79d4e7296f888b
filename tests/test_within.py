from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from tests.conftest import DATA
from tupleshare.operators import estimate as est
from tupleshare.operators import evaluate, lineage, measures, within
from tupleshare.operators import strata as st
from tupleshare.plans.queries import LETTERS, SHAPLEY, queries
from tupleshare.plans.workloads import WORKLOADS

PLANS = {
    "w10": [est.Plan(60), est.Plan(60, "*", cycles=2, pooling="cycle_mean"), est.Plan(60, "*", bins=2, cycles=2)],
    "w21": [est.Plan(60, "*", cycles=2), est.Plan(60, "*", "count", prune=True, floor=0, rounding="nearest")],
    "w18_low": [est.Plan(60, "*", cycles=2), est.Plan(60, "*", attribute_quantiles=2)],
}


def no_shuffle(df):
    return "Exchange" not in df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", sorted(PLANS))
def test_rows_give_what_tables_give(spark, name):
    w = WORKLOADS[name]
    settings = lineage.settings(lineage.compiled(spark, DATA, w, 9))
    settings = settings.join(settings.select("answer").distinct().orderBy("answer").limit(2), "answer").localCheckpoint()
    assert settings.count() > 0
    for plan in PLANS[name]:
        plan = replace(plan, letters=LETTERS[name] if plan.letters else None)
        got = est.stratified(settings, w, plan, 2)
        assert no_shuffle(got.where("TRUE"))
        tables = est.stratified(settings, w, plan, 2, progress=[])
        a, b = ({(r.answer, r.tid, r.run): (r.estimate, r.se, r.starved_weight, r.draws) for r in df.collect()} for df in (got, tables))
        assert a.keys() == b.keys()
        for k in a:
            assert a[k] == pytest.approx(b[k], rel=1e-9, abs=1e-9), (plan, k)


def test_one_order_for_all_targets(spark):
    w = WORKLOADS["w18_low"]
    view = lineage.compiled(spark, DATA, w, 9)
    view = view.orderBy("answer").limit(5).localCheckpoint()
    got = within.orders(view, w, [10, 30], 2)
    assert no_shuffle(got)
    settings = lineage.settings(view)
    place = [42, "order", F.col("answer"), F.col("run"), F.col("draw")]
    mask = est._members(lambda p: est.key(*place, p["tid"]) < est.key(*place, F.col("tid")))
    deltas = est._plain_draws(settings, 30, 2).withColumn("mask", mask).withColumn("delta", evaluate.marginal(F.col("view"), F.col("mask"), F.col("bit"), w))
    want = {(r.answer, r.tid, r.run, r.checkpoint): r.estimate for r in measures.convergence(deltas, [10, 30]).collect()}
    assert {(r.answer, r.tid, r.run, r.checkpoint): r.total / r.draws for r in got.collect()} == want and want


def test_values_of_many_coalitions(spark, monkeypatch):
    """By table and one by one they are those of single coalitions, and orders give the same either way."""
    import numpy as np

    for name in ("w2", "w18_low", "w21"):
        w = WORKLOADS[name]
        view = lineage.compiled(spark, DATA, w, 9).orderBy("answer").limit(4).localCheckpoint()
        for r in view.collect():
            rows = [(v.need, v.x, v.any_of, v.none_of) for v in r.view]
            masks = np.arange(1 << len(r.players))
            want = [within.value(rows, int(m), w.agg, w.above) for m in masks]
            assert within.values_at(rows, masks, w).tolist() == within.values_of(rows, len(r.players), w)(masks).tolist() == want
        tabled = {tuple(r) for r in within.orders(view, w, [7, 20]).collect()}
        monkeypatch.setattr(within, "TABLED", 0)
        assert {tuple(r) for r in within.orders(view, w, [7, 20]).collect()} == tabled
        monkeypatch.undo()


def test_totals_stay_in_the_row(spark):
    """Answers of the view are sampled without a shuffle, those it lacks on the rows, all with the draws of the rows."""
    for name in ("w2", "w18_low"):
        w = WORKLOADS[name]
        rows = lineage.rows_of(spark, DATA, w)
        answers = rows.select("answer").distinct().orderBy("answer").limit(6)
        rows = rows.join(answers, "answer").localCheckpoint()
        view = lineage.compile_view(rows).localCheckpoint()
        assert no_shuffle(within.multilinear(view, w, 40))
        part = view.orderBy("answer").limit(3).localCheckpoint()
        want = {(r.answer, r.tid): (r.estimate, r.se, r.draws) for r in est.multilinear_totals(rows, lineage.lineage(rows), w, 40).collect()}
        for v in (view, part):
            got = {(r.answer, r.tid): (r.estimate, r.se, r.draws) for r in est.multilinear_totals(rows, None, w, 40, view=v).collect()}
            assert got.keys() == want.keys() and got
            for k in got:
                assert got[k] == pytest.approx(want[k], rel=1e-9, abs=1e-9), k


def tagged_by_tables(spark, view, rows, w, plan):
    """(compared, different) by a table of draws and one of memberships."""
    pooled, strata, width = est.prepare(lineage.settings(view), plan, SHAPLEY)
    draws = est.draw(st.allocate(est.with_runs(strata, 1), st.share_of("value"), plan.budget, 1, by=est.RUN), pooled, plan, 0, width)
    players = view.select("answer", "players")
    draws = draws.withColumn("coalition", F.concat_ws("/", "answer", "tid", "stratum", "draw")).join(players, "answer")
    by_mask = draws.select("coalition", evaluate.value(F.col("view"), F.col("mask"), w).alias("by_mask"))
    by_join = evaluate.tagged(rows, evaluate.memberships(draws, False), draws, w)
    return tuple(by_mask.join(by_join, "coalition").agg(F.count("*"), F.coalesce(F.sum((F.col("by_mask") != F.col("v")).cast("int")), F.lit(0))).first())


@pytest.mark.parametrize("name", ["w10", "w2_second", "w18_low", "w21"])
def test_tagged_draws_stay_in_the_row(spark, name):
    """As many are compared, and as many differ if an answer's rows are missing and others count twice."""
    w, plan = WORKLOADS[name], est.Plan(20, LETTERS[name])
    rows = lineage.rows_of(spark, DATA, w)
    view = lineage.compile_view(rows, 12)
    view = view.orderBy("answer").limit(4).localCheckpoint()
    rows = rows.join(view.select("answer"), "answer").localCheckpoint()
    other = rows.where(F.col("answer") != view.first().answer).withColumn("x", 2 * F.col("x")).localCheckpoint()
    assert tuple(within.tagged_differences(view, rows, w, plan, SHAPLEY).first()) == tagged_by_tables(spark, view, rows, w, plan)
    got = tuple(within.tagged_differences(view, other, w, plan, SHAPLEY).first())
    assert got == tagged_by_tables(spark, view, other, w, plan) and 0 < got[1] < got[0]
    assert tuple(within.tagged_differences(view.limit(0), rows, w, plan, SHAPLEY).first()) == (0, 0)


def test_tagged_query_makes_no_table_of_draws(spark):
    plan = queries()["tagged_equals_bitset_w10"](spark, DATA)._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plan and "MapInArrow" in plan
