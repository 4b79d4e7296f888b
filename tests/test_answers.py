"""Answers in their own rows against tables of settings, strata and draws."""

from dataclasses import replace

import pytest

from tests.conftest import DATA
from tests.test_within import PLANS, no_shuffle
from tupleshare.functions.semivalue import Semivalue
from tupleshare.operators import estimate as est
from tupleshare.operators import evaluate, lineage, within
from tupleshare.operators import strata as st
from tupleshare.plans.queries import LETTERS
from tupleshare.plans.workloads import WORKLOADS

SHAPLEY = Semivalue.shapley()


def few(spark, name, answers):
    view = lineage.compiled(spark, DATA, WORKLOADS[name], 9)
    return view.orderBy("answer").limit(answers).localCheckpoint()


def by_key(df):
    return {(r.answer, r.tid, r.run): (r.estimate, r.se, r.starved_weight, r.draws) for r in df.collect()}


@pytest.mark.parametrize("name", sorted(PLANS))
def test_answers_give_what_settings_give(spark, name):
    view, w = few(spark, name, 4), WORKLOADS[name]
    settings = lineage.settings(view)
    for plan in PLANS[name]:
        plan = replace(plan, letters=LETTERS[name] if plan.letters else None)
        got = est.stratified(settings, w, plan, 2, view=view)
        assert no_shuffle(got)
        assert by_key(got) == by_key(est.stratified(settings, w, plan, 2)) != {}


@pytest.mark.parametrize("name", ["w10", "w18_low"])
def test_census_within_rows(spark, name):
    view, w = few(spark, name, 3), WORKLOADS[name]
    settings, plan = lineage.settings(view), est.Plan(60, LETTERS[name], census=True)
    got = est.stratified(settings, w, plan, view=view)
    assert no_shuffle(got)
    a, b = by_key(got), by_key(est.stratified(settings, w, plan, progress=[]))
    assert a.keys() == b.keys() and a
    for k in a:
        assert a[k] == pytest.approx(b[k], rel=1e-9, abs=1e-9)


@pytest.mark.parametrize("name", sorted(PLANS))
def test_pruning_and_cache_within_rows(spark, name):
    view, w = few(spark, name, 6), WORKLOADS[name]
    plan = est.Plan(50, LETTERS[name])
    pooled, strata, width = est.prepare(lineage.settings(view), plan, SHAPLEY)
    draws = est.draw(st.allocate(est.with_runs(strata, 1), st.share_of("value"), 50, 1, by=est.RUN), pooled, plan, 0, width).localCheckpoint()
    assert within.pruning(view, w, plan, SHAPLEY).collect() == evaluate.pruning(draws, w).collect()
    assert within.cache_hits(view, w, plan, SHAPLEY).collect() == evaluate.cache_hits(draws).collect()
    assert within.cache_hits(view.limit(0), w, plan, SHAPLEY).first().distinct_evaluations == 0
