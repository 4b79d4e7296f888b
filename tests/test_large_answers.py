"""Answers with more tuples than masks take, in the one-call interface."""

import pytest

from tupleshare.api import attribute
from tupleshare.functions.semivalue import MAX_PLAYERS
from tupleshare.operators import lineage
from tupleshare.plans.workloads import WORKLOADS

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("method", ["relvec_adaptive", "exact"])
def test_large_sums_get_the_closed_form(spark, method):
    want = {(r.answer, r.tid): r.estimate for r in attribute(spark, SF, "w6", "closed_form").collect()}
    assert len(want) > MAX_PLAYERS and any(want.values())
    assert {(r.answer, r.tid): r.estimate for r in attribute(spark, SF, "w6", method).collect()} == pytest.approx(want)
    some = [*sorted(want)[:3], ("all", "l:none")]
    got = {(r.answer, r.tid): r.estimate for r in attribute(spark, SF, "w6", method, spark.createDataFrame(some, "answer string, tid string")).collect()}
    assert got == pytest.approx({k: want.get(k, 0.0) for k in some})


def test_other_large_answers_raise(spark, monkeypatch):
    monkeypatch.setattr("tupleshare.api.MAX_PLAYERS", 2)
    sizes = lineage.lineage(lineage.rows_of(spark, SF, WORKLOADS["w18"])).groupBy("answer").count()
    assert sizes.where("count > 2").count() > 0
    with pytest.raises(ValueError, match="more than 2 tuples"):
        attribute(spark, SF, "w18", "relvec_adaptive")


def test_row_games_of_sums_with_alternatives(spark):
    """Row by row as by all coalitions of an answer's tuples, and beyond what masks take."""
    from tupleshare.functions.semivalue import Semivalue
    from tupleshare.operators import exact

    w = WORKLOADS["w21"]
    data = lineage.rows_of(spark, "/root/testdata/sf0.01", w)
    whole = {(r.answer, r.tid): r.value for r in exact.by_rows(data, w, Semivalue.shapley()).collect()}
    small = lineage.settings(lineage.compile_view(data, 10))
    some = {(r.answer, r.tid): r.value for r in exact.by_subset(small, w, Semivalue.shapley()).collect()}
    assert some and {k: whole[k] for k in some} == pytest.approx(some)
    sizes = {r.answer: r["count"] for r in lineage.lineage(data).groupBy("answer").count().collect()}
    rows = {r.answer: r["count"] for r in data.groupBy("answer").count().collect()}
    assert max(sizes.values()) > MAX_PLAYERS
    for answer, n in rows.items():  # efficiency: the values add up to the rows
        assert sum(v for (a, _), v in whole.items() if a == answer) == pytest.approx(n)


def test_what_can_not_be_enumerated_raises(spark):
    from tupleshare.functions.semivalue import Semivalue
    from tupleshare.operators import exact

    wide = spark.createDataFrame([("a", 1, [f"l|{k}" for k in range(28)], [], [])], "answer string, x long, need array<string>, any_of array<array<string>>, none_of array<array<string>>")
    settings = lineage.settings(lineage.compile_view(wide))
    for action in (lambda: exact.by_subset(settings, WORKLOADS["w18"], Semivalue.shapley()), lambda: exact.by_permutation(settings, WORKLOADS["w18"])):
        with pytest.raises(Exception, match="more than"):
            action().collect()
