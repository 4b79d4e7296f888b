"""The one-call interface, the value store and the table functions."""

import math

import pytest

from tupleshare.api import attribute
from tupleshare.functions.table_functions import register
from tupleshare.operators import cache, evaluate
from tupleshare.operators import estimate as est
from tupleshare.operators import strata as st
from tupleshare.operators.lineage import compile_view, rows_of, settings
from tupleshare.plans.workloads import WORKLOADS

SF = "/root/testdata/sf0.01"


def test_attribute_methods_agree_and_strangers_get_nothing(spark):
    targets = spark.createDataFrame([("102", "o|102"), ("102", "o|nobody")], "answer string, tid string")
    for method in ("exact", "relvec", "size_adaptive"):
        got = {r.tid: r.estimate for r in attribute(spark, SF, "w18_low", method, targets, "answer = '102'", 2000).collect()}
        assert got["o|nobody"] == 0 and got["o|102"] == pytest.approx(27.015873, rel=0.1)
    with pytest.raises(ValueError):
        attribute(spark, SF, "w21", "closed_form")


def test_store_evaluates_each_coalition_once(spark, tmp_path):
    w, path = WORKLOADS["w18_low"], str(tmp_path / "values")
    everyone = settings(compile_view(rows_of(spark, SF, w).where("answer = '102'")))
    plan = est.Plan(100, "clo")
    pooled = st.pools(everyone, "clo")
    from tupleshare.functions.semivalue import Semivalue

    strata = est.with_runs(st.vectors(pooled, Semivalue.shapley(), 3), 1)
    draws = est.draw(st.allocate(strata, st.share_of("value"), 100, 1, by=est.RUN), pooled, plan, 0, 3).cache()
    assert cache.extend(draws, w, path) == evaluate.cache_hits(draws).first()["distinct_evaluations"]
    assert cache.extend(draws, w, path) == 0
    stored = sorted((r.tid, r.mask, r.delta) for r in cache.marginals_from(draws, w, path).collect())
    assert stored == sorted((r.tid, r.mask, r.delta) for r in evaluate.marginals(draws, w, cached=False).collect())


def test_table_functions(spark):
    register(spark)
    assert sorted(tuple(r.vec) for r in spark.sql("SELECT * FROM enumerate_vectors(array(1, 2))").collect()) == [(a, b) for a in range(2) for b in range(3)]
    subsets = {tuple(r.member for r in spark.sql(f"SELECT * FROM unrank_subset(5, 2, {k})").collect()) for k in range(math.comb(5, 2))}
    assert len(subsets) == 10 and all(len(s) == 2 for s in subsets)
