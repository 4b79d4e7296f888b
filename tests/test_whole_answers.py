"""Queries that take all answers, whatever their size: none is left out for its number of tuples."""

from dataclasses import replace

import duckdb
import numpy as np
import pytest

from tests.conftest import DATA
from tupleshare.functions.semivalue import MAX_PLAYERS
from tupleshare.operators import estimate as est
from tupleshare.operators import lineage, within
from tupleshare.plans import oracles
from tupleshare.plans.queries import ENUMERATED, LETTERS, SHAPLEY, oracle_sql, queries
from tupleshare.plans.workloads import WORKLOADS

SF = "/root/testdata/sf0.01"


def large_rows(spark, answer="a", n=70):
    """An answer of n lines, an order and a customer; a line's row needs the order, that of an even line the customer too."""
    rows = [(answer, k + 1, [f"l|{k:03}", "o|1", *(["c|1"] if k % 2 == 0 else [])], [], []) for k in range(n)]
    return spark.createDataFrame(rows, "answer string, x long, need array<string>, any_of array<array<string>>, none_of array<array<string>>")


def both_views(spark, monkeypatch, name, few=5):
    """Answers with masks, and the same with ids in their place for those of more than 3 players."""
    rows = lineage.rows_of(spark, DATA, WORKLOADS[name])
    sizes = lineage.lineage(rows).groupBy("answer").count()
    some = sizes.where("count BETWEEN 3 AND 12").orderBy("answer").limit(few).select("answer")
    rows = rows.join(some, "answer", "left_semi").localCheckpoint()
    masks = lineage.compile_view(rows).localCheckpoint()
    monkeypatch.setattr(lineage, "MAX_PLAYERS", 3)
    ids = lineage.compile_view(rows, None).localCheckpoint()
    monkeypatch.undo()
    assert ids.where("size(listed) > 0 AND size(view) = 0").count() > 0
    return masks, ids


def test_orders_take_all_answers_of_w18(spark):
    """Every tuple has an estimate, and those of an answer add up to its sum: the marginals of an order do."""
    w = WORKLOADS["w18"]
    rows = lineage.rows_of(spark, SF, w)
    tuples = {(r.answer, r.tid) for r in lineage.lineage(rows).collect()}
    sums = {r.answer: r.x for r in rows.groupBy("answer").sum("x").toDF("answer", "x").collect()}
    assert len(tuples) > len({t for t in tuples if sum(a == t[0] for a, _ in tuples) <= ENUMERATED})
    got = queries()["all_targets_w18"](spark, SF).collect()
    assert {(r.answer, r.tid) for r in got} == tuples and len(got) == len(tuples)
    for answer, total in sums.items():
        assert sum(r.estimate for r in got if r.answer == answer) == pytest.approx(total)


def test_convergence_takes_all_answers_of_w18(spark):
    rows = lineage.rows_of(spark, SF, WORKLOADS["w18"])
    tuples = {(r.answer, r.tid) for r in lineage.lineage(rows).collect()}
    got = queries()["convergence_w18"](spark, SF).collect()
    assert {(r.answer, r.tid, r.checkpoint) for r in got} == {(*t, c) for t in tuples for c in (100, 200, 500, 1000)} and len(got) == 4 * len(tuples)
    for a, total in {r.answer: r.x for r in rows.groupBy("answer").sum("x").toDF("answer", "x").collect()}.items():
        for c in (100, 1000):
            assert sum(r.estimate for r in got if (r.answer, r.checkpoint) == (a, c)) == pytest.approx(total, abs=1e-4)


@pytest.mark.parametrize("name", ["w2_second", "w18_low", "w21"])
def test_ids_give_what_masks_give_in_orders(spark, monkeypatch, name):
    masks, ids = both_views(spark, monkeypatch, name)
    want = {tuple(r) for r in within.orders(masks, WORKLOADS[name], [7, 20], 2).collect()}
    assert want == {tuple(r) for r in within.orders(ids, WORKLOADS[name], [7, 20], 2).collect()} != set()


def test_growing_coalitions_have_their_values(monkeypatch):
    """By places in the order as one by one, with alternatives, blockers and rows that need nothing, tabled or not."""
    rng = np.random.default_rng(4)
    for name in ("w10", "w18", "w2"):
        w = WORKLOADS[name]
        for n, tabled in ((6, 12), (6, 0), (40, 0), (90, 12)):
            monkeypatch.setattr(within, "TABLED", tabled)
            some = lambda k: sum(1 << int(i) for i in rng.choice(n, k, replace=False))
            rows = [(some(rng.integers(0, 4)), int(rng.integers(1, 400)), [some(rng.integers(1, 3)) for _ in range(rng.integers(0, 3))], [some(rng.integers(1, 4)) for _ in range(rng.integers(0, 3))]) for _ in range(30)]
            order = np.array([rng.permutation(n) for _ in range(8)])
            got = within.growing(rows, [1 << i for i in range(n)], w)(order)
            for line, values in zip(order, got, strict=True):
                masks = [sum(1 << int(i) for i in line[:k]) for k in range(n + 1)]
                assert [within.value(rows, m, w.agg, w.above) for m in masks] == values.tolist()


def test_orders_of_more_players_than_masks_take(spark):
    rows = large_rows(spark)
    sizes = lineage.lineage(rows).groupBy("answer").count().first()
    assert sizes["count"] == 72 > MAX_PLAYERS and lineage.compile_view(rows).count() == 0
    got = {r.tid: r.total / r.draws for r in within.orders(lineage.compile_view(rows, None), WORKLOADS["w10"], [400]).collect()}
    want = {f"l|{k:03}": (k + 1) / (3 if k % 2 == 0 else 2) for k in range(70)}
    assert len(got) == 72 and sum(got.values()) == pytest.approx(sum(range(71)))
    assert sum(got[t] for t in want) == pytest.approx(sum(want.values()), rel=0.15)
    assert lineage.settings(lineage.compile_view(rows, None)).count() == 0


def estimates(df):
    return {(r.answer, r.tid, r.run): (r.estimate, r.se, r.starved_weight, r.draws) for r in df.collect()}


@pytest.mark.parametrize("name", ["w10", "w18_low", "w21"])
def test_ids_give_what_masks_give_in_strata(spark, monkeypatch, name):
    masks, ids = both_views(spark, monkeypatch, name, 3)
    for plan in (est.Plan(60, LETTERS[name], bins=4), est.Plan(60, LETTERS[name], cycles=2, pooling="cycle_mean"), est.Plan(60, None, prune=True)):
        want, got = (estimates(est.stratified(lineage.settings(masks), WORKLOADS[name], plan, view=v)) for v in (masks, ids))
        assert want == got != {}


@pytest.mark.parametrize("more", [{"bins": 4}, {"bins": 4, "cycles": 2}, {"cycles": 2, "pooling": "cycle_mean"}])
def test_strata_of_more_players_than_masks_take(spark, more):
    """A line adds its row's measure where the order and perhaps the customer are: values by the closed form."""
    view, w = lineage.compile_view(large_rows(spark), None), WORKLOADS["w10"]
    got = estimates(est.stratified(lineage.settings(view), w, est.Plan(3000, "lco", **more), view=view))
    want = {f"l|{k:03}": (k + 1) / (3 if k % 2 == 0 else 2) / w.unit for k in range(70)}
    assert len(got) == 72 and {t for _, t, _ in got} == {*want, "o|1", "c|1"}
    assert all(draws == 3000 and starved == 0 for _, _, starved, draws in got.values())
    assert sum(got["a", t, 0][0] for t in want) == pytest.approx(sum(want.values()), rel=0.02)
    assert max(abs(got["a", t, 0][0] - v) / v for t, v in want.items()) < 0.25


def test_what_rows_can_not_do_for_large_answers_raises(spark):
    view = lineage.compile_view(large_rows(spark), None)
    for plan in (est.Plan(60, "lco", cycles=3), est.Plan(60, "lco", prune_draws=True), est.Plan(60, "lco", attribute_quantiles=2)):
        with pytest.raises(ValueError, match="more than 62 tuples"):
            est.stratified(lineage.settings(view), WORKLOADS["w10"], plan, view=view)


def test_weights_of_many_players():
    """Those of one word as before; of more, and of more than floats count, they add up to 1."""
    from tupleshare.functions.semivalue import Semivalue

    omega = within.weights_of(Semivalue.shapley())
    assert omega(62) == Semivalue.shapley().table()[62]
    for n, c in ((63, (40, 20, 2)), (1400, (1398, 1))):
        strata = within.strata_of(n, c, (False,) * len(c), omega(n))
        assert sum(strata.w_value) == pytest.approx(1) == sum(strata.w_count)
        assert sum(within.allocate(strata.w_value, (True,) * len(strata.number), 5000, 1, "largest")) == 5000
        assert within.cells_of(strata, c, (True,) * len(strata.number), 4).w_value


def all_of_w10(spark, name):
    """Every tuple of every answer has an estimate of the draws asked for."""
    rows = lineage.rows_of(spark, DATA, WORKLOADS["w10"])
    tuples = {(r.answer, r.tid) for r in lineage.lineage(rows).collect()}
    assert len(tuples) > lineage.settings(lineage.compile_view(rows, ENUMERATED)).count()
    got = queries()[name](spark, DATA).collect()
    assert {(r.answer, r.tid) for r in got} == tuples and len(got) == len(tuples)
    assert {r.draws for r in got} == {100}


@pytest.mark.parametrize("name", ["relvec_binned_adaptive_w10", "relvec_binned_w10", "relvec_cycle_mean_w10"])
def test_strata_take_all_answers_of_w10(spark, name):
    all_of_w10(spark, name)


def test_cache_hits_take_all_answers_of_w10(spark):
    """200 draws of each tuple, and the same counts by SQL."""
    tuples = lineage.lineage(lineage.rows_of(spark, DATA, WORKLOADS["w10"])).count()
    got = queries()["cache_hits_w10"](spark, DATA).first()
    assert got.drawn == 200 * tuples
    con = duckdb.connect()
    for t in ("customer", "orders", "lineitem", "nation"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    assert con.execute(oracle_sql()["cache_hits_w10"]).fetchall() == [tuple(got)]


def test_cache_hits_of_ids_and_of_large_answers(spark, monkeypatch):
    """As of masks; and of an answer of more players than masks take the counts of SQL."""
    w, plan = WORKLOADS["w10"], est.Plan(50, "clno")
    masks, ids = both_views(spark, monkeypatch, "w10")
    assert within.cache_hits(masks, w, plan, SHAPLEY).first() == within.cache_hits(ids, w, plan, SHAPLEY).first()
    rows = large_rows(spark).select("answer", "x", "need")
    con, large = duckdb.connect(), [(r.answer, r.x, r.need) for r in rows.collect()]
    con.execute("CREATE TABLE given (answer VARCHAR, x BIGINT, need VARCHAR[])")
    con.executemany("INSERT INTO given VALUES (?, ?, ?)", large)
    sql = oracles.cache_hits(replace(w, rows="SELECT answer, x, need FROM given"), "clo", 200)
    got = within.cache_hits(lineage.compile_view(large_rows(spark), None), w, est.Plan(200, "clo"), SHAPLEY).first()
    assert got.drawn == 200 * 72 and con.execute(sql).fetchall() == [tuple(got)]
