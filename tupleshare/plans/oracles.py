"""DuckDB SQL for the attribution queries, from the same workload rows but by other ways than the Spark plans."""

from __future__ import annotations

import math
from dataclasses import replace

from ..functions.semivalue import Semivalue
from ..sources.tables import duck_sql
from .workloads import Workload


def rows(w: Workload, where: str = "TRUE", most: int | None = None) -> str:
    """CTEs `r`: answer, id, x, part (the y of ratios), need, any_of, none_of; only answers of at most `most` tuples, if given."""
    any_of = "any_of" if "AS any_of" in w.rows else "CAST([] AS VARCHAR[][])"
    none_of = "none_of" if "AS none_of" in w.rows else "CAST([] AS VARCHAR[][])"
    part = "y" if " AS y," in w.rows else "CAST(0 AS BIGINT)"
    fit = f"answer IN (SELECT answer FROM (SELECT DISTINCT answer, unnest(list_concat(need, list_concat(flatten(any_of), flatten(none_of)))) AS tid FROM q1) GROUP BY answer HAVING count(*) <= {most})" if most else "TRUE"
    return f"""q0 AS MATERIALIZED ({duck_sql(w.rows)}), q1 AS MATERIALIZED (SELECT answer, row_number() OVER () AS id, x, {part} AS part, list_sort(list_distinct(need)) AS need, {any_of} AS any_of, {none_of} AS none_of FROM q0 WHERE {where}),
r AS MATERIALIZED (SELECT * FROM q1 WHERE {fit})"""


def players(w: Workload, where: str = "TRUE", most: int | None = None) -> str:
    return f"{rows(w, where, most)}, pl AS MATERIALIZED (SELECT DISTINCT answer, unnest(list_concat(need, list_concat(flatten(any_of), flatten(none_of)))) AS tid FROM r)"


def lineage(w: Workload) -> str:
    return f"WITH {players(w)} SELECT answer, substr(tid, 1, 1) AS rel, tid FROM pl"


def size_vectors(w: Workload, letters: str) -> str:
    each = ", ".join(f"CAST(count(*) FILTER (WHERE substr(tid, 1, 1) = '{c}') AS BIGINT) AS {c}" for c in letters)
    return f"WITH {players(w)} SELECT answer, {each}, count(*) AS players FROM pl GROUP BY answer"


def stats(w: Workload) -> str:
    return f"WITH {players(w)}, p AS (SELECT answer, count(*) AS n FROM pl GROUP BY answer) SELECT count(*) AS answers, min(n) AS least, max(n) AS most, CAST(sum(n) AS BIGINT) AS total, (SELECT count(DISTINCT substr(tid, 1, 1)) FROM pl) AS relations FROM p"


def closed_form(w: Workload, semivalue: Semivalue, digits: int = 7) -> str:
    share = " ".join(f"WHEN {m + 1} THEN {float(semivalue.chance(m))!r}::DOUBLE" for m in range(8))
    return f"WITH {rows(w)}, u AS (SELECT answer, x, len(need) AS m, unnest(need) AS tid FROM r) SELECT answer, substr(tid, 1, 1) AS rel, tid, round(sum(x * CASE m {share} END) / {w.unit}, {digits}) AS value FROM u GROUP BY answer, tid"


def _total(w: Workload) -> str:
    return {"exists": "CASE WHEN count(a.x) > 0 THEN 1 ELSE 0 END", "having": f"CASE WHEN coalesce(sum(a.x), 0) > {w.above} THEN sum(a.x) ELSE 0 END"}.get(w.agg, "coalesce(sum(a.x), 0)")


def masks(w: Workload, where: str = "TRUE", most: int | None = None) -> str:
    """CTEs up to the masks of each row: `b` the players' bits, `n` their number, `m`, `am`, `nm` what a row needs, its
    alternatives and its blockers."""
    return f"""WITH {players(w, where, most)},
b AS MATERIALIZED (SELECT answer, tid, 1::BIGINT << (row_number() OVER (PARTITION BY answer ORDER BY tid) - 1) AS bit FROM pl),
n AS MATERIALIZED (SELECT answer, count(*) AS n FROM pl GROUP BY answer),
m AS MATERIALIZED (SELECT u.id, u.answer, any_value(u.x) AS x, CAST(sum(bit) AS BIGINT) AS need FROM (SELECT id, answer, x, unnest(need) AS tid FROM r) u JOIN b USING (answer, tid) GROUP BY u.id, u.answer),
ka AS (SELECT id, answer, generate_subscripts(any_of, 1) AS k, unnest(any_of) AS s FROM r),
am AS MATERIALIZED (SELECT id, k, CAST(sum(bit) AS BIGINT) AS mask FROM (SELECT id, answer, k, unnest(s) AS tid FROM ka) JOIN b USING (answer, tid) GROUP BY id, k),
kn AS (SELECT id, answer, generate_subscripts(none_of, 1) AS k, unnest(none_of) AS s FROM r),
nm AS MATERIALIZED (SELECT id, k, CAST(sum(bit) AS BIGINT) AS mask FROM (SELECT id, answer, k, unnest(s) AS tid FROM kn) JOIN b USING (answer, tid) GROUP BY id, k)"""


def _valued(w: Workload, coalitions: str) -> str:
    """CTEs `a`, the rows that hold in each coalition (answer, s) of a table, and `v`, its value by key `k`."""
    alive = []
    if "AS any_of" in w.rows:
        alive.append("(NOT EXISTS (SELECT 1 FROM am WHERE am.id = m.id) OR EXISTS (SELECT 1 FROM am WHERE am.id = m.id AND (c.s & am.mask) = am.mask))")
    if "AS none_of" in w.rows:
        alive.append("NOT EXISTS (SELECT 1 FROM nm WHERE nm.id = m.id AND (c.s & nm.mask) = nm.mask)")
    return f"""a AS (SELECT c.answer, c.s, m.x FROM {coalitions} c JOIN m ON c.answer = m.answer AND (c.s & m.need) = m.need WHERE {' AND '.join(alive) or 'TRUE'}),
v AS MATERIALIZED (SELECT c.answer, c.n, c.s, c.answer || '/' || CAST(c.s AS VARCHAR) AS k, {_total(w)} AS v FROM {coalitions} c LEFT JOIN a ON a.answer = c.answer AND a.s = c.s GROUP BY c.answer, c.n, c.s)"""


def values_of_all(w: Workload, where: str, most: int | None = None) -> str:
    """CTEs up to `v`: the value of every coalition of all players of the answers."""
    return f"{masks(w, where, most)},\nc AS MATERIALIZED (SELECT answer, n, unnest(range(0, 1::BIGINT << n)) AS s FROM n),\n{_valued(w, 'c')}"


OMEGA = {"shapley": "factorial(bit_count(v0.s)::INTEGER)::DOUBLE * factorial((v0.n - 1 - bit_count(v0.s))::INTEGER)::DOUBLE / factorial(v0.n::INTEGER)::DOUBLE", "banzhaf": "1.0::DOUBLE / (1::BIGINT << (v0.n - 1))"}


def by_subset(w: Workload, where: str = "TRUE", semivalue: str = "shapley", digits: int = 6, most: int | None = None) -> str:
    return f"""{values_of_all(w, where, most)}
SELECT b.answer, substr(b.tid, 1, 1) AS rel, b.tid, round(sum({OMEGA[semivalue]} * (v1.v - v0.v)) / {w.unit}, {digits}) AS value
FROM b JOIN v v0 ON v0.answer = b.answer AND (v0.s & b.bit) = 0 JOIN v v1 ON v1.k = b.answer || '/' || CAST(v0.s | b.bit AS VARCHAR) GROUP BY b.answer, b.tid"""


def by_rows(w: Workload, digits: int = 7) -> str:
    """Sums whose rows have alternatives of one tuple each: a row of m needed tuples and j alternatives is a game of
    m + j players, whose Shapley values have a formula."""
    share = "CASE WHEN j = 0 THEN 1.0 / m ELSE list_sum(list_transform(range(1, j + 1), lambda i: factorial(j) / (factorial(CAST(i AS INTEGER)) * factorial(CAST(j - i AS INTEGER))) * factorial(CAST(m - 1 + i AS INTEGER)) * factorial(CAST(j - i AS INTEGER)) / factorial(CAST(m + j AS INTEGER)))) END"
    one = "factorial(CAST(m AS INTEGER)) * factorial(CAST(j - 1 AS INTEGER)) / factorial(CAST(m + j AS INTEGER))"
    return f"""WITH {rows(w)}, g AS (SELECT answer, x, need, any_of, CAST(len(need) AS INTEGER) AS m, CAST(len(any_of) AS INTEGER) AS j FROM r),
u AS (SELECT answer, unnest(need) AS tid, x * ({share}) AS y FROM g UNION ALL SELECT answer, unnest(flatten(any_of)) AS tid, x * ({one}) AS y FROM g WHERE j > 0)
SELECT answer, substr(tid, 1, 1) AS rel, tid, round(sum(y) / {w.unit}, {digits}) AS value FROM u GROUP BY answer, tid"""


def owen(w: Workload, letters: str, most: int, digits: int = 6) -> str:
    """Coalitions in which every other relation is whole or absent."""
    groups = ", ".join(f"CAST(coalesce(sum(bit) FILTER (WHERE substr(tid, 1, 1) = '{c}'), 0) AS BIGINT) AS {c}" for c in letters)
    whole = " AND ".join(f"(substr(b.tid, 1, 1) = '{c}' OR (v0.s & g.{c}) IN (0, g.{c}))" for c in letters)
    foreign = "CAST(" + " + ".join(f"(CASE WHEN substr(b.tid, 1, 1) <> '{c}' AND g.{c} <> 0 THEN 1 ELSE 0 END)" for c in letters) + " AS INTEGER)"
    chosen = "CAST(" + " + ".join(f"(CASE WHEN substr(b.tid, 1, 1) <> '{c}' AND g.{c} <> 0 AND (v0.s & g.{c}) = g.{c} THEN 1 ELSE 0 END)" for c in letters) + " AS INTEGER)"
    own = "CASE substr(b.tid, 1, 1) " + " ".join(f"WHEN '{c}' THEN g.{c}" for c in letters) + " END"
    weigh = "factorial({k}) * factorial({n} - {k}) / factorial({n} + 1)"
    weight = f"({weigh.format(k=chosen, n=foreign)}) * ({weigh.format(k=f'CAST(bit_count(v0.s & {own}) AS INTEGER)', n=f'CAST(bit_count({own}) - 1 AS INTEGER)')})"
    return f"""{values_of_all(w, 'TRUE', most)}, g AS (SELECT answer, {groups} FROM b GROUP BY answer)
SELECT b.answer, substr(b.tid, 1, 1) AS rel, b.tid, round(sum({weight} * (v1.v - v0.v)) / {w.unit}, {digits}) AS value
FROM b JOIN g ON g.answer = b.answer JOIN v v0 ON v0.answer = b.answer AND (v0.s & b.bit) = 0 AND {whole} JOIN v v1 ON v1.k = b.answer || '/' || CAST(v0.s | b.bit AS VARCHAR) GROUP BY b.answer, b.tid"""


def strata(w: Workload, where: str, letters: str | None, most: int | None = None) -> str:
    """By target and vector of the others: coalitions and value weight, counted from all coalitions."""
    if letters is None:
        vec = "[bit_count(v0.s)]"
    else:
        vec = "[" + ", ".join(f"bit_count(v0.s & g.{c})" for c in letters) + "]"
    groups = ", ".join(f"CAST(coalesce(sum(bit) FILTER (WHERE substr(tid, 1, 1) = '{c}'), 0) AS BIGINT) AS {c}" for c in (letters or "clno"))
    return f"""{values_of_all(w, where, most)}, g AS (SELECT answer, {groups} FROM b GROUP BY answer)
SELECT b.answer, b.tid, array_to_string({vec}, ',') AS vec, CAST(count(*) AS DOUBLE) AS n_coal, round(sum({OMEGA['shapley']}), 9) AS w_value,
round(avg(v1.v - v0.v) / {w.unit}, 9) AS mean FROM b JOIN g ON g.answer = b.answer JOIN v v0 ON v0.answer = b.answer AND (v0.s & b.bit) = 0 JOIN v v1 ON v1.k = b.answer || '/' || CAST(v0.s | b.bit AS VARCHAR)
GROUP BY b.answer, b.tid, {vec}"""


def _hash(*parts: str) -> str:
    return "md5(concat_ws('|', " + ", ".join(parts) + "))"


def _unit(h: str) -> str:
    return f"(('0x' || substr({h}, 1, 13))::UBIGINT::DOUBLE / {16**13}.0)"


def sampled(w: Workload, where: str, method: str, budget: int, runs: int, seed: int = 42, digits: int = 6, most: int | None = None) -> str:
    """Plain sampling with the same md5 draws: each coalition is built from its members' hashes and looked up in `v`."""
    place = {"mc": f"'{seed}', 'mc', b.answer, b.tid, run, draw", "mc_permutation": f"'{seed}', 'order', b.answer, run, draw", "mc_multilinear": f"'{seed}', 'chance', b.answer, b.tid, run, draw"}[method]
    test = {
        "mc": f"substr({_hash(place, 'o.tid')}, 1, 1) < '8'",
        "mc_permutation": f"{_hash(place, 'o.tid')} < {_hash(place, 'b.tid')}",
        "mc_multilinear": f"{_unit(_hash(place, 'o.tid'))} < {_unit(_hash(place))}",
    }[method]
    weight = f"{OMEGA['shapley']} * (1::BIGINT << (v0.n - 1))" if method == "mc" else "1.0::DOUBLE"
    return f"""{values_of_all(w, where, most)},
d AS (SELECT b.answer, b.tid, b.bit, run, draw, CAST(coalesce(sum(o.bit) FILTER (WHERE {test}), 0) AS BIGINT) AS s
  FROM b CROSS JOIN range(0, {runs}) x(run) CROSS JOIN range(0, {budget}) y(draw) JOIN b o ON o.answer = b.answer AND o.tid <> b.tid GROUP BY b.answer, b.tid, b.bit, run, draw)
SELECT d.answer, d.tid, CAST(d.run AS INTEGER) AS run, round(avg({weight} * (v1.v - v0.v)) / {w.unit}, {digits}) AS estimate
FROM d JOIN v v0 ON v0.k = d.answer || '/' || CAST(d.s AS VARCHAR) JOIN v v1 ON v1.k = d.answer || '/' || CAST(d.s | d.bit AS VARCHAR) GROUP BY d.answer, d.tid, d.run"""


CONCERNED = "((m.need & y.bit) <> 0 OR EXISTS (SELECT 1 FROM am WHERE am.id = m.id AND (am.mask & y.bit) <> 0) OR EXISTS (SELECT 1 FROM nm WHERE nm.id = m.id AND (nm.mask & y.bit) <> 0))"


def strata_of(w: Workload, letters: str | None, most: int, prune: bool = False, where: str = "TRUE", target: str = "TRUE") -> str:
    """CTEs `st`, the settings with their pools, and `z`, their strata from counts alone: vec, size, n_coal, w_count,
    w_value, stratum, live."""
    kinds = [f"substr(o.tid, 1, 1) = '{c}'" for c in letters] if letters else ["TRUE"]
    width = len(kinds)
    binomials = [[math.comb(n, k) for k in range(n + 1)] for n in range(min(most, 62) + 1)]
    pools = ", ".join(f"list(struct_pack(tid := o.tid, bit := o.bit) ORDER BY o.tid) FILTER (WHERE {c}) AS p{k}, count(*) FILTER (WHERE {c}) AS c{k}, CAST(coalesce(sum(o.bit) FILTER (WHERE {c}), 0) AS BIGINT) AS g{k}" for k, c in enumerate(kinds))
    inner = "SELECT * FROM st"
    for k in range(width):
        inner = f"SELECT *, unnest(range(c{k} + 1)) AS s{k} FROM ({inner})"
    stratum = "s0" if width else "0"
    for k in range(1, width):
        stratum = f"({stratum}) * (c{k} + 1) + s{k}"
    coal = " * ".join(f"bin[c{k} + 1][s{k} + 1]::DOUBLE" for k in range(width))
    size = " + ".join(f"s{k}" for k in range(width))
    joins = " * ".join(f"(CASE WHEN c{k} > 0{f" AND substr(tid, 1, 1) <> '{letters[k]}'" if letters else ''} THEN s{k}::DOUBLE / c{k} ELSE 1.0::DOUBLE END)" for k in range(width))
    fits = " AND ".join(f"bit_count(m.need & ~y.bit & y.g{k}) <= y.s{k}" for k in range(width))
    live = f"EXISTS (SELECT 1 FROM m WHERE m.answer = y.answer AND {CONCERNED} AND {fits})" if prune else "TRUE"
    return f"""{masks(w, where, most)},
st AS MATERIALIZED (SELECT * FROM (SELECT t.answer, t.tid, t.bit, any_value(n.n) AS n, {pools} FROM b t JOIN n ON n.answer = t.answer JOIN b o ON o.answer = t.answer AND o.tid <> t.tid GROUP BY t.answer, t.tid, t.bit) WHERE {target}),
bins AS (SELECT {binomials} AS bin),
y AS MATERIALIZED (SELECT answer, tid, bit, n, {', '.join(f's{k}, g{k}' for k in range(width))}, [{', '.join(f's{k}' for k in range(width))}] AS vec, {stratum} AS stratum, {size} AS size, {coal} AS n_coal, 1.0 / (n * bin[n][{size} + 1]) * ({coal}) AS w_value, ({coal}) / pow(2.0, n - 1) AS w_count, {joins} AS joins FROM ({inner}) CROSS JOIN bins),
z AS MATERIALIZED (SELECT y.*, {live} AS live FROM y)"""


def _share(rule: str, sigma: str = "sigma") -> str:
    base = {"count": "w_count", "equal": "1.0::DOUBLE", "value": "w_value", "structure": "w_count * joins", "neyman_count": "w_count", "neyman_value": "w_value"}[rule]
    return f"{base} * {sigma}" if rule.startswith("neyman") else base


def allocated(table: str, share: str, budget: int, floor: int, rounding: str = "largest", by: str = "answer, tid, run") -> str:
    """The table with `m`: the floor, then shares of the rest, largest remainders first."""
    if rounding == "nearest":
        return f"SELECT *, CAST(fl + floor(exact + 0.5) AS INTEGER) AS m FROM ({_dealt(table, share, budget, floor, by)})"
    return f"""SELECT * EXCLUDE (base, nth, lft), CASE WHEN live THEN CAST(fl + base + (CASE WHEN nth <= lft THEN 1 ELSE 0 END) AS INTEGER) ELSE 0 END AS m FROM (
SELECT *, {budget} - sum(base + fl) OVER (PARTITION BY {by}) AS lft, row_number() OVER (PARTITION BY {by} ORDER BY live DESC, round(exact - base, 9) DESC, stratum) AS nth FROM (
SELECT *, floor(round(exact, 9)) AS base FROM ({_dealt(table, share, budget, floor, by)})))"""


def _dealt(table: str, share: str, budget: int, floor: int, by: str) -> str:
    return f"""SELECT * EXCLUDE (sh, tot, lives, ea), CASE WHEN live THEN ea ELSE 0 END AS fl, ({budget} - lives * ea) * CASE WHEN tot > 0 THEN sh / tot WHEN live THEN 1.0 / lives ELSE 0.0 END AS exact FROM (
SELECT *, CASE WHEN lives * {floor} <= {budget} THEN {floor} ELSE floor({budget} / greatest(lives, 1)) END AS ea FROM (
SELECT *, sum(sh) OVER (PARTITION BY {by}) AS tot, sum(CASE WHEN live THEN 1 ELSE 0 END) OVER (PARTITION BY {by}) AS lives FROM (
SELECT *, CASE WHEN live THEN greatest({share}, 0.0) ELSE 0.0 END AS sh FROM {table})))"""


def coverage(w: Workload, letters: str | None, most: int, rule: str, budget: int, floor: int, prune: bool = False) -> str:
    dealt = allocated("z", _share(rule), budget, floor, by="answer, tid")
    return f"""{strata_of(w, letters, most, prune)}, al AS ({dealt})
SELECT answer, tid, count(*) AS strata, CAST(sum(CASE WHEN live THEN 1 ELSE 0 END) AS BIGINT) AS live, CAST(sum(CASE WHEN m > 0 THEN 1 ELSE 0 END) AS BIGINT) AS drawn, CAST(sum(m) AS BIGINT) AS draws,
round(sum(CASE WHEN live AND m = 0 THEN w_value ELSE 0.0 END), 9) AS starved_weight FROM al GROUP BY answer, tid"""


def _cycle(w: Workload, width: int, cycle: int, seed: int = 42) -> str:
    """CTEs of one cycle: `d` the draws of the allocated strata `al`, their values, and `stats` of the strata."""
    c = f"_{cycle}"
    place = f"'{seed}|' || al.answer || '|' || al.tid || '|' || run || '|{cycle}|' || stratum || '|' || draw || '|'"
    picks = " + ".join(
        f"coalesce(list_sum(list_transform(list_slice(list_sort(list_transform(p{k}, lambda p: struct_pack(h := md5(place || p.tid), bit := p.bit))), 1, s{k}), lambda q: q.bit)), 0)" for k in range(width)
    )
    valued = _valued(w, f"asked{c}").replace("a AS (", f"a{c} AS (", 1).replace("v AS MATERIALIZED", f"v{c} AS MATERIALIZED", 1).replace("LEFT JOIN a ON", f"LEFT JOIN a{c} a ON")
    return f"""e{c} AS (SELECT al.answer, al.tid, al.run, al.stratum, al.bit, al.n, {', '.join(f'al.s{k}' for k in range(width))}, {', '.join(f'st.p{k}' for k in range(width))}, unnest(range(al.m)) AS draw FROM al{c} al JOIN st ON st.answer = al.answer AND st.tid = al.tid),
h{c} AS (SELECT al.*, {place} AS place FROM e{c} al),
d{c} AS MATERIALIZED (SELECT answer, tid, run, stratum, bit, n, CAST({picks} AS BIGINT) AS s FROM h{c}),
asked{c} AS MATERIALIZED (SELECT DISTINCT answer, n, s FROM (SELECT answer, n, s FROM d{c} UNION ALL SELECT answer, n, s | bit FROM d{c})),
{valued},
stats{c} AS MATERIALIZED (SELECT d.answer, d.tid, d.run, d.stratum, count(*) AS k, sum((v1.v - v0.v)::HUGEINT) AS s1, sum((v1.v - v0.v)::HUGEINT * (v1.v - v0.v)::HUGEINT) AS s2
  FROM d{c} d JOIN v{c} v0 ON v0.k = d.answer || '/' || CAST(d.s AS VARCHAR) JOIN v{c} v1 ON v1.k = d.answer || '/' || CAST(d.s | d.bit AS VARCHAR) GROUP BY d.answer, d.tid, d.run, d.stratum)"""


def stratified(
    w: Workload, letters: str | None, budget: int, runs: int = 1, most: int = 62, rule: str = "value", later: str = "neyman_value", cycles: int = 1, floor: int = 1,
    rounding: str = "largest", prune: bool = False, where: str = "TRUE", target: str = "TRUE", digits: int | None = 6,
) -> str:
    """Static (one cycle) and adaptive (two) stratified estimates with the same md5 draws: answer, tid, run, estimate, se,
    starved_weight, draws."""
    width = len(letters) if letters else 1
    ctes = f"{strata_of(w, letters, most, prune, where, target)},\nzr AS MATERIALIZED (SELECT z.*, run FROM z CROSS JOIN range({runs}) x(run)),\n"
    first = budget // cycles + (budget % cycles > 0)
    ctes += f"al_0 AS MATERIALIZED ({allocated('zr', _share(rule), first, floor, rounding)}),\n{_cycle(w, width, 0)}"
    stats = "stats_0"
    if cycles == 2:
        ctes += f""",
sg AS MATERIALIZED (SELECT zr.*, CASE WHEN n_coal <= 1 THEN 0.0 WHEN coalesce(tk, 0) >= 2 THEN sqrt(greatest(0.0, (tk * t2 - t1 * t1)::DOUBLE / (tk::DOUBLE * (tk - 1)))) ELSE coalesce(pooled, 0.0) END AS sigma
  FROM (SELECT zr.*, t.k AS tk, t.s1 AS t1, t.s2 AS t2, sqrt(greatest(0.0, (sum(t.k) OVER q * sum(t.s2) OVER q - (sum(t.s1) OVER q) * (sum(t.s1) OVER q))::DOUBLE / ((sum(t.k) OVER q)::DOUBLE * (sum(t.k) OVER q)::DOUBLE))) AS pooled
    FROM zr LEFT JOIN stats_0 t ON t.answer = zr.answer AND t.tid = zr.tid AND t.run = zr.run AND t.stratum = zr.stratum WINDOW q AS (PARTITION BY zr.answer, zr.tid, zr.run)) zr),
al_1 AS MATERIALIZED ({allocated('sg', _share(later), budget // 2, floor)}),
{_cycle(w, width, 1)},
stats AS MATERIALIZED (SELECT answer, tid, run, stratum, sum(k) AS k, sum(s1) AS s1, sum(s2) AS s2 FROM (SELECT * FROM stats_0 UNION ALL SELECT * FROM stats_1) GROUP BY answer, tid, run, stratum)"""
        stats = "stats"
    put = (lambda x, d: f"round({x}, {d})") if digits is not None else (lambda x, d: x)
    var = "CASE WHEN t.k > 1 THEN greatest(0.0, (t.k * t.s2 - t.s1 * t.s1)::DOUBLE / (t.k::DOUBLE * (t.k - 1))) ELSE 0.0 END"
    return f"""{ctes}
SELECT z.answer, z.tid, CAST(z.run AS INTEGER) AS run, {put(f"sum(coalesce(w_value * (t.s1::DOUBLE / t.k::DOUBLE), 0.0)) / {w.unit}", digits)} AS estimate,
{put(f"sqrt(sum(coalesce(w_value * w_value * ({var}) / t.k::DOUBLE, 0.0))) / {w.unit}", digits)} AS se, {put("sum(CASE WHEN live AND t.k IS NULL THEN w_value ELSE 0.0 END)", 9)} AS starved_weight, CAST(coalesce(sum(t.k), 0) AS BIGINT) AS draws
FROM zr z LEFT JOIN {stats} t ON t.answer = z.answer AND t.tid = z.tid AND t.run = z.run AND t.stratum = z.stratum GROUP BY z.answer, z.tid, z.run"""


def cache_hits(w: Workload, letters: str, budget: int, seed: int = 42) -> str:
    """All answers, whatever their size: a coalition is known by the numbers of its tuples, not by a mask, and binomials go up to
    the largest answer, as whole numbers of 128 bits (more than about 130 tuples are an error)."""
    width = len(letters)
    each = lambda text, sep=", ": sep.join(text.format(k=k, r=r) for k, r in enumerate(letters))
    inner, stratum = "SELECT * FROM st", "s0"
    for k in range(width):
        inner = f"SELECT *, unnest(range(c{k} + 1)) AS s{k} FROM ({inner})"
    for k in range(1, width):
        stratum = f"({stratum}) * (c{k} + 1) + s{k}"
    size = each("s{k}", " + ")
    picks = each("coalesce(list_transform(list_slice(list_sort(list_transform(p{k}, lambda p: struct_pack(h := md5(place || p.tid), no := p.no))), 1, s{k}), lambda q: q.no), CAST([] AS BIGINT[]))")
    return f"""WITH RECURSIVE {players(w)},
b AS MATERIALIZED (SELECT answer, tid, row_number() OVER (PARTITION BY answer ORDER BY tid) AS no FROM pl),
n AS MATERIALIZED (SELECT answer, count(*) AS n FROM pl GROUP BY answer),
st AS MATERIALIZED (SELECT t.answer, t.tid, t.no, any_value(n.n) AS n, {each("list(struct_pack(tid := o.tid, no := o.no)) FILTER (WHERE substr(o.tid, 1, 1) = '{r}') AS p{k}, count(*) FILTER (WHERE substr(o.tid, 1, 1) = '{r}') AS c{k}")}
  FROM b t JOIN n ON n.answer = t.answer LEFT JOIN b o ON o.answer = t.answer AND o.tid <> t.tid GROUP BY t.answer, t.tid, t.no),
pas(k, line) AS (SELECT 0, [1::HUGEINT] UNION ALL SELECT k + 1, list_transform(range(0, k + 2), lambda i: coalesce(line[i], 0::HUGEINT) + coalesce(line[i + 1], 0::HUGEINT)) FROM pas WHERE k < (SELECT max(n) FROM n)),
bins AS MATERIALIZED (SELECT list(line ORDER BY k) AS bin FROM pas),
z AS MATERIALIZED (SELECT answer, tid, {each('s{k}')}, {stratum} AS stratum, 1.0 / (n * bin[n][{size} + 1]) * ({each('bin[c{k} + 1][s{k} + 1]::DOUBLE', ' * ')}) AS w_value, TRUE AS live FROM ({inner}) CROSS JOIN bins),
al AS ({allocated('z', _share('value'), budget, 1, by='answer, tid')}),
e AS (SELECT al.*, st.no, {each('st.p{k}')}, unnest(range(al.m)) AS draw FROM al JOIN st ON st.answer = al.answer AND st.tid = al.tid),
h AS (SELECT e.*, '{seed}|' || answer || '|' || tid || '|0|0|' || stratum || '|' || draw || '|' AS place FROM e),
d AS MATERIALIZED (SELECT answer, no, list_sort(flatten([{picks}])) AS s FROM h),
asked AS MATERIALIZED (SELECT DISTINCT answer, s FROM (SELECT answer, s FROM d UNION ALL SELECT answer, list_sort(list_append(s, no)) AS s FROM d))
SELECT count(*) AS drawn, 2 * count(*) AS evaluations, (SELECT count(*) FROM asked) AS distinct_evaluations, 2 * count(*) - (SELECT count(*) FROM asked) AS hits FROM d"""


def pruning(w: Workload, letters: str, budget: int, most: int = 62) -> str:
    """Drawn coalitions, those in which no row of the target's finds what it needs, and how many of these it changes."""
    ctes = f"{strata_of(w, letters, most)},\nzr AS (SELECT z.*, run FROM z CROSS JOIN range(1) x(run)),\nal_0 AS ({allocated('zr', _share('value'), budget, 1)}),\n{_cycle(w, len(letters), 0)}"
    dead = f"NOT EXISTS (SELECT 1 FROM m WHERE m.answer = y.answer AND {CONCERNED} AND (m.need & (y.s | y.bit)) = m.need)"
    value = lambda s: f"y.answer || '/' || CAST({s} AS VARCHAR)"
    return f"""{ctes},
dd AS MATERIALIZED (SELECT answer, bit, s, count(*) AS k FROM d_0 GROUP BY answer, bit, s),
dz AS (SELECT y.k, {dead} AS dead, v1.v <> v0.v AS moves FROM dd y JOIN v_0 v0 ON v0.k = {value('y.s')} JOIN v_0 v1 ON v1.k = {value('y.s | y.bit')})
SELECT CAST(sum(k) AS BIGINT) AS drawn, CAST(sum(CASE WHEN dead THEN k ELSE 0 END) AS BIGINT) AS pruned, CAST(sum(CASE WHEN dead AND moves THEN k ELSE 0 END) AS BIGINT) AS wrong FROM dz"""


def given(w: Workload, letters: str) -> Workload:
    """The workload for DuckDB where tuples of some relations are always there; for rows without alternatives, whose
    blockers have other tuples too."""
    left = f"lambda t: substr(t, 1, 1) NOT IN ({', '.join(repr(c) for c in letters)})"
    blockers = f", list_transform(none_of, lambda s: list_filter(s, {left})) AS none_of" if "AS none_of" in w.rows else ""
    return replace(w, rows=f"SELECT answer, x, list_filter(need, {left}) AS need{blockers} FROM ({w.rows}) q")


def totals(w: Workload, budget: int, seed: int = 42, digits: int = 8) -> str:
    """Sampling on rows without alternatives or blockers, with the same draws: by row and draw how many needed tuples are
    gone, and so what holds with and without each of them."""
    place = f"'{seed}', 'totals', pl.answer, draw"
    value = {"ratio": f"CASE WHEN {{x}} <> 0 THEN CAST(floor(({{y}})::DOUBLE / ({{x}})::DOUBLE * {w.unit}) AS BIGINT) ELSE 0 END", "exists": "CASE WHEN {x} > 0 THEN 1 ELSE 0 END"}.get(w.agg, f"CASE WHEN {{x}} > {w.above} THEN {{x}} ELSE 0 END")
    of = lambda side: value.format(x=f"(b.x + e.x{side})", y=f"(b.y + e.y{side})")
    held = "CASE WHEN gone = 0 THEN {0} ELSE 0 END"
    there = "CASE WHEN gone = 0 OR (gone = 1 AND NOT here) THEN {0} ELSE 0 END"
    return f"""WITH {players(w)},
mem AS MATERIALIZED (SELECT pl.answer, pl.tid, draw, {_unit(_hash(place, 'pl.tid'))} < {_unit(_hash(place))} AS here FROM pl CROSS JOIN range(0, {budget}) k(draw)),
ur AS MATERIALIZED (SELECT answer, id, x, part, unnest(need) AS tid FROM r),
rk AS MATERIALIZED (SELECT u.answer, u.id, mem.draw, any_value(u.x) AS x, any_value(u.part) AS part, count(*) FILTER (WHERE NOT here) AS gone FROM ur u JOIN mem ON mem.answer = u.answer AND mem.tid = u.tid GROUP BY u.answer, u.id, mem.draw),
base AS (SELECT answer, draw, sum({held.format('x')}) AS x, sum({held.format('part')}) AS y FROM rk GROUP BY answer, draw),
mine AS (SELECT u.answer, u.tid, rk.draw, sum({there.format('rk.x')}) - sum({held.format('rk.x')}) AS x1, -sum({held.format('rk.x')}) AS x0, sum({there.format('rk.part')}) - sum({held.format('rk.part')}) AS y1, -sum({held.format('rk.part')}) AS y0
  FROM ur u JOIN rk ON rk.id = u.id JOIN mem ON mem.answer = u.answer AND mem.tid = u.tid AND mem.draw = rk.draw GROUP BY u.answer, u.tid, rk.draw)
SELECT e.answer, e.tid, round(avg(({of(1)}) - ({of(0)})) / {w.unit}, {digits}) AS estimate, count(*) AS draws
FROM mine e JOIN base b ON b.answer = e.answer AND b.draw = e.draw GROUP BY e.answer, e.tid"""


def errors(w: Workload, estimates: dict[str, str], budget: int, most: int) -> str:
    """Errors of estimates by method (SQL of answer, tid, run, estimate, starved_weight, draws) against enumeration."""
    each = " UNION ALL ".join(f"SELECT '{name}' AS method, answer, tid, run, estimate, starved_weight, draws FROM ({sql})" for name, sql in estimates.items())
    return f"""WITH est AS MATERIALIZED ({each}), ex AS MATERIALIZED ({by_subset(w, digits=15, most=most)})
SELECT method, {budget} AS budget, est.answer, est.tid, count(*) AS runs, round(any_value(value), 6) AS exact, round(avg(estimate), 6) AS mean_estimate,
round(avg(CASE WHEN value <> 0 THEN abs(estimate - value) / abs(value) END), 6) AS mre, round(avg(abs(estimate - value)), 6) AS mean_abs_error, round(avg(estimate - value), 6) + 0.0 AS bias,
round(var_samp(estimate), 6) AS variance, round(sqrt(avg((estimate - value) * (estimate - value))), 6) AS rmse, round(avg(starved_weight), 6) AS starved_weight, avg(draws) AS draws
FROM est JOIN ex ON ex.answer = est.answer AND ex.tid = est.tid GROUP BY method, est.answer, est.tid"""


def view_size(w: Workload, most: int) -> str:
    return f"WITH {players(w, 'TRUE', most)} SELECT (SELECT count(DISTINCT answer) FROM r) AS answers, (SELECT count(*) FROM r) AS rows, (SELECT count(*) FROM pl) AS players"


def first_sizes(w: Workload, digits: int = 6) -> str:
    """All weight on the coalitions of none or one of four others, half each."""
    inner = by_subset(w, most=5).replace(OMEGA["shapley"], "CASE bit_count(v0.s) WHEN 0 THEN 0.5 WHEN 1 THEN 0.125 ELSE 0.0 END")
    return f"WITH a AS ({inner}) SELECT a.* FROM a WHERE (SELECT count(*) FROM a b WHERE b.answer = a.answer) = 5"
