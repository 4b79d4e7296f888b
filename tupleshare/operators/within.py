"""Sampling within the row of a setting or an answer: strata, shares, draws and their sums never leave the task.

The same draws and sums as by tables (`estimate.draw`, `strata.allocate`), without a row for each stratum or draw and
without a shuffle. What can't matter is not hashed: a relation of which a vector has none or all, relations that no row of
the target mentions (sums only), and strata in which no row of the target can find what it needs, whose marginals are 0.
"""

from __future__ import annotations

import math
from collections import Counter, OrderedDict
from collections.abc import Callable, Iterator
from decimal import ROUND_HALF_UP, Decimal
from itertools import combinations, product
from typing import NamedTuple

try:
    from _md5 import md5  # without the detours of a general library of digests
except ImportError:
    from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.semivalue import MAX_PLAYERS, Semivalue
from ..plans.workloads import Workload
from .lineage import n_parts

#: Shapes of settings whose strata and shares a task remembers.
SHAPES = 4000
#: Coalitions for which a form of game remembers the rows that change.
CHANGES = 4096
VIEW = ("need", "x", "any_of", "none_of")


class Strata(NamedTuple):
    """In order of number, by column. inside: of coarse strata the vectors with their value weights, else None."""

    number: list[int]
    vec: list[tuple[int, ...]]
    n_coal: list[float]
    w_count: list[float]
    w_value: list[float]
    joins: list[float]
    inside: list[list[tuple[tuple[int, ...], float]]] | None = None


def round9(x: float) -> float:
    """To nine digits, halves up, as the engine rounds the shortest text of a number."""
    y = x * 1e9
    if abs(y) < 1e15 and abs(y - math.floor(y) - 0.5) > 1e-3:
        return math.floor(y + 0.5) / 1e9
    return float(Decimal(repr(x)).quantize(Decimal("1e-9"), ROUND_HALF_UP))


def weights_of(semivalue: Semivalue) -> Callable[[int], list]:
    """By number of players the weights by size; fractions beyond the players of one word, where floats might not hold them."""
    table = semivalue.table()
    return lambda n: table[n] if n < len(table) else [semivalue.weight(n, k) for k in range(n)]


def strata_of(n: int, c: tuple[int, ...], own: tuple[bool, ...], omega: list) -> Strata:
    """Every vector of counts, as `strata.vectors` has them; equal for all settings of a shape."""
    out = Strata([], [], [], [], [], [])
    for number, vec in enumerate(product(*(range(k + 1) for k in c))):
        if n <= MAX_PLAYERS:
            coal = math.prod(float(math.comb(k, s)) for k, s in zip(c, vec, strict=True))
            part, weight = coal / 2.0 ** (n - 1), omega[sum(vec)] * coal
        else:
            whole = math.prod(math.comb(k, s) for k, s in zip(c, vec, strict=True))
            coal, part, weight = float(whole) if whole < 2**1000 else math.inf, whole / 2 ** (n - 1), float(omega[sum(vec)] * whole)
        out.number.append(number)
        out.vec.append(vec)
        out.n_coal.append(coal)
        out.w_count.append(part)
        out.w_value.append(weight)
        out.joins.append(math.prod((s / k if k and not mine else 1.0) for k, s, mine in zip(c, vec, own, strict=True)))
    return out


def cells_of(fine: Strata, c: tuple[int, ...], live: tuple[bool, ...], bins: int) -> Strata:
    """Products of bins of counts, as `estimate.cells` has them, of the live vectors."""
    groups: dict[int, list[int]] = {}
    for i, vec in enumerate(fine.vec):
        if live[i]:
            number = 0
            for s, k in zip(vec, c, strict=True):
                number = number * 1000 + min(bins - 1, s * bins // (k + 1))
            groups.setdefault(number, []).append(i)
    out = Strata([], [], [], [], [], [], [])
    for number, at in sorted(groups.items()):
        out.number.append(number)
        out.vec.append(())
        out.n_coal.append(sum(fine.n_coal[i] for i in at))
        out.w_count.append(sum(fine.w_count[i] for i in at))
        out.w_value.append(sum(fine.w_value[i] for i in at))
        out.joins.append(sum(fine.w_count[i] * fine.joins[i] for i in at) / (out.w_count[-1] or 1.0))
        out.inside.append([(fine.vec[i], fine.w_value[i]) for i in at])
    return out


def shares(strata: Strata, rule: str, sigma: list[float] | None = None) -> list[float]:
    if rule == "equal":
        return [1.0] * len(strata.number)
    base = strata.w_value if rule in ("value", "neyman_value") else strata.w_count
    by = {"structure": strata.joins}.get(rule, sigma if rule.startswith("neyman") else None)
    return [a * b for a, b in zip(base, by, strict=True)] if by is not None else base


def allocate(share: list[float], live: tuple[bool, ...], budget: int, floor: int, rounding: str) -> list[int]:
    """Draws of each stratum, as `strata.allocate` deals them; strata in order of number."""
    share = [max(s, 0.0) if alive else 0.0 for s, alive in zip(share, live, strict=True)]
    total, lives = sum(share), sum(live)
    each = floor if lives * floor <= budget else budget // max(lives, 1)
    rest = budget - lives * each
    exact = [rest * (s / total if total > 0 else 1.0 / lives if alive else 0.0) for s, alive in zip(share, live, strict=True)]
    if rounding == "nearest":
        return [(each if alive else 0) + math.floor(x + 0.5) for x, alive in zip(exact, live, strict=True)]
    out = [math.floor(round9(x)) if x else 0 for x in exact]
    left = budget - sum(out) - lives * each
    if left > 0:  # shares of nothing come last
        first = sorted([(-r, i) for i, x in enumerate(exact) if x and (r := round9(x - out[i])) > 0 and live[i]])
        if len(first) >= left:
            for _, i in first[:left]:
                out[i] += 1
            return [m + each if alive else 0 for m, alive in zip(out, live, strict=True)]
    order = sorted(range(len(out)), key=lambda i: (not live[i], -round9(exact[i] - out[i]), i)) if left > 0 else []
    for i in order[:left]:
        out[i] += 1
    return [m + each if alive else 0 for m, alive in zip(out, live, strict=True)]


class Form:
    """What games whose players and rows stand alike have in common, whatever their ids and measures: built once."""

    def __init__(self, bit: int, pools: tuple[tuple[int, ...], ...], sets: tuple[tuple, ...], agg: str):
        self.bit, self.sets, self.pools = bit, sets, pools
        self.masks = [sum(bits) for bits in pools]
        part = lambda m: m & bit
        self.mine = [i for i, r in enumerate(sets) if r[0] & bit or any(map(part, r[1])) or any(map(part, r[2]))]
        self.rows = self.mine if agg == "sum" else range(len(sets))  # of sums only these rows change
        self.relevant = 0
        for i in self.rows:
            for m in (sets[i][0], *sets[i][1], *sets[i][2]):
                self.relevant |= m
        self.asked = {tuple((sets[i][0] & ~bit & m).bit_count() for m in self.masks) for i in self.mine}
        self.changed: dict[int, list[tuple[int, int]]] = {}
        self.places: dict[tuple[int, ...], tuple | None] = {}

    def dead(self, vec: tuple[int, ...]) -> bool:
        """Whether in no coalition of the vector a row of the target finds what it needs."""
        return not any(all(a <= s for a, s in zip(asked, vec, strict=True)) for asked in self.asked)

    def can_change(self, mask: int) -> bool:
        joined = mask | self.bit
        return any(joined & self.sets[i][0] == self.sets[i][0] for i in self.mine)

    def changes(self, mask: int) -> list[tuple[int, int]]:
        """The rows that the target brings into being (1) or ends (-1) by joining."""
        out = self.changed.get(mask)
        if out is None:
            if len(self.changed) >= CHANGES:
                self.changed.clear()
            sign = lambda i: stands(*self.sets[i], mask | self.bit) - stands(*self.sets[i], mask)
            out = self.changed[mask] = [(i, d) for i in self.mine if (d := sign(i))]
        return out

    def fixed(self, vec: tuple[int, ...], relevant: int = -1) -> tuple[int, list[tuple[int, int]]]:
        """Of a vector the part that all its coalitions share, and the pools with their counts that are left to chance."""
        mask, open_pools = 0, []
        for k, s in enumerate(vec):
            if s >= len(self.pools[k]):
                mask |= self.masks[k]
            elif s and self.masks[k] & relevant:
                open_pools.append((k, s))
        return mask, open_pools

    def place(self, vec: tuple[int, ...]) -> tuple[int, list[tuple[int, int]]] | None:
        """As `fixed`, of the pools that matter; None for a vector that is dead."""
        if vec not in self.places:
            self.places[vec] = None if self.dead(vec) else self.fixed(vec, self.relevant)
        return self.places[vec]


class Game:
    """One target of one answer: who else plays, in pools, and the rows that the target has a part in."""

    def __init__(self, form: Form, tids: list[list[bytes]], view: list[tuple], workload: Workload):
        self.form, self.tids, self.view, self.above, self.agg = form, tids, view, workload.above, workload.agg
        self.deltas: dict[int, int] = {}

    def delta(self, mask: int) -> int:
        d = self.deltas.get(mask)
        if d is None:
            if self.agg == "sum":
                d = sum([self.view[i][1] * sign for i, sign in self.form.changes(mask)])
            else:
                d = value(self.view, mask | self.form.bit, self.agg, self.above) - value(self.view, mask, self.agg, self.above)
            self.deltas[mask] = d
        return d

    def pick(self, k: int, s: int, place: bytes) -> int:
        """A uniform subset of a pool: those with the least hashes."""
        bits = self.form.pools[k]
        hashed = [(md5(place + t).digest(), b) for t, b in zip(self.tids[k], bits, strict=True)]
        if s == 1:
            return min(hashed)[1]
        if s == len(bits) - 1:
            return self.form.masks[k] - max(hashed)[1]
        hashed.sort()
        return sum([b for _, b in hashed[:s]])


def stands(need: int, any_of: tuple, none_of: tuple, mask: int) -> int:
    """1 if the coalition has what a row needs, an alternative, and no blocker."""
    return int(mask & need == need and (not any_of or any(mask & m == m for m in any_of)) and not any(mask & m == m for m in none_of))


def value(rows: list[tuple], mask: int, agg: str, above: int) -> int:
    """Of a coalition, as `evaluate.value` has it."""
    total = 0
    for need, x, any_of, none_of in rows:
        if mask & need == need and (not any_of or any(mask & m == m for m in any_of)) and not any(mask & m == m for m in none_of):
            total += x
    if agg == "exists":
        return int(total > 0)
    return 0 if agg == "having" and total <= above else total


def _lists(column: pa.Array) -> list[list]:
    at, flat = column.offsets.to_pylist(), column.flatten().to_pylist()  # flatten heeds the slice, offsets count from the whole
    return [flat[a - at[0] : b - at[0]] for a, b in zip(at, at[1:])]


def _nested(column: pa.Array) -> list[list]:
    return column.to_pylist() if len(column.flatten()) else [()] * len(column)


def _views(batch: pa.RecordBatch) -> list[list[tuple]]:
    """By row of the batch the view's rows: need, x, any_of, none_of."""
    need, x = _lists(batch.column("need")), _lists(batch.column("x"))
    any_of, none_of = _nested(batch.column("any_of")), _nested(batch.column("none_of"))
    return [list(zip(m, y, a or [()] * len(m), b or [()] * len(m), strict=True)) for m, y, a, b in zip(need, x, any_of, none_of, strict=True)]


def _sets(name: str):
    """An empty list where no row of the view has such sets, so that they are rarely moved."""
    every = F.transform("view", lambda r: r[name])
    return F.when(F.exists(every, lambda s: F.size(s) > 0), every).otherwise(F.array().cast("array<array<bigint>>"))


Run = Callable[[str, str, int, tuple, tuple, Game], Iterator[tuple]]


def _out(rows: list[tuple], names: list[str], types: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict(dict(zip(names, map(list, zip(*rows, strict=True)) if rows else [[] for _ in names], strict=True)), schema=types)


def _sets_of(view: list[tuple]) -> tuple[tuple, ...]:
    return tuple((need, tuple(a), tuple(b)) for need, _, a, b in view)


def games(pooled: DataFrame, workload: Workload, run: Run, schema: str, names: list[str], answers: int = 1000) -> DataFrame:
    """Calls `run` with (answer, tid, n, c, own, game) of every setting; its tuples become rows of the schema."""
    flat = F.flatten("pools")
    columns = pooled.select("answer", "tid", "bit", "n", "c", "own", flat["tid"].alias("tids"), flat["bit"].alias("bits"), F.col("view.need").alias("need"), F.col("view.x").alias("x"), _sets("any_of").alias("any_of"), _sets("none_of").alias("none_of"))
    types, agg = _arrow(schema), workload.agg

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forms = Remembered()
        for whole in batches:
            for lo in range(0, whole.num_rows, answers):
                b = whole.slice(lo, answers)
                plain = [b.column(c).to_pylist() for c in ("answer", "tid", "bit", "n")]
                out = []
                for answer, tid, bit, n, c, own, tids, bits, view in zip(*plain, *map(_lists, (b.column("c"), b.column("own"), b.column("tids"), b.column("bits"))), _views(b), strict=True):
                    groups, members, at = [], [], 0
                    for k in c:
                        groups.append(tuple(bits[at : at + k]))
                        members.append([t.encode() for t in tids[at : at + k]])
                        at += k
                    form = forms.of(Form, bit, tuple(groups), _sets_of(view), agg)
                    out.extend(run(answer, tid, n, tuple(c), tuple(own), Game(form, members, view, workload)))
                yield _out(out, names, types)

    return columns.mapInArrow(work, schema)


def of_answers(view: DataFrame, workload: Workload, each: Callable[..., Iterator[tuple]], schema: str, names: list[str], answers: int = 200, more: tuple[str, ...] = ()) -> DataFrame:
    """Calls `each` with (answer, its players, its rows) of every answer of a compiled view, and what it has in the columns
    `more`; its tuples become rows."""
    large = "listed" in view.columns
    columns = view.select("answer", F.col("players.rel").alias("rels"), F.col("players.tid").alias("tids"), F.col("players.bit").alias("bits"), F.col("view.need").alias("need"), F.col("view.x").alias("x"), _sets("any_of").alias("any_of"), _sets("none_of").alias("none_of"), *(["listed"] if large else []), *more)
    types = _arrow(schema)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, answers):
                b = whole.slice(lo, answers)
                out = []
                listed = b.column("listed").to_pylist() if large else [None] * b.num_rows
                for answer, rels, tids, bits, rows, by_ids, *rest in zip(b.column("answer").to_pylist(), *(_lists(b.column(c)) for c in ("rels", "tids", "bits")), _views(b), listed, *(b.column(c).to_pylist() for c in more), strict=True):
                    players, rows = numbered(by_ids) if by_ids else (list(zip(rels, tids, bits, strict=True)), rows)
                    out.extend(each(answer, players, rows, *rest))
                yield _out(out, names, types)

    return columns.mapInArrow(work, schema)


def numbered(listed: list[dict]) -> tuple[list[tuple[str, str, int]], list[tuple]]:
    """Players and rows of an answer whose rows have ids, as a compiled view has them, with masks of any width."""
    sets = [(r["need"], *r["any_of"], *r["none_of"]) for r in listed]
    bit = {t: 1 << i for i, t in enumerate(sorted({t for row in sets for s in row for t in s}))}
    mask = lambda s: sum(bit[t] for t in set(s))
    return [(t[:1], t, b) for t, b in bit.items()], [(mask(r["need"]), r["x"], tuple(map(mask, r["any_of"])), tuple(map(mask, r["none_of"]))) for r in listed]


def targets_of(letters: str | None, workload: Workload) -> Callable[[str, list[tuple[str, str, int]], list[tuple]], Iterator[tuple]]:
    """Of an answer (tid, n, c, own, game) of every player, with the pools that `strata.pools` makes."""
    forms, kinds, agg = Remembered(), letters or "*", workload.agg

    def targets(answer: str, players: list[tuple[str, str, int]], view: list[tuple]) -> Iterator[tuple]:
        sets, n = _sets_of(view), len(players)
        pools = [[(t.encode(), b) for r, t, b in players if letters is None or r == k] for k in kinds]
        for rel, tid, bit in players:
            others = [[p for p in pool if p[1] != bit] for pool in pools]
            form = forms.of(Form, bit, tuple([tuple([b for _, b in pool]) for pool in others]), sets, agg)
            own = (False,) if letters is None else tuple([k == rel for k in kinds])
            yield tid, n, tuple(map(len, others)), own, Game(form, [[t for t, _ in pool] for pool in others], view, workload)

    return targets


def _arrow(schema: str) -> pa.Schema:
    kinds = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64()}
    return pa.schema([(name, kinds[kind]) for name, kind in (f.split() for f in schema.split(", "))])


class Remembered(OrderedDict):
    """The latest results of a function of hashable arguments."""

    def of(self, fn: Callable, *key):
        if key not in self:
            if len(self) >= SHAPES:
                self.popitem(last=False)
            self[key] = fn(*key)
        return self[key]


def drawn(game: Game, strata: Strata, m: list[int], place: str, w_place: str) -> list[tuple[int, int, int] | None]:
    """By stratum the number, the sum and the sum of squares of the marginals of its draws; None without a draw."""
    out: list[tuple[int, int, int] | None] = []
    for i, k in enumerate(m):
        if not k:
            out.append(None)
            continue
        here, number, s1, s2 = strata.vec[i], strata.number[i], 0, 0
        start = f"{place}{number}|"
        if strata.inside is None:
            known = game.form.place(here)
            if known is not None:
                mask, chance = known
                if not chance:
                    d = game.delta(mask)
                    s1, s2 = k * d, k * d * d
                else:
                    for draw in range(k):
                        at, coalition = f"{start}{draw}|".encode(), mask
                        for pool, s in chance:
                            coalition |= game.pick(pool, s, at)
                        d = game.delta(coalition)
                        s1 += d
                        s2 += d * d
        else:
            for draw in range(k):
                left = int(md5(f"{w_place}{number}|{draw}".encode()).hexdigest()[:13], 16) / float(16**13) * strata.w_value[i]
                vec = strata.inside[i][0][0]
                for v, w in strata.inside[i]:
                    if left < 0:
                        break
                    vec = v
                    left -= w
                known = game.form.place(vec)
                if known is None:
                    continue
                coalition, chance = known
                if chance:
                    at = f"{start}{draw}|".encode()
                    for pool, s in chance:
                        coalition |= game.pick(pool, s, at)
                d = game.delta(coalition)
                s1 += d
                s2 += d * d
        out.append((k, s1, s2))
    return out


def _spread(k: int, s1: int, s2: int) -> float:
    return max(0.0, float(k * s2 - s1 * s1))


def sigmas(strata: Strata, stats: list[tuple[int, int, int] | None]) -> list[float]:
    """As `estimate._sigma`: with under two draws the deviation of all the setting's draws."""
    k, s1, s2 = (sum(t[j] for t in stats if t) for j in range(3))
    pooled = math.sqrt(_spread(k, s1, s2) / (float(k) * k)) if k else 0.0
    return [0.0 if n <= 1 else math.sqrt(_spread(*t) / (float(t[0]) * (t[0] - 1))) if t and t[0] >= 2 else pooled for n, t in zip(strata.n_coal, stats, strict=True)]


def combined(strata: Strata, live: tuple[bool, ...], stats: list[tuple[int, int, int] | None], unit: float) -> tuple[float, float, float, int]:
    """As `estimate.combine`: estimate, standard error, weight of live strata without a draw, draws."""
    estimate = error = starved = 0.0
    draws = 0
    for w, alive, t in zip(strata.w_value, live, stats, strict=True):
        if t is None:
            starved += w if alive else 0.0
            continue
        k, s1, s2 = t
        draws += k
        if s1 or s2:
            estimate += w * (float(s1) / k)
            if k > 1:
                error += w * w * (_spread(k, s1, s2) / (float(k) * (k - 1))) / k
    return estimate / unit, math.sqrt(error) / unit, starved, draws


def stratified(pooled: DataFrame, workload: Workload, plan, runs: int, semivalue: Semivalue, cycles: int, view: DataFrame | None = None) -> DataFrame:
    """What `estimate.stratified` returns, each setting in its own row; with the view that all the settings are of, all
    settings of an answer in the answer's row."""
    omega, unit = weights_of(semivalue), workload.unit
    known = Remembered()
    budgets = [plan.budget // cycles + (c < plan.budget % cycles) for c in range(cycles)]

    def shape(n: int, c: tuple, own: tuple, live: tuple | None) -> tuple[Strata, tuple, list[int]]:
        """Strata, which are live, and the shares of the first cycle."""
        strata = known.of(strata_of_shape, n, c, own)
        live = live or (True,) * len(strata.number)
        if plan.bins:
            strata = cells_of(strata, c, live, plan.bins)
            live = (True,) * len(strata.number)
        return strata, live, allocate(shares(strata, plan.rule), live, budgets[0], plan.floor, plan.rounding)

    def strata_of_shape(n: int, c: tuple, own: tuple) -> Strata:
        return strata_of(n, c, own, omega(n))

    def run(answer: str, tid: str, n: int, c: tuple, own: tuple, game: Game) -> Iterator[tuple]:
        live = tuple(not game.form.dead(v) for v in known.of(strata_of_shape, n, c, own).vec) if plan.prune else None
        strata, live, first = known.of(shape, n, c, own, live)
        for r in range(runs):
            stats, each = None, []
            for cycle in range(cycles):
                m = first if stats is None else allocate(shares(strata, plan.later, sigmas(strata, stats)), live, budgets[cycle], plan.floor, "largest")
                counted = [n_coal <= k for n_coal, k in zip(strata.n_coal, m, strict=True)] if plan.census and cycles == 1 else None
                asked = [0 if out else k for k, out in zip(m, counted, strict=True)] if counted else m  # what is counted out needs no draws
                new = drawn(game, strata, asked, f"{plan.seed}|{answer}|{tid}|{r}|{cycle}|", f"{plan.seed}|vec|{answer}|{tid}|{r}|{cycle}|")
                if counted:
                    new = [census(game, strata.vec[i]) if out and m[i] else t for i, (t, out) in enumerate(zip(new, counted, strict=True))]
                each.append(new)
                stats = new if stats is None else [tuple(map(sum, zip(a, b, strict=True))) if a and b else a or b for a, b in zip(stats, new, strict=True)]
            if plan.pooling == "cycle_mean":
                parts = [combined(strata, live, s, unit) for s in each]
                yield answer, tid, r, sum(p[0] for p in parts) / cycles, math.sqrt(sum(p[1] * p[1] for p in parts)) / cycles, sum(p[2] for p in parts) / cycles, sum(p[3] for p in parts)
            else:
                yield answer, tid, r, *combined(strata, live, stats, unit)

    names = ["answer", "tid", "run", "estimate", "se", "starved_weight", "draws"]
    schema = "answer string, tid string, run int, estimate double, se double, starved_weight double, draws long"
    if view is None:
        return games(pooled, workload, run, schema, names)
    targets = targets_of(plan.letters, workload)

    def each(answer: str, players: list[tuple[str, str, int]], rows: list[tuple]) -> Iterator[tuple]:
        for tid, n, c, own, game in targets(answer, players, rows):
            yield from run(answer, tid, n, c, own, game)

    return of_answers(view, workload, each, schema, names)


def census(game: Game, vec: tuple[int, ...]) -> tuple[int, int, int]:
    """Of all coalitions of a vector the number and the sum of the marginals; counted out, so without spread."""
    k = s1 = 0
    for parts in product(*(combinations(bits, s) for bits, s in zip(game.form.pools, vec, strict=True))):
        k += 1
        s1 += game.delta(sum(map(sum, parts)))
    return k, s1, 0


def static_draws(plan, semivalue: Semivalue) -> Callable[..., Iterator[tuple[int, int]]]:
    """Of a target (answer, tid, n, c, own, game) the coalitions that the first cycle draws, and how often each. Pools that
    have nothing of `relevant` are not drawn from."""
    known, omega = Remembered(), weights_of(semivalue)

    def shape(n: int, c: tuple, own: tuple) -> list[tuple]:
        """Of strata with draws the number, the draws, the pools that are wholly in, and those left to chance with their counts."""
        strata = strata_of(n, c, own, omega(n))
        m = allocate(shares(strata, plan.rule), (True,) * len(strata.number), plan.budget, plan.floor, plan.rounding)
        pools = [([i for i, s in enumerate(vec) if s >= c[i]], [(i, s) for i, s in enumerate(vec) if 0 < s < c[i]]) for vec in strata.vec]
        return [(number, k, *at) for number, k, at in zip(strata.number, m, pools, strict=True) if k]

    def draws(answer: str, tid: str, n: int, c: tuple, own: tuple, game: Game, relevant: int = -1) -> Iterator[tuple[int, int]]:
        masks, pick = game.form.masks, game.pick
        for number, k, inside, chance in known.of(shape, n, c, own):
            mask = 0
            for i in inside:
                mask |= masks[i]
            if relevant != -1:
                chance = [at for at in chance if masks[at[0]] & relevant]
            if not chance:
                yield mask, k
                continue
            start = f"{plan.seed}|{answer}|{tid}|0|0|{number}|"
            if k == 1:
                place = f"{start}0|".encode()
                for pool, s in chance:
                    mask |= pick(pool, s, place)
                yield mask, 1
                continue
            drawn_masks: dict[int, int] = {}
            for draw in range(k):
                place, coalition = f"{start}{draw}|".encode(), mask
                for pool, s in chance:
                    coalition |= pick(pool, s, place)
                drawn_masks[coalition] = drawn_masks.get(coalition, 0) + 1
            yield from drawn_masks.items()

    return draws


def coalitions_of(view: DataFrame, workload: Workload, plan, semivalue: Semivalue, of: Callable[[Game, int, int, set], tuple], names: list[str], matter: bool) -> DataFrame:
    """A row for each answer: the sums of what `of` says of every drawn coalition (game, mask, times drawn, what the answer
    has seen so far). With `matter` pools that can't change the target's marginal are not drawn from."""
    targets, draws = targets_of(plan.letters, workload), static_draws(plan, semivalue)

    def each(answer: str, players: list[tuple[str, str, int]], rows: list[tuple]) -> Iterator[tuple]:
        sums, seen = [0] * len(names), set()
        for tid, n, c, own, game in targets(answer, players, rows):
            for coalition, times in draws(answer, tid, n, c, own, game, game.form.relevant if matter else -1):
                sums = list(map(int.__add__, sums, of(game, coalition, times, seen)))
        yield (answer, *sums)

    return of_answers(view, workload, each, ", ".join(["answer string", *(f"{n} long" for n in names)]), ["answer", *names])


def cache_hits(view: DataFrame, workload: Workload, plan, semivalue: Semivalue) -> DataFrame:
    """As `evaluate.cache_hits` of the static draws: a coalition of an answer is told from others within its row."""

    def of(game: Game, mask: int, times: int, seen: set) -> tuple:
        before = len(seen)
        seen.update((mask, mask | game.form.bit))
        return times, len(seen) - before

    drawn, distinct = F.sum("drawn"), F.coalesce(F.sum("found"), F.lit(0).cast("long"))
    counted = coalitions_of(view, workload, plan, semivalue, of, ["drawn", "found"], False)
    return counted.agg(drawn.alias("drawn"), (2 * drawn).cast("long").alias("evaluations"), distinct.alias("distinct_evaluations"), (2 * drawn - distinct).cast("long").alias("hits"))


def pruning(view: DataFrame, workload: Workload, plan, semivalue: Semivalue) -> DataFrame:
    """As `evaluate.pruning` of the static draws; the marginal of every drawn coalition is taken, of pruned ones too."""

    def of(game: Game, mask: int, times: int, seen: set) -> tuple:
        dead = not game.form.can_change(mask)
        return times, dead * times, (dead and game.delta(mask) != 0) * times

    counted = coalitions_of(view, workload, plan, semivalue, of, ["drawn", "pruned", "wrong"], True)
    return counted.agg(F.coalesce(F.sum("drawn"), F.lit(0).cast("long")).alias("drawn"), F.sum("pruned").alias("pruned"), F.sum("wrong").alias("wrong"))


def joined_values(rows: list[dict], holders: dict[str, np.ndarray], n: int, workload: Workload) -> np.ndarray:
    """As `evaluate.tagged`, of the n coalitions of an answer: rows of the un-aggregated query, whose tuples have ids and no
    bits, meet by these ids the coalitions that hold them. holders: by tuple whether each coalition holds it."""
    nobody = np.zeros(n, bool)

    def whole(tids: list[str]) -> np.ndarray:
        held = np.ones(n, bool)
        for t in tids:
            held &= holders.get(t, nobody)
        return held

    total = np.zeros(n, np.int64)
    for r in rows:
        there = whole(r["need"])
        if r["any_of"]:
            there &= np.logical_or.reduce([whole(s) for s in r["any_of"]])
        for s in r["none_of"]:
            there &= ~whole(s)
        total += there * np.int64(r["x"] or 0)
    return finish(total, workload)


def tagged_differences(view: DataFrame, rows: DataFrame, workload: Workload, plan, semivalue: Semivalue) -> DataFrame:
    """(compared, different): the static draws of all tuples of the view's answers, and those whose value by joins with
    `rows`, as `lineage.rows_of` has them, differs from that by masks. The row of an answer meets the list of its rows; its
    draws, who is in them and what they join stay there, and equal coalitions of an answer are valued once by either way."""
    targets, draws = targets_of(plan.letters, workload), static_draws(plan, semivalue)

    def each(answer: str, players: list[tuple[str, str, int]], by_bits: list[tuple], by_ids: list[dict] | None) -> Iterator[tuple]:
        drawn = Counter()
        for target in targets(answer, players, []):  # draws don't depend on the rows, so that more targets look alike
            for coalition, times in draws(answer, *target):
                drawn[coalition] += times
        masks, times = np.fromiter(drawn, np.int64, len(drawn)), np.fromiter(drawn.values(), np.int64, len(drawn))
        holders = {tid: masks & bit == bit for _, tid, bit in players}
        unequal = values_at(by_bits, masks, workload) != joined_values(by_ids or [], holders, len(masks), workload)
        yield answer, int(times.sum()), int(times[unequal].sum())

    dealt = view.repartition(n_parts(view), "answer")
    listed = rows.repartition(n_parts(view), "answer").join(dealt.select("answer"), "answer", "left_semi").groupBy("answer").agg(F.collect_list(F.struct("need", "x", "any_of", "none_of")).alias("by_ids"))
    names = ["compared", "different"]
    counted = of_answers(dealt.join(listed, "answer", "left"), workload, each, "answer string, compared long, different long", ["answer", *names], more=("by_ids",))
    return counted.agg(*(F.coalesce(F.sum(c), F.lit(0).cast("long")).alias(c) for c in names))


def orders(view: DataFrame, workload: Workload, checkpoints: list[int], runs: int = 1, seed: int = 42) -> DataFrame:
    """(answer, tid, run, checkpoint, total, draws): sums of the marginals in random orders, up to each number of orders. One
    order serves all targets of an answer, and a coalition of an answer is evaluated once."""
    schema = "answer string, tid string, run int, checkpoint int, total long, draws long"

    def each(answer: str, players: list[tuple[str, str, int]], rows: list[tuple]) -> Iterator[tuple]:
        if not players:
            return
        tids = [t.encode() for _, t, _ in players]
        values, most = growing(rows, [b for _, _, b in players], workload), max(1, min(TOGETHER, CELLS // len(tids)))
        for run in range(runs):
            totals, done, at = np.zeros(len(tids), np.int64), 0, 0
            while at < len(checkpoints):
                upto = min(checkpoints[at], done + most)
                order = np.lexsort(hashes(f"{seed}|order|{answer}|{run}|", range(done, upto), tids)[::-1], axis=1)
                np.add.at(totals, order, np.diff(values(order), axis=1))
                done = upto
                while at < len(checkpoints) and checkpoints[at] == done:
                    yield from ((answer, t, run, done, s, done) for (_, t, _), s in zip(players, totals.tolist(), strict=True))
                    at += 1

    return of_answers(view, workload, each, schema, ["answer", "tid", "run", "checkpoint", "total", "draws"])


#: Draws of an answer that are hashed at once, as far as their tuples come to at most so many hashes, and tuples of the
#: largest answers whose coalitions are all tabled.
TOGETHER, CELLS, TABLED = 1000, 1_000_000, 12


def hashes(start: str, draws: range, tids: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """md5 of start, draw and tuple as two words, by draw and tuple."""
    digests = b"".join([md5(place + t).digest() for place in (f"{start}{d}|".encode() for d in draws) for t in tids])
    words = np.frombuffer(digests, ">u8").reshape(len(draws), len(tids), 2)
    return words[..., 0].astype(np.uint64), words[..., 1].astype(np.uint64)


def values_at(rows: list[tuple], masks: np.ndarray, workload: Workload) -> np.ndarray:
    """As `value`, of many coalitions at once."""
    total = np.zeros(masks.shape, np.int64)
    for need, x, any_of, none_of in rows:
        there = masks & need == need
        if any_of:
            there &= np.logical_or.reduce([masks & m == m for m in any_of])
        for m in none_of:
            there &= masks & m != m
        total += there * np.int64(x or 0)
    return finish(total, workload)


def finish(total: np.ndarray, workload: Workload) -> np.ndarray:
    """What a workload makes of the sums of coalitions."""
    if workload.agg == "exists":
        return (total > 0).astype(np.int64)
    return np.where(total > workload.above, total, 0) if workload.agg == "having" else total


def values_of(rows: list[tuple], n: int, workload: Workload) -> Callable[[np.ndarray], np.ndarray]:
    """The values of coalitions of an answer of n players; few players have them all taken once, with the same result."""
    if n > TABLED:
        return lambda masks: values_at(rows, masks, workload)
    table = values_at(rows, np.arange(1 << n), workload)
    return lambda masks: table[masks]


def growing(rows: list[tuple], bits: list[int], workload: Workload) -> Callable[[np.ndarray], np.ndarray]:
    """By order (players by number, a line for each order) the values of the coalitions that it goes through, from none to
    all. Beyond what is tabled a row stands from where the last of its tuples joins up to where a blocker is whole, so the
    work is linear in the rows' tuples and masks are never formed, for any number of players."""
    n = len(bits)
    if n <= TABLED:
        known, masks = values_of(rows, n, workload), np.array(bits, np.int64)
        return lambda order: known(np.bitwise_or.accumulate(np.hstack([np.zeros((len(order), 1), np.int64), masks[order]]), axis=1))
    number = {b: i for i, b in enumerate(bits)}

    def members(m: int) -> list[int]:
        return [number[1 << i] for i in range(m.bit_length()) if m >> i & 1]

    listed = [(members(need), x or 0, list(map(members, any_of)), list(map(members, none_of))) for need, x, any_of, none_of in rows]

    def values(order: np.ndarray) -> np.ndarray:
        line, place = np.arange(len(order)), np.empty_like(order)
        np.put_along_axis(place, order, np.broadcast_to(np.arange(1, n + 1), order.shape), axis=1)
        whole = lambda s: place[:, s].max(axis=1, initial=0)
        change = np.zeros((len(order), n + 2), np.int64)
        for need, x, any_of, none_of in listed:
            start, end = whole(need), np.full(len(order), n + 1)
            if any_of:
                start = np.maximum(start, np.minimum.reduce([whole(s) for s in any_of]))
            for s in none_of:
                end = np.minimum(end, whole(s))
            change[line, start] += x
            change[line, np.maximum(start, end)] -= x
        return finish(np.cumsum(change, axis=1)[:, : n + 1], workload)

    return values


def multilinear(view: DataFrame, workload: Workload, budget: int, seed: int = 42) -> DataFrame:
    """(answer, tid, estimate, se, draws) as `estimate.multilinear_totals` has them, with the same draws, of all tuples of
    the view's answers: tuples are there whose first 52 bits are less than the draw's own."""

    def each(answer: str, players: list[tuple[str, str, int]], rows: list[tuple]) -> Iterator[tuple]:
        bits, start = np.array([b for _, _, b in players], np.int64), f"{seed}|totals|{answer}|"
        s1, s2 = np.zeros(len(bits)), np.zeros(len(bits))
        for lo in range(0, budget, TOGETHER):
            draws = range(lo, min(budget, lo + TOGETHER))
            chance = np.frombuffer(b"".join([md5(f"{start}{d}".encode()).digest() for d in draws]), ">u8")[::2].astype(np.uint64)
            here = hashes(start, draws, [t.encode() for _, t, _ in players])[0] >> np.uint64(12) < chance[:, None] >> np.uint64(12)
            masks = (here * bits).sum(axis=1)[:, None]
            delta = (values_at(rows, masks | bits, workload) - values_at(rows, masks & ~bits, workload)) / workload.unit
            s1 += delta.sum(axis=0)
            s2 += (delta * delta).sum(axis=0)
        error = np.sqrt(np.maximum(0.0, s2 - s1 * s1 / budget) / (budget - 1) / budget) if budget > 1 else np.full(len(bits), np.nan)
        yield from ((answer, t, a, None if np.isnan(e) else e, budget) for (_, t, _), a, e in zip(players, (s1 / budget).tolist(), error.tolist(), strict=True))

    return of_answers(view, workload, each, "answer string, tid string, estimate double, se double, draws long", ["answer", "tid", "estimate", "se", "draws"])
