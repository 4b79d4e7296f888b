"""The workloads: what every row of an answer needs, as SQL that Spark and DuckDB both run.

`rows` has answer (text), row_id, x (a whole number), need (tuple ids that must all be there), any_of (alternatives, one
of which must be there; none asked if empty) and none_of (sets of which none may be wholly there). A tuple id begins
with its relation's letter: c, l, n, o, p, q (part-supplier), r, s, e (events), u (users), d (documents), k (labels).
"""

from __future__ import annotations

from dataclasses import dataclass, replace

LINE = "'l|' || CAST(l_orderkey AS STRING) || '|' || CAST(l_linenumber AS STRING) || '|' || CAST(l_partkey AS STRING) || '|' || CAST(l_suppkey AS STRING) || '|' || CAST(CAST(l_shipdate AS DATE) AS STRING)"
REV = "CAST(round(l_extendedprice * 100) AS BIGINT) * CAST(round((1 - l_discount) * 100) AS BIGINT)"


def tid(letter: str, column: str) -> str:
    return f"'{letter}|' || CAST({column} AS STRING)"


CUST, NAT, ORD, PART, REG, SUPP = tid("c", "c_custkey"), tid("n", "n_nationkey"), tid("o", "o_orderkey"), tid("p", "p_partkey"), tid("r", "r_regionkey"), tid("s", "s_suppkey")
PARTSUPP = "(SELECT l_partkey AS ps_partkey, l_suppkey AS ps_suppkey, min(CAST(round(l_extendedprice * 100 / l_quantity) AS BIGINT)) AS ps_cost, CAST(sum(l_quantity) AS BIGINT) AS ps_avail FROM {lineitem} GROUP BY l_partkey, l_suppkey)"
PS = "'q|' || CAST(ps_partkey AS STRING) || '|' || CAST(ps_suppkey AS STRING)"
LATE = "l_shipdate > o_orderdate + INTERVAL '180' DAY"
NO_SETS = "array(array('x')) AS any_of, array(array('x')) AS none_of"
ROW_ID = "row_number() OVER (ORDER BY {key}) AS row_id"


@dataclass(frozen=True)
class Workload:
    """agg: sum, exists (1 if a row is there), having (the sum where it exceeds `above`) or ratio (of the sum of y to that
    of x, in parts of the unit). unit: of x in the result."""

    name: str
    rows: str
    agg: str = "sum"
    above: int = 0
    unit: float = 1.0
    money: bool = True

    def boolean(self) -> Workload:
        """The game of whether the answer is there at all, as far as a row of it is."""
        sets = "".join(f", {c}" for c in ("any_of", "none_of") if f"AS {c}" in self.rows)
        return replace(self, name=f"{self.name}_boolean", rows=f"SELECT answer, CAST(1 AS BIGINT) AS x, need{sets} FROM ({self.rows}) q", agg="exists", above=0, unit=1.0)


def spj(name: str, answer: str, x: str, tids: list[str], tail: str, unit: float = 1e4, agg: str = "sum", above: int = 0, y: str = "") -> Workload:
    """Select, project, join: each row needs one tuple of every role."""
    rows = f"SELECT {answer} AS answer, {x} AS x,{f' {y} AS y,' if y else ''} array({', '.join(tids)}) AS need FROM {tail}"
    return Workload(name, rows, agg, above, unit)


def day(text: str) -> str:
    return f"CAST('{text}' AS TIMESTAMP)"


CO = "{customer} JOIN {orders} ON c_custkey = o_custkey"
COL = f"{CO} JOIN {{lineitem}} ON l_orderkey = o_orderkey"
W3_TAIL = f"{COL} WHERE c_mktsegment = 'BUILDING' AND o_orderdate < {day('1998-03-15')} AND l_shipdate > {day('1998-03-15')}"
W10_JOIN = f"{COL} JOIN {{nation}} ON n_nationkey = c_nationkey WHERE l_returnflag = 'R'"


def w10(name: str, start: str, end: str, only: str = "") -> Workload:
    return spj(name, "CAST(c_custkey AS STRING)", REV, [CUST, LINE, NAT, ORD], f"{W10_JOIN} AND o_orderdate >= {day(start)} AND o_orderdate < {day(end)}{only}")


def w18(name: str, above: int) -> Workload:
    """Orders whose quantity exceeds a bound; a coalition's own quantity is held against the bound too."""
    large = f"SELECT l_orderkey FROM {{lineitem}} GROUP BY l_orderkey HAVING sum(l_quantity) > {above}"
    return spj(name, "CAST(o_orderkey AS STRING)", "CAST(l_quantity AS BIGINT)", [CUST, LINE, ORD], f"{COL} WHERE o_orderkey IN ({large})", 1.0, "having", above)


W8_NEED = [CUST, LINE, tid("n", "a.n_nationkey"), tid("n", "b.n_nationkey"), ORD, PART, REG, SUPP]
W8_TAIL = f"{COL} JOIN {{part}} ON p_partkey = l_partkey JOIN {{supplier}} ON s_suppkey = l_suppkey JOIN {{nation}} a ON a.n_nationkey = c_nationkey JOIN {{region}} ON r_regionkey = a.n_regionkey JOIN {{nation}} b ON b.n_nationkey = s_nationkey WHERE r_name = 'AMERICA' AND p_type = 'ECONOMY' AND o_orderdate >= {day('1996-01-01')} AND o_orderdate < {day('1998-01-01')}"
W11_VALUES = f"SELECT ps_partkey AS k, sum(ps_cost * ps_avail) AS value FROM {PARTSUPP} q JOIN {{supplier}} ON s_suppkey = ps_suppkey JOIN {{nation}} ON n_nationkey = s_nationkey WHERE n_name = 'NATION_7' GROUP BY ps_partkey"

SPJ = [
    spj("w1", "l_returnflag || '/' || l_linestatus", REV, [LINE], f"{{lineitem}} WHERE l_shipdate <= {day('2001-06-01')}"),
    spj("w3", "CAST(o_orderkey AS STRING)", REV, [CUST, LINE, ORD], W3_TAIL),
    spj("w3_late", "CAST(o_orderkey AS STRING)", REV, [CUST, LINE, ORD], f"{COL} WHERE c_mktsegment = 'BUILDING' AND l_shipdate > o_orderdate"),
    spj(
        "w5", "n_name", REV, [CUST, LINE, NAT, ORD, REG, SUPP],
        f"{COL} JOIN {{supplier}} ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey JOIN {{nation}} ON n_nationkey = s_nationkey JOIN {{region}} ON r_regionkey = n_regionkey WHERE r_name = 'ASIA' AND o_orderdate >= {day('1996-01-01')} AND o_orderdate < {day('1997-01-01')}",
    ),
    spj(
        "w6", "'all'", "CAST(round(l_extendedprice * 100) AS BIGINT) * CAST(round(l_discount * 100) AS BIGINT)", [LINE],
        f"{{lineitem}} WHERE l_shipdate >= {day('1996-01-01')} AND l_shipdate < {day('1997-01-01')} AND round(l_discount * 100) BETWEEN 5 AND 7 AND l_quantity < 24",
    ),
    spj(
        "w7", "a.n_name || '/' || b.n_name || '/' || CAST(year(l_shipdate) AS STRING)", REV, [CUST, LINE, tid("n", "a.n_nationkey"), tid("n", "b.n_nationkey"), ORD, SUPP],
        f"{COL} JOIN {{supplier}} ON s_suppkey = l_suppkey JOIN {{nation}} a ON a.n_nationkey = s_nationkey JOIN {{nation}} b ON b.n_nationkey = c_nationkey WHERE ((a.n_name = 'NATION_3' AND b.n_name = 'NATION_7') OR (a.n_name = 'NATION_7' AND b.n_name = 'NATION_3')) AND l_shipdate >= {day('1996-01-01')} AND l_shipdate < {day('1998-01-01')}",
    ),
    spj(
        "w9", "n_name || '/' || CAST(year(o_orderdate) AS STRING)", f"{REV} - ps_cost * CAST(l_quantity AS BIGINT) * 100", [LINE, NAT, ORD, PART, PS, SUPP],
        f"{{orders}} JOIN {{lineitem}} ON l_orderkey = o_orderkey JOIN {{part}} ON p_partkey = l_partkey JOIN {{supplier}} ON s_suppkey = l_suppkey JOIN {{nation}} ON n_nationkey = s_nationkey JOIN {PARTSUPP} q ON ps_partkey = l_partkey AND ps_suppkey = l_suppkey WHERE p_name LIKE '%small%'",
    ),
    w10("w10", "1996-01-01", "1997-01-01"),
    w10("w10_wide", "1995-01-01", "1999-01-01"),
    spj(
        "w12", "l_linestatus", "CAST(CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 1 ELSE 0 END AS BIGINT)", [LINE, ORD],
        f"{{orders}} JOIN {{lineitem}} ON l_orderkey = o_orderkey WHERE {LATE} AND l_shipdate >= {day('1997-01-01')} AND l_shipdate < {day('1998-01-01')}", 1.0,
    ),
    spj("w14", "'all'", REV, [LINE, PART], f"{{lineitem}} JOIN {{part}} ON p_partkey = l_partkey WHERE p_type = 'PROMO' AND l_shipdate >= {day('1997-09-01')} AND l_shipdate < {day('1997-10-01')}"),
    spj("w15", "CAST(s_suppkey AS STRING)", REV, [LINE, SUPP], f"{{lineitem}} JOIN {{supplier}} ON s_suppkey = l_suppkey WHERE l_shipdate >= {day('1996-01-01')} AND l_shipdate < {day('1996-04-01')}"),
    spj(
        "w19", "'all'", REV, [LINE, PART],
        "{lineitem} JOIN {part} ON p_partkey = l_partkey WHERE (p_brand = 'Brand#12' AND p_size <= 15 AND l_quantity <= 11) OR (p_brand = 'Brand#23' AND p_size <= 25 AND l_quantity BETWEEN 10 AND 20) OR (p_brand = 'Brand#4' AND p_size <= 35 AND l_quantity BETWEEN 20 AND 30)",
    ),
    spj("we", "CAST(CAST(ts AS DATE) AS STRING)", "CAST(round(value * 100) AS BIGINT)", [tid("e", "event_id"), tid("u", "user_id")], "{events} WHERE event_type = 'purchase'", 1e2),
    spj("wd", "source", "CAST(quality AS BIGINT)", [tid("d", "documents.doc_id"), tid("k", "labels.doc_id")], "{documents} documents JOIN {labels} labels ON documents.doc_id = labels.doc_id", 1.0),
    w18("w18", 300),
    w18("w18_low", 150),
    spj("w8_part", "CAST(year(o_orderdate) AS STRING)", REV, W8_NEED, f"{W8_TAIL} AND b.n_name = 'NATION_7'"),
    spj("w8_whole", "CAST(year(o_orderdate) AS STRING)", REV, W8_NEED, W8_TAIL),
    spj(
        "w11", "CAST(ps_partkey AS STRING)", "CAST(ps_cost * ps_avail AS BIGINT)", [NAT, PS, SUPP],
        f"{PARTSUPP} q JOIN {{supplier}} ON s_suppkey = ps_suppkey JOIN {{nation}} ON n_nationkey = s_nationkey JOIN ({W11_VALUES}) v ON v.k = ps_partkey WHERE n_name = 'NATION_7' AND v.value * 1000 > (SELECT sum(value) FROM ({W11_VALUES}))", 1e2,
    ),
    spj(
        "w12_low", "l_linestatus", "CAST(CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 0 ELSE 1 END AS BIGINT)", [LINE, ORD],
        f"{{orders}} JOIN {{lineitem}} ON l_orderkey = o_orderkey WHERE {LATE} AND l_shipdate >= {day('1997-01-01')} AND l_shipdate < {day('1998-01-01')}", 1.0,
    ),
    spj("w14_whole", "'all'", REV, [LINE, PART], f"{{lineitem}} JOIN {{part}} ON p_partkey = l_partkey WHERE l_shipdate >= {day('1997-09-01')} AND l_shipdate < {day('1997-10-01')}"),
    spj(
        "w17", "'all'", "CAST(round(l_extendedprice * 100) AS BIGINT)", [LINE, PART],
        "{lineitem} JOIN {part} ON p_partkey = l_partkey JOIN (SELECT l_partkey AS k, avg(l_quantity) AS q FROM {lineitem} GROUP BY l_partkey) a ON k = l_partkey WHERE p_brand = 'Brand#3' AND l_quantity < 0.2 * q", 700.0,
    ),
    spj(
        "w22", "CAST(c_nationkey AS STRING)", "CAST(1 AS BIGINT)", [CUST],
        f"{{customer}} WHERE c_acctbal > (SELECT avg(c_acctbal) FROM {{customer}} WHERE c_acctbal > 0) AND NOT EXISTS (SELECT 1 FROM {{orders}} WHERE o_custkey = c_custkey AND o_orderdate >= {day('2001-06-01')})", 1.0,
    ),
]

W2_BASE = f"{{part}} JOIN {PARTSUPP} q ON ps_partkey = p_partkey JOIN {{supplier}} ON s_suppkey = ps_suppkey JOIN {{nation}} ON n_nationkey = s_nationkey JOIN {{region}} ON r_regionkey = n_regionkey WHERE p_size = 15 AND r_name = 'EUROPE'"
#: Is there a supplier of the part; one row for each candidate.
W2 = Workload("w2", f"SELECT CAST(p_partkey AS STRING) AS answer, CAST(1 AS BIGINT) AS x, array({NAT}, {PART}, {PS}, {REG}, {SUPP}) AS need FROM {W2_BASE}", "exists", 0, 1.0, False)
#: Is the dearer candidate the cheapest; a cheaper one is a set that must not be whole.
W2_SECOND = Workload(
    "w2_second",
    f"""WITH c AS (SELECT p_partkey, ps_cost, array({NAT}, {PART}, {PS}, {REG}, {SUPP}) AS need FROM {W2_BASE}),
k AS (SELECT p_partkey, need, ps_cost, row_number() OVER (PARTITION BY p_partkey ORDER BY ps_cost, ps_cost) AS place FROM c)
SELECT CAST(a.p_partkey AS STRING) AS answer, CAST(1 AS BIGINT) AS x, a.need AS need, collect_list(b.need) AS none_of
FROM k a JOIN k b ON a.p_partkey = b.p_partkey AND b.place = 1 WHERE a.place = 2 GROUP BY a.p_partkey, a.need""",
    "exists", 0, 1.0, False,
)
_W21_LINES = f"SELECT l_orderkey, l_suppkey, {LINE} AS tid, {LATE} AS late FROM {{lineitem}} JOIN {{orders}} ON o_orderkey = l_orderkey WHERE o_orderstatus = 'F' AND o_orderdate >= {day('1996-01-01')} AND o_orderdate < {day('1999-01-01')}"
#: Late lines of a supplier in orders where others delivered, none of them late; another's line is the witness.
W21 = Workload(
    "w21",
    f"""WITH t AS ({_W21_LINES}),
w AS (SELECT a.tid AS tid, collect_list(array(b.tid)) AS witnesses, max(CASE WHEN b.late THEN 1 ELSE 0 END) AS blocked FROM t a JOIN t b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey <> b.l_suppkey WHERE a.late GROUP BY a.tid)
SELECT CAST(s_suppkey AS STRING) AS answer, CAST(1 AS BIGINT) AS x, array(t.tid, {NAT}, {tid('o', 't.l_orderkey')}, {SUPP}) AS need, w.witnesses AS any_of
FROM w JOIN t ON w.tid = t.tid JOIN {{supplier}} ON s_suppkey = t.l_suppkey JOIN {{nation}} ON n_nationkey = s_nationkey WHERE w.blocked = 0""",
    "sum", 0, 1.0, False,
)
#: Orders with a late line; which one does not matter.
W4 = Workload(
    "w4",
    f"""SELECT o_orderpriority AS answer, CAST(1 AS BIGINT) AS x, array({ORD}) AS need, collect_list(array({LINE})) AS any_of
FROM {{orders}} JOIN {{lineitem}} ON l_orderkey = o_orderkey WHERE {LATE} AND o_orderdate >= {day('1997-07-01')} AND o_orderdate < {day('1997-10-01')}
GROUP BY o_orderpriority, o_orderkey""",
    "sum", 0, 1.0, False,
)

#: Customers by how many open or finished orders they have; each counts if all of these are there.
W13 = Workload(
    "w13",
    f"""SELECT CAST(count(o_orderkey) AS STRING) AS answer, CAST(1 AS BIGINT) AS x, flatten(array(array({CUST}), collect_list({ORD}))) AS need
FROM {{customer}} LEFT JOIN {{orders}} ON o_custkey = c_custkey AND o_orderstatus <> 'P' GROUP BY c_custkey""",
    "sum", 0, 1.0, False,
)
#: Distinct suppliers of a kind of part; any part of the kind that a supplier offers will do.
W16 = Workload(
    "w16",
    f"""SELECT p_brand || '/' || p_type || '/' || CAST(p_size AS STRING) AS answer, CAST(1 AS BIGINT) AS x, array({SUPP}) AS need, collect_list(array({PART}, {PS})) AS any_of
FROM {{part}} JOIN {PARTSUPP} q ON ps_partkey = p_partkey JOIN {{supplier}} ON s_suppkey = ps_suppkey
WHERE p_brand <> 'Brand#5' AND p_type <> 'MEDIUM' AND p_size IN (3, 9, 14, 19, 23, 36, 45, 49) AND s_acctbal >= 0 GROUP BY p_brand, p_type, p_size, s_suppkey""",
    "sum", 0, 1.0, False,
)
#: Suppliers with more of some small part than half of what was shipped of it; any such part will do.
W20 = Workload(
    "w20",
    f"""SELECT CAST(s_suppkey AS STRING) AS answer, CAST(1 AS BIGINT) AS x, array({NAT}, {SUPP}) AS need, collect_list(array({PART}, {PS})) AS any_of
FROM {PARTSUPP} q JOIN {{part}} ON p_partkey = ps_partkey JOIN (SELECT l_partkey AS pk, l_suppkey AS sk, sum(l_quantity) AS shipped FROM {{lineitem}} WHERE l_shipdate >= {day('1996-01-01')} AND l_shipdate < {day('1997-01-01')} GROUP BY l_partkey, l_suppkey) sh ON pk = ps_partkey AND sk = ps_suppkey
JOIN {{supplier}} ON s_suppkey = ps_suppkey JOIN {{nation}} ON n_nationkey = s_nationkey WHERE n_name = 'NATION_7' AND p_name LIKE 'small%' AND ps_avail > 0.5 * shipped GROUP BY s_suppkey, n_nationkey""",
    "sum", 0, 1.0, False,
)

#: Nested conditions as they come out on the data, whatever the coalition: the sum without its bound, lines without witnesses.
FROZEN = [replace(w18("w18_low", 150), name="w18_frozen", agg="sum"), replace(W21, name="w21_frozen", rows=W21.rows.replace(", w.witnesses AS any_of", ""))]
#: Shares: of a nation's suppliers in a market, of promoted parts in the revenue of a month.
RATIOS = [
    spj("w8_ratio", "CAST(year(o_orderdate) AS STRING)", REV, W8_NEED, W8_TAIL, 1e6, "ratio", 0, f"CASE WHEN b.n_name = 'NATION_7' THEN {REV} ELSE 0 END"),
    spj(
        "w14_ratio", "'all'", REV, [LINE, PART], f"{{lineitem}} JOIN {{part}} ON p_partkey = l_partkey WHERE l_shipdate >= {day('1997-09-01')} AND l_shipdate < {day('1997-10-01')}",
        1e6, "ratio", 0, f"CASE WHEN p_type = 'PROMO' THEN {REV} ELSE 0 END",
    ),
]

WORKLOADS = {w.name: w for w in [*SPJ, W2, W2_SECOND, W4, W13, W16, W20, W21, *FROZEN, *RATIOS]}
