"""The 22 workload queries as plain results, in SQL that Spark and DuckDB both run."""

from __future__ import annotations

from .workloads import COL, LATE, PARTSUPP, W10_JOIN, day

M = "CAST(round(l_extendedprice * 100) AS BIGINT) * CAST(round((1 - l_discount) * 100) AS BIGINT)"
MONEY = f"round(CAST(sum({M}) AS DOUBLE) / CAST(10000 AS DOUBLE), 4)"


def between(column: str, a: str, b: str) -> str:
    return f"{column} >= {day(a)} AND {column} < {day(b)}"


PS_JOIN = f"{PARTSUPP} q"
QUERIES = {
    "w1": f"SELECT l_returnflag, l_linestatus, CAST(sum(l_quantity) AS BIGINT) AS qty, {MONEY} AS revenue, round(avg(l_quantity), 4) AS avg_qty, count(*) AS n FROM {{lineitem}} WHERE l_shipdate <= {day('2001-06-01')} GROUP BY l_returnflag, l_linestatus",
    "w2": f"SELECT p_partkey, min(ps_cost) AS cost FROM {{part}} JOIN {PS_JOIN} ON ps_partkey = p_partkey JOIN {{supplier}} ON s_suppkey = ps_suppkey JOIN {{nation}} ON n_nationkey = s_nationkey JOIN {{region}} ON r_regionkey = n_regionkey WHERE p_size = 15 AND r_name = 'EUROPE' GROUP BY p_partkey",
    "w3": f"SELECT o_orderkey, {MONEY} AS revenue FROM {COL} WHERE c_mktsegment = 'BUILDING' AND o_orderdate < {day('1998-03-15')} AND l_shipdate > {day('1998-03-15')} GROUP BY o_orderkey",
    "w4": f"SELECT o_orderpriority, count(*) AS n FROM {{orders}} WHERE {between('o_orderdate', '1997-07-01', '1997-10-01')} AND EXISTS (SELECT 1 FROM {{lineitem}} WHERE l_orderkey = o_orderkey AND {LATE}) GROUP BY o_orderpriority",
    "w5": f"SELECT n_name, {MONEY} AS revenue FROM {COL} JOIN {{supplier}} ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey JOIN {{nation}} ON n_nationkey = s_nationkey JOIN {{region}} ON r_regionkey = n_regionkey WHERE r_name = 'ASIA' AND {between('o_orderdate', '1996-01-01', '1997-01-01')} GROUP BY n_name",
    "w6": f"SELECT round(CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT) * CAST(round(l_discount * 100) AS BIGINT)) AS DOUBLE) / CAST(10000 AS DOUBLE), 4) AS revenue FROM {{lineitem}} WHERE {between('l_shipdate', '1996-01-01', '1997-01-01')} AND round(l_discount * 100) BETWEEN 5 AND 7 AND l_quantity < 24",
    "w7": f"SELECT a.n_name AS supp_nation, b.n_name AS cust_nation, CAST(year(l_shipdate) AS BIGINT) AS ship_year, {MONEY} AS revenue FROM {COL} JOIN {{supplier}} ON s_suppkey = l_suppkey JOIN {{nation}} a ON a.n_nationkey = s_nationkey JOIN {{nation}} b ON b.n_nationkey = c_nationkey WHERE ((a.n_name = 'NATION_3' AND b.n_name = 'NATION_7') OR (a.n_name = 'NATION_7' AND b.n_name = 'NATION_3')) AND {between('l_shipdate', '1996-01-01', '1998-01-01')} GROUP BY a.n_name, b.n_name, year(l_shipdate)",
    "w8": f"SELECT CAST(year(o_orderdate) AS BIGINT) AS order_year, round(CAST(sum(CASE WHEN b.n_name = 'NATION_7' THEN {M} ELSE 0 END) AS DOUBLE) / CAST(sum({M}) AS DOUBLE), 6) AS share FROM {COL} JOIN {{part}} ON p_partkey = l_partkey JOIN {{supplier}} ON s_suppkey = l_suppkey JOIN {{nation}} a ON a.n_nationkey = c_nationkey JOIN {{region}} ON r_regionkey = a.n_regionkey JOIN {{nation}} b ON b.n_nationkey = s_nationkey WHERE r_name = 'AMERICA' AND p_type = 'ECONOMY' AND {between('o_orderdate', '1996-01-01', '1998-01-01')} GROUP BY year(o_orderdate)",
    "w9": f"SELECT n_name, CAST(year(o_orderdate) AS BIGINT) AS order_year, round(CAST(sum({M} - ps_cost * CAST(l_quantity AS BIGINT) * 100) AS DOUBLE) / CAST(10000 AS DOUBLE), 4) AS profit FROM {{orders}} JOIN {{lineitem}} ON l_orderkey = o_orderkey JOIN {{part}} ON p_partkey = l_partkey JOIN {{supplier}} ON s_suppkey = l_suppkey JOIN {{nation}} ON n_nationkey = s_nationkey JOIN {PS_JOIN} ON ps_partkey = l_partkey AND ps_suppkey = l_suppkey WHERE p_name LIKE '%small%' GROUP BY n_name, year(o_orderdate)",
    "w10": f"SELECT c_custkey, n_name, {MONEY} AS revenue FROM {W10_JOIN} AND {between('o_orderdate', '1996-01-01', '1997-01-01')} GROUP BY c_custkey, n_name ORDER BY revenue DESC, c_custkey LIMIT 20",
    "w11": f"WITH v AS (SELECT ps_partkey, sum(ps_cost * ps_avail) AS value FROM {PS_JOIN} JOIN {{supplier}} ON s_suppkey = ps_suppkey JOIN {{nation}} ON n_nationkey = s_nationkey WHERE n_name = 'NATION_7' GROUP BY ps_partkey) SELECT ps_partkey, CAST(value AS BIGINT) AS value FROM v WHERE value * 1000 > (SELECT sum(value) FROM v)",
    "w12": f"SELECT l_linestatus, CAST(sum(CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 1 ELSE 0 END) AS BIGINT) AS high, CAST(sum(CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 0 ELSE 1 END) AS BIGINT) AS low FROM {{orders}} JOIN {{lineitem}} ON l_orderkey = o_orderkey WHERE {LATE} AND {between('l_shipdate', '1997-01-01', '1998-01-01')} GROUP BY l_linestatus",
    "w13": "WITH c AS (SELECT c_custkey, count(o_orderkey) AS n_orders FROM {customer} LEFT JOIN {orders} ON o_custkey = c_custkey AND o_orderstatus <> 'P' GROUP BY c_custkey) SELECT n_orders, count(*) AS n FROM c GROUP BY n_orders",
    "w14": f"SELECT round(CAST(100 AS DOUBLE) * CAST(sum(CASE WHEN p_type = 'PROMO' THEN {M} ELSE 0 END) AS DOUBLE) / CAST(sum({M}) AS DOUBLE), 6) AS promo FROM {{lineitem}} JOIN {{part}} ON p_partkey = l_partkey WHERE {between('l_shipdate', '1997-09-01', '1997-10-01')}",
    "w15": f"WITH v AS (SELECT l_suppkey, sum({M}) AS revenue FROM {{lineitem}} WHERE {between('l_shipdate', '1996-01-01', '1996-04-01')} GROUP BY l_suppkey) SELECT s_suppkey, s_name, round(CAST(revenue AS DOUBLE) / CAST(10000 AS DOUBLE), 4) AS revenue FROM v JOIN {{supplier}} ON s_suppkey = l_suppkey WHERE revenue = (SELECT max(revenue) FROM v)",
    "w16": f"SELECT p_brand, p_type, p_size, count(DISTINCT ps_suppkey) AS n FROM {{part}} JOIN {PS_JOIN} ON ps_partkey = p_partkey WHERE p_brand <> 'Brand#5' AND p_type <> 'MEDIUM' AND p_size IN (3, 9, 14, 19, 23, 36, 45, 49) AND NOT EXISTS (SELECT 1 FROM {{supplier}} WHERE s_suppkey = ps_suppkey AND s_acctbal < 0) GROUP BY p_brand, p_type, p_size",
    "w17": "WITH a AS (SELECT l_partkey AS k, avg(l_quantity) AS q FROM {lineitem} GROUP BY l_partkey) SELECT round(CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS DOUBLE) / CAST(700 AS DOUBLE), 2) AS yearly FROM {lineitem} JOIN {part} ON p_partkey = l_partkey JOIN a ON k = l_partkey WHERE p_brand = 'Brand#3' AND l_quantity < 0.2 * q",
    "w18": "SELECT c_custkey, o_orderkey, CAST(sum(l_quantity) AS BIGINT) AS qty FROM {customer} JOIN {orders} ON c_custkey = o_custkey JOIN {lineitem} ON l_orderkey = o_orderkey GROUP BY c_custkey, o_orderkey HAVING sum(l_quantity) > 300",
    "w19": f"SELECT {MONEY} AS revenue FROM {{lineitem}} JOIN {{part}} ON p_partkey = l_partkey WHERE (p_brand = 'Brand#12' AND p_size <= 15 AND l_quantity <= 11) OR (p_brand = 'Brand#23' AND p_size <= 25 AND l_quantity BETWEEN 10 AND 20) OR (p_brand = 'Brand#4' AND p_size <= 35 AND l_quantity BETWEEN 20 AND 30)",
    "w20": f"WITH sh AS (SELECT l_partkey AS pk, l_suppkey AS sk, sum(l_quantity) AS shipped FROM {{lineitem}} WHERE {between('l_shipdate', '1996-01-01', '1997-01-01')} GROUP BY l_partkey, l_suppkey) SELECT DISTINCT s_suppkey, s_name FROM {PS_JOIN} JOIN {{part}} ON p_partkey = ps_partkey JOIN sh ON pk = ps_partkey AND sk = ps_suppkey JOIN {{supplier}} ON s_suppkey = ps_suppkey JOIN {{nation}} ON n_nationkey = s_nationkey WHERE n_name = 'NATION_7' AND p_name LIKE 'small%' AND ps_avail > 0.5 * shipped",
    "w21": f"WITH t AS (SELECT l_orderkey, l_suppkey, {LATE} AS late FROM {{lineitem}} JOIN {{orders}} ON o_orderkey = l_orderkey WHERE o_orderstatus = 'F' AND {between('o_orderdate', '1996-01-01', '1999-01-01')}) SELECT l_suppkey AS s_suppkey, count(*) AS n FROM t a WHERE a.late AND EXISTS (SELECT 1 FROM t b WHERE b.l_orderkey = a.l_orderkey AND b.l_suppkey <> a.l_suppkey) AND NOT EXISTS (SELECT 1 FROM t b WHERE b.l_orderkey = a.l_orderkey AND b.l_suppkey <> a.l_suppkey AND b.late) GROUP BY l_suppkey",
    "w22": f"WITH g AS (SELECT c_custkey, c_nationkey, c_acctbal FROM {{customer}} WHERE c_acctbal > (SELECT avg(c_acctbal) FROM {{customer}} WHERE c_acctbal > 0)) SELECT c_nationkey, count(*) AS n, round(sum(c_acctbal), 2) AS balance FROM g WHERE NOT EXISTS (SELECT 1 FROM {{orders}} WHERE o_custkey = c_custkey AND o_orderdate >= {day('2001-06-01')}) GROUP BY c_nationkey",
}
