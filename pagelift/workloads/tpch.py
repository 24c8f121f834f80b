"""The 22-query decision-support workload over direct scans, re-expressed on the reduced schema.

Money is summed in whole units (cents, or ten-thousandths where a discount is applied), so that sums don't depend on the
order of rows.  One text serves both engines: Spark gets scans for the names in braces, the oracle the tables.
"""

from __future__ import annotations

from pagelift.workloads import fixtures as fx
from pagelift.workloads.registry import Registry

REG = Registry()
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")

EXT = "CAST(round(l_extendedprice * 100) AS BIGINT)"
REV = f"{EXT} * (100 - CAST(round(l_discount * 100) AS BIGINT))"
QTY = "CAST(l_quantity AS BIGINT)"
#: Stand-in for the missing supply table: what a supplier charges for a part, and how much of it was sold.
PS = "(SELECT l_partkey AS ps_partkey, l_suppkey AS ps_suppkey, min(CAST(floor(l_extendedprice * 100 / l_quantity) AS BIGINT)) AS ps_cost, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS ps_qty FROM {lineitem} GROUP BY l_partkey, l_suppkey)"


def total(x: str) -> str:
    return f"CAST(sum({x}) AS BIGINT)"


QUERIES = {
    1: f"""SELECT l_returnflag, l_linestatus, {total(QTY)} AS sum_qty, {total(EXT)} AS sum_base, {total(REV)} AS sum_disc,
  {total(f"{REV} * (100 + CAST(round(l_tax * 100) AS BIGINT))")} AS sum_charge, round(CAST({total(QTY)} AS DOUBLE) / count(*), 4) AS avg_qty,
  round(CAST({total("CAST(round(l_discount * 100) AS BIGINT)")} AS DOUBLE) / count(*), 4) AS avg_disc, count(*) AS n
FROM {{lineitem}} WHERE l_shipdate <= DATE '2001-09-01' GROUP BY l_returnflag, l_linestatus ORDER BY l_returnflag, l_linestatus""",
    2: f"""WITH ps AS {PS}, offers AS (
  SELECT s_name, n_name, p_partkey, p_brand, ps_cost, s_suppkey FROM ps JOIN {{part}} ON p_partkey = ps_partkey JOIN {{supplier}} ON s_suppkey = ps_suppkey
  JOIN {{nation}} ON n_nationkey = s_nationkey JOIN {{region}} ON r_regionkey = n_regionkey WHERE p_size <= 15 AND p_type = 'LARGE' AND r_name = 'EUROPE')
SELECT s_name, n_name, p_partkey, p_brand, ps_cost FROM offers o WHERE ps_cost = (SELECT min(i.ps_cost) FROM offers i WHERE i.p_partkey = o.p_partkey)
ORDER BY ps_cost DESC, n_name, s_name, p_partkey LIMIT 100""",
    3: f"""SELECT l_orderkey, {total(REV)} AS revenue, o_orderdate FROM {{customer}} JOIN {{orders}} ON c_custkey = o_custkey JOIN {{lineitem}} ON l_orderkey = o_orderkey
WHERE c_mktsegment = 'BUILDING' AND o_orderdate < DATE '1998-03-15' AND l_shipdate > DATE '1998-03-15'
GROUP BY l_orderkey, o_orderdate ORDER BY revenue DESC, o_orderdate, l_orderkey LIMIT 10""",
    4: """SELECT o_orderpriority, count(*) AS order_count FROM {orders} WHERE o_orderdate >= DATE '1997-07-01' AND o_orderdate < DATE '1997-10-01'
AND EXISTS (SELECT 1 FROM {lineitem} WHERE l_orderkey = o_orderkey AND l_shipdate > o_orderdate + INTERVAL 90 DAY) GROUP BY o_orderpriority ORDER BY o_orderpriority""",
    5: f"""SELECT n_name, {total(REV)} AS revenue FROM {{customer}} JOIN {{orders}} ON c_custkey = o_custkey JOIN {{lineitem}} ON l_orderkey = o_orderkey
JOIN {{supplier}} ON l_suppkey = s_suppkey AND c_nationkey = s_nationkey JOIN {{nation}} ON s_nationkey = n_nationkey JOIN {{region}} ON n_regionkey = r_regionkey
WHERE r_name = 'ASIA' AND o_orderdate >= DATE '1997-01-01' AND o_orderdate < DATE '1998-01-01' GROUP BY n_name ORDER BY revenue DESC, n_name""",
    6: f"""SELECT {total(f"{EXT} * CAST(round(l_discount * 100) AS BIGINT)")} AS revenue FROM {{lineitem}}
WHERE l_shipdate >= DATE '1997-01-01' AND l_shipdate < DATE '1998-01-01' AND CAST(round(l_discount * 100) AS BIGINT) BETWEEN 5 AND 7 AND l_quantity < 24""",
    7: f"""SELECT supp_nation, cust_nation, l_year, {total("volume")} AS revenue FROM (
  SELECT n1.n_name AS supp_nation, n2.n_name AS cust_nation, CAST(year(l_shipdate) AS INT) AS l_year, {REV} AS volume
  FROM {{supplier}} JOIN {{lineitem}} ON s_suppkey = l_suppkey JOIN {{orders}} ON o_orderkey = l_orderkey JOIN {{customer}} ON c_custkey = o_custkey
  JOIN {{nation}} n1 ON s_nationkey = n1.n_nationkey JOIN {{nation}} n2 ON c_nationkey = n2.n_nationkey
  WHERE (n1.n_name = 'NATION_1' AND n2.n_name = 'NATION_2') OR (n1.n_name = 'NATION_2' AND n2.n_name = 'NATION_1')) v
GROUP BY supp_nation, cust_nation, l_year ORDER BY supp_nation, cust_nation, l_year""",
    8: f"""SELECT o_year, {total("CASE WHEN nation = 'NATION_1' THEN volume ELSE 0 END")} AS part_volume, {total("volume")} AS all_volume,
  round(CAST({total("CASE WHEN nation = 'NATION_1' THEN volume ELSE 0 END")} AS DOUBLE) / CAST({total("volume")} AS DOUBLE), 6) AS mkt_share FROM (
  SELECT CAST(year(o_orderdate) AS INT) AS o_year, {REV} AS volume, n2.n_name AS nation FROM {{part}} JOIN {{lineitem}} ON p_partkey = l_partkey JOIN {{supplier}} ON s_suppkey = l_suppkey
  JOIN {{orders}} ON l_orderkey = o_orderkey JOIN {{customer}} ON o_custkey = c_custkey JOIN {{nation}} n1 ON c_nationkey = n1.n_nationkey JOIN {{region}} ON n1.n_regionkey = r_regionkey
  JOIN {{nation}} n2 ON s_nationkey = n2.n_nationkey WHERE r_name = 'AMERICA' AND p_type = 'ECONOMY') v GROUP BY o_year ORDER BY o_year""",
    9: f"""WITH ps AS {PS} SELECT nation, o_year, {total("amount")} AS sum_profit FROM (
  SELECT n_name AS nation, CAST(year(o_orderdate) AS INT) AS o_year, {REV} - ps_cost * {QTY} * 100 AS amount FROM {{part}} JOIN {{lineitem}} ON p_partkey = l_partkey
  JOIN {{supplier}} ON s_suppkey = l_suppkey JOIN ps ON ps_partkey = l_partkey AND ps_suppkey = l_suppkey JOIN {{orders}} ON o_orderkey = l_orderkey JOIN {{nation}} ON s_nationkey = n_nationkey
  WHERE p_name LIKE '%widget%') v GROUP BY nation, o_year ORDER BY nation, o_year DESC""",
    10: f"""SELECT c_custkey, c_name, {total(REV)} AS revenue, CAST(round(c_acctbal * 100) AS BIGINT) AS acctbal, n_name FROM {{customer}} JOIN {{orders}} ON c_custkey = o_custkey
JOIN {{lineitem}} ON l_orderkey = o_orderkey JOIN {{nation}} ON c_nationkey = n_nationkey WHERE o_orderdate >= DATE '1997-10-01' AND o_orderdate < DATE '1998-01-01' AND l_returnflag = 'R'
GROUP BY c_custkey, c_name, c_acctbal, n_name ORDER BY revenue DESC, c_custkey LIMIT 20""",
    11: f"""WITH ps AS {PS}, v AS (SELECT ps_partkey, {total("ps_cost * ps_qty")} AS value FROM ps JOIN {{supplier}} ON ps_suppkey = s_suppkey JOIN {{nation}} ON s_nationkey = n_nationkey
  WHERE n_name = 'NATION_1' GROUP BY ps_partkey)
SELECT ps_partkey, value FROM v WHERE value * 1000 > (SELECT CAST(sum(value) AS BIGINT) FROM v) ORDER BY value DESC, ps_partkey""",
    12: """SELECT l_returnflag, CAST(sum(CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 1 ELSE 0 END) AS BIGINT) AS high_count,
  CAST(sum(CASE WHEN o_orderpriority NOT IN ('1-URGENT', '2-HIGH') THEN 1 ELSE 0 END) AS BIGINT) AS low_count FROM {orders} JOIN {lineitem} ON o_orderkey = l_orderkey
WHERE l_shipdate >= DATE '1997-01-01' AND l_shipdate < DATE '1998-01-01' GROUP BY l_returnflag ORDER BY l_returnflag""",
    13: """SELECT c_count, count(*) AS custdist FROM (SELECT c_custkey, count(o_orderkey) AS c_count FROM {customer} LEFT JOIN {orders} ON c_custkey = o_custkey AND o_orderpriority = '1-URGENT'
GROUP BY c_custkey) c GROUP BY c_count ORDER BY custdist DESC, c_count DESC""",
    14: f"""SELECT round(100 * CAST({total(f"CASE WHEN p_type = 'PROMO' THEN {REV} ELSE 0 END")} AS DOUBLE) / CAST({total(REV)} AS DOUBLE), 6) AS promo_revenue
FROM {{lineitem}} JOIN {{part}} ON l_partkey = p_partkey WHERE l_shipdate >= DATE '1997-09-01' AND l_shipdate < DATE '1997-10-01'""",
    15: f"""WITH r AS (SELECT l_suppkey AS supplier_no, {total(REV)} AS total_revenue FROM {{lineitem}} WHERE l_shipdate >= DATE '1997-01-01' AND l_shipdate < DATE '1997-04-01' GROUP BY l_suppkey)
SELECT s_suppkey, s_name, total_revenue FROM {{supplier}} JOIN r ON s_suppkey = supplier_no WHERE total_revenue = (SELECT max(total_revenue) FROM r) ORDER BY s_suppkey""",
    16: f"""WITH ps AS {PS} SELECT p_brand, p_type, p_size, count(DISTINCT ps_suppkey) AS supplier_cnt FROM ps JOIN {{part}} ON p_partkey = ps_partkey
WHERE p_brand <> 'Brand#5' AND p_type NOT LIKE 'MED%' AND p_size IN (49, 14, 23, 45, 19, 3, 36, 9) AND ps_suppkey NOT IN (SELECT s_suppkey FROM {{supplier}} WHERE s_acctbal < 0)
GROUP BY p_brand, p_type, p_size ORDER BY supplier_cnt DESC, p_brand, p_type, p_size""",
    17: f"""SELECT {total(EXT)} AS spent, round(CAST({total(EXT)} AS DOUBLE) / 7, 4) AS avg_yearly FROM {{lineitem}} l JOIN {{part}} ON p_partkey = l_partkey
WHERE p_brand = 'Brand#23' AND l_quantity < (SELECT 0.2 * avg(i.l_quantity) FROM {{lineitem}} i WHERE i.l_partkey = p_partkey)""",
    18: f"""SELECT c_name, c_custkey, o_orderkey, o_orderdate, CAST(round(o_totalprice * 100) AS BIGINT) AS total, {total(QTY)} AS qty FROM {{customer}} JOIN {{orders}} ON c_custkey = o_custkey
JOIN {{lineitem}} ON o_orderkey = l_orderkey WHERE o_orderkey IN (SELECT l_orderkey FROM {{lineitem}} GROUP BY l_orderkey HAVING sum(l_quantity) > 250)
GROUP BY c_name, c_custkey, o_orderkey, o_orderdate, o_totalprice ORDER BY total DESC, o_orderdate, o_orderkey LIMIT 100""",
    19: f"""SELECT {total(REV)} AS revenue FROM {{lineitem}} JOIN {{part}} ON p_partkey = l_partkey WHERE (p_brand = 'Brand#12' AND l_quantity BETWEEN 1 AND 11 AND p_size BETWEEN 1 AND 5)
OR (p_brand = 'Brand#23' AND l_quantity BETWEEN 10 AND 20 AND p_size BETWEEN 1 AND 10) OR (p_brand = 'Brand#2' AND l_quantity BETWEEN 20 AND 30 AND p_size BETWEEN 1 AND 15)""",
    20: f"""WITH ps AS {PS} SELECT s_name, s_suppkey FROM {{supplier}} JOIN {{nation}} ON s_nationkey = n_nationkey WHERE n_name = 'NATION_3' AND s_suppkey IN (
  SELECT ps_suppkey FROM ps WHERE ps_partkey IN (SELECT p_partkey FROM {{part}} WHERE p_name LIKE 'blue%') AND 2 * ps_qty > (
    SELECT {total(QTY)} FROM {{lineitem}} WHERE l_partkey = ps_partkey AND l_suppkey = ps_suppkey AND l_shipdate >= DATE '1997-01-01' AND l_shipdate < DATE '1998-01-01')) ORDER BY s_name, s_suppkey""",
    21: """SELECT s_name, count(*) AS numwait FROM {supplier} JOIN {lineitem} l1 ON s_suppkey = l1.l_suppkey JOIN {orders} ON o_orderkey = l1.l_orderkey
WHERE o_orderstatus = 'F' AND l1.l_shipdate > o_orderdate + INTERVAL 365 DAY AND EXISTS (SELECT 1 FROM {lineitem} l2 WHERE l2.l_orderkey = l1.l_orderkey AND l2.l_suppkey <> l1.l_suppkey)
AND NOT EXISTS (SELECT 1 FROM {lineitem} l3 JOIN {orders} o3 ON o3.o_orderkey = l3.l_orderkey WHERE l3.l_orderkey = l1.l_orderkey AND l3.l_suppkey <> l1.l_suppkey AND l3.l_shipdate > o3.o_orderdate + INTERVAL 365 DAY)
GROUP BY s_name ORDER BY numwait DESC, s_name LIMIT 100""",
    22: f"""SELECT cntrycode, count(*) AS numcust, {total("CAST(round(c_acctbal * 100) AS BIGINT)")} AS totacctbal FROM (SELECT c_nationkey AS cntrycode, c_acctbal, c_custkey FROM {{customer}}
  WHERE c_nationkey IN (1, 3, 5, 7, 11, 13, 17) AND CAST(round(c_acctbal * 100) AS BIGINT) > (SELECT CAST(sum(CAST(round(c_acctbal * 100) AS BIGINT)) AS DOUBLE) / count(*) FROM {{customer}} WHERE c_acctbal > 0 AND c_nationkey IN (1, 3, 5, 7, 11, 13, 17))
  AND NOT EXISTS (SELECT 1 FROM {{orders}} WHERE o_custkey = c_custkey AND o_orderstatus = 'P')) c GROUP BY cntrycode ORDER BY cntrycode""",
}


def run(kind: str, number: int):
    text = QUERIES[number]
    names = [t for t in TABLES if "{" + t + "}" in text]

    def query(spark, sf_dir):
        return spark.sql(text, **{t: fx.direct(spark, sf_dir, t, kind) for t in names})

    return query


for _n in QUERIES:
    for _short, _kind in (("heap", "pageheap"), ("tree", "pagetree")):
        REG.add(f"tpch_q{_n:02d}_{_short}", run(_kind, _n), QUERIES[_n].format(**{t: t for t in TABLES}))


@REG.query("tpch_q06_brin", QUERIES[6].format(lineitem="lineitem"))
def q06_indexed(spark, sf_dir):
    """The sixth query over lineitem clustered by date, with its range index."""
    from pagelift.workloads.scans import indexed

    _, scan = indexed(spark, sf_dir, "lineitem", "l_shipdate", 8, label="brin_date_sorted_lineitem", cluster=("l_shipdate",), pushdown=True, index_column="l_shipdate")
    return spark.sql(QUERIES[6].replace("DATE '", "TIMESTAMP_NTZ '"), lineitem=scan)
