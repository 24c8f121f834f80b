"""Surrounding operators over direct scans: what a user does with the rows once they are out of the pages.

Most entries are one SQL text for both engines; names in braces are direct scans of heap pages.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagelift import scan
from pagelift.operators import ranges
from pagelift.session import scratch
from pagelift.workloads import fixtures as fx
from pagelift.workloads.registry import Registry

REG = Registry()
NAMES = tuple(fx.SPECS)
CENTS = "CAST(round(l_extendedprice * 100) AS BIGINT)"


def sql(name: str, text: str, oracle: str | None = None, kind: str = "pageheap") -> None:
    """Register a text; oracle where the other engine's dialect differs."""
    used = [t for t in NAMES if "{" + t + "}" in text]

    def run(spark, d):
        return spark.sql(text, **{t: fx.direct(spark, d, t, kind) for t in used})

    REG.add(name, run, (oracle or text).format(**{t: t for t in NAMES}))


def many(prefix: str, texts: dict[str, str | tuple[str, str]]) -> None:
    for name, text in texts.items():
        sql(f"{prefix}_{name}", *([text] if isinstance(text, str) else text))


# -- sources and sinks


def through(fmt: str, table: str = "orders", **options):
    def run(spark, d):
        path = scratch(spark, "sink")
        df = fx.direct(spark, d, table, "pageheap")
        df.write.format(fmt).options(**options).save(path)
        return spark.read.schema(df.schema).format(fmt).options(**options).load(path)

    return run


REG.add("src_parquet", lambda s, d: fx.table(s, d, "lineitem"), "SELECT * FROM lineitem")
for _f in ("csv", "json", "orc"):
    REG.add(f"src_{_f}", through(_f), "SELECT * FROM orders")
for _f in ("parquet", "csv", "json"):
    REG.add(f"sink_{_f}", through(_f, "customer"), "SELECT * FROM customer")


@REG.query("sink_parquet_partitioned", "SELECT o_orderkey, o_totalprice, o_orderpriority FROM orders")
def sink_parquet_partitioned(spark, d):
    path = scratch(spark, "sink")
    fx.direct(spark, d, "orders", "pageheap").select("o_orderkey", "o_totalprice", "o_orderpriority").repartition("o_orderpriority").write.partitionBy("o_orderpriority").parquet(path)
    return spark.read.parquet(path)


def paged_sink(kind):
    def run(spark, d):
        path = scratch(spark, "sink")
        scan.write(fx.direct(spark, d, "orders", "pageheap"), kind, path, fx.SPECS["orders"], pk=("o_orderkey",) if kind == "pagetree" else ())
        return scan.scan(spark, kind, path)

    return run


for _k in ("pageheap", "pagetree"):
    REG.add(f"sink_{_k}", paged_sink(_k), "SELECT * FROM orders")


@REG.query("sink_modes", "SELECT * FROM nation UNION ALL SELECT * FROM nation")
def sink_modes(spark, d):
    """Overwrite, then append to a relation."""
    path = scratch(spark, "sink")
    df = fx.table(spark, d, "nation")
    for mode in ("append", "overwrite", "append"):
        scan.write(df, "pageheap", path, fx.SPECS["nation"], mode=mode)
    return scan.scan(spark, "pageheap", path)


@REG.query("sink_jdbc", "SELECT * FROM nation")
def sink_jdbc(spark, d):
    from pagelift import wire

    url = wire.load_jdbc(fx.direct(spark, d, "nation", "pageheap"), f"{scratch(spark, 'sink')}/nation.jar", "nation")
    r = wire.jdbc(spark, url, "nation", 1000)
    return r.select(*(F.col(c).alias(c.lower()) for c in r.columns))


@REG.query("src_jdbc", "SELECT l_linenumber, count(*) AS n, max(l_quantity) AS top FROM lineitem GROUP BY l_linenumber")
def src_jdbc(spark, d):
    """A query that the server runs: groups cross the protocol, not rows."""
    from pagelift.workloads.scans import jdbc_lineitem

    groups = '(SELECT "l_linenumber", COUNT(*) AS "n", MAX("l_quantity") AS "top" FROM lineitem GROUP BY "l_linenumber") t'
    return jdbc_lineitem(spark, d, fetchsize=100, relation=groups).withColumn("n", F.col("n").cast("long"))


@REG.query("src_jdbc_partitioned", "SELECT l_orderkey, l_linenumber FROM lineitem")
def src_jdbc_partitioned(spark, d):
    """A connection for each of several given conditions."""
    from pagelift.workloads.scans import jdbc_address

    parts = ['"l_linenumber" <= 2 OR "l_linenumber" IS NULL', '"l_linenumber" BETWEEN 3 AND 4', '"l_linenumber" > 4']
    r = spark.read.jdbc(jdbc_address(spark, d), "lineitem", predicates=parts, properties={"driver": "org.apache.derby.jdbc.EmbeddedDriver"})
    return r.select("l_orderkey", "l_linenumber")


for _k in ("pageheap", "pagetree"):

    def _view(spark, d, kind=_k):
        path = fx.base(spark, d, "customer", kind)
        spark.sql(f"CREATE OR REPLACE TEMPORARY VIEW pl_view_{kind} USING {kind} OPTIONS (path '{path}')")
        return spark.sql(f"SELECT c_custkey, c_name FROM pl_view_{kind} WHERE c_nationkey < 10")

    REG.add(f"src_{_k}_sql", _view, "SELECT c_custkey, c_name FROM customer WHERE c_nationkey < 10")


@REG.query("src_glob_union", "SELECT * FROM nation UNION ALL SELECT * FROM nation")
def src_glob_union(spark, d):
    path = fx.base(spark, d, "nation", "pageheap")
    return scan.scan(spark, "pageheap", [path, path])


# -- projection and filter

many("proj", {
    "select": "SELECT l_orderkey, l_tax FROM {lineitem}",
    "compute": f"SELECT l_orderkey, {CENTS} * l_linenumber AS x FROM {{lineitem}}",
    "rename": "SELECT l_orderkey AS k, l_returnflag AS f FROM {lineitem}",
    "cast": "SELECT CAST(l_quantity AS BIGINT) AS q, CAST(l_orderkey AS VARCHAR(20)) AS k FROM {lineitem}",
    "case": "SELECT l_orderkey, CASE WHEN l_quantity > 40 THEN 'many' WHEN l_quantity > 10 THEN 'some' ELSE 'few' END AS c FROM {lineitem}",
    "distinct": "SELECT DISTINCT l_returnflag, l_linestatus FROM {lineitem}",
})
EV_NULL = "(SELECT event_id, CASE WHEN event_id % 3 = 0 THEN NULL ELSE event_type END AS e FROM {events})"
many("flt", {
    "compare": "SELECT l_orderkey, l_partkey FROM {lineitem} WHERE l_quantity >= 45 AND l_partkey <> 7",
    "between": "SELECT l_orderkey FROM {lineitem} WHERE l_quantity BETWEEN 10 AND 11",
    "in": "SELECT p_partkey FROM {part} WHERE p_type IN ('PROMO', 'LARGE')",
    "like": "SELECT p_partkey FROM {part} WHERE p_name LIKE 'blue%'",
    "rlike": ("SELECT p_partkey FROM {part} WHERE p_name RLIKE '^(red|small) .*g'", "SELECT p_partkey FROM {part} WHERE regexp_matches(p_name, '^(red|small) .*g')"),
    "or": "SELECT p_partkey FROM {part} WHERE p_size < 5 OR p_brand = 'Brand#12'",
    "not": "SELECT p_partkey FROM {part} WHERE NOT (p_size < 25)",
    "null": f"SELECT event_id FROM {EV_NULL} t WHERE e IS NULL",
    "null_safe_eq": (f"SELECT event_id FROM {EV_NULL} t WHERE e <=> NULL OR e = 'click'", f"SELECT event_id FROM {EV_NULL} t WHERE e IS NOT DISTINCT FROM NULL OR e = 'click'"),
})

# -- joins

for _n, _h in (("hash_inner", "SHUFFLE_HASH(l)"), ("sort_merge", "MERGE(l)")):
    sql(f"join_{_n}", f"SELECT /*+ {_h} */ o_orderkey, l_partkey, l_linenumber FROM {{orders}} o JOIN {{lineitem}} l ON o_orderkey = l_orderkey", "SELECT o_orderkey, l_partkey, l_linenumber FROM {orders} o JOIN {lineitem} l ON o_orderkey = l_orderkey")
many("join", {
    "broadcast": ("SELECT /*+ BROADCAST(n) */ s_name, n_name FROM {supplier} JOIN {nation} n ON s_nationkey = n_nationkey", "SELECT s_name, n_name FROM {supplier} JOIN {nation} n ON s_nationkey = n_nationkey"),
    "left": "SELECT o_orderkey, l_partkey FROM {orders} LEFT JOIN {lineitem} ON o_orderkey = l_orderkey AND l_quantity > 49",
    "right": "SELECT o_orderkey, l_partkey FROM {lineitem} RIGHT JOIN {orders} ON o_orderkey = l_orderkey AND l_quantity > 49",
    "full": "SELECT c_custkey, s_suppkey FROM {customer} FULL JOIN {supplier} ON c_custkey = s_suppkey * 3",
    "semi": ("SELECT o_orderkey FROM {orders} LEFT SEMI JOIN {lineitem} ON o_orderkey = l_orderkey", "SELECT o_orderkey FROM {orders} WHERE o_orderkey IN (SELECT l_orderkey FROM {lineitem})"),
    "anti": ("SELECT o_orderkey FROM {orders} LEFT ANTI JOIN {lineitem} ON o_orderkey = l_orderkey", "SELECT o_orderkey FROM {orders} WHERE o_orderkey NOT IN (SELECT l_orderkey FROM {lineitem})"),
    "cross": "SELECT a.r_name AS a, b.r_name AS b FROM {region} a CROSS JOIN {region} b",
    "theta": ("SELECT /*+ BROADCAST(r) */ s_suppkey, r_regionkey FROM {supplier} JOIN {region} r ON s_nationkey > 4 * r_regionkey AND s_nationkey < 4 * r_regionkey + 9", "SELECT s_suppkey, r_regionkey FROM {supplier} JOIN {region} r ON s_nationkey > 4 * r_regionkey AND s_nationkey < 4 * r_regionkey + 9"),
    "self": "SELECT a.n_name AS a, b.n_name AS b FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey",
    "multiway": "SELECT r_name, count(*) AS n FROM {region} JOIN {nation} ON r_regionkey = n_regionkey JOIN {customer} ON c_nationkey = n_nationkey JOIN {orders} ON o_custkey = c_custkey JOIN {lineitem} ON l_orderkey = o_orderkey JOIN {part} ON p_partkey = l_partkey GROUP BY r_name",
})


@REG.query("join_range", "SELECT a.event_id AS purchase, b.event_id AS other FROM events a JOIN events b ON b.ts BETWEEN a.ts AND a.ts + INTERVAL 10 MINUTE WHERE a.event_type = 'purchase'")
def join_range(spark, d):
    e = fx.direct(spark, d, "events", "pageheap").select("event_id", "ts", "event_type")
    points = e.select(F.col("event_id").alias("other"), F.col("ts").alias("at"))
    spans = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("ts").alias("low"), (F.col("ts") + F.expr("INTERVAL 10 MINUTES")).alias("high"))
    return ranges.range_join(spans, points, "low", "high", "at", 600).select("purchase", "other")


@REG.query("join_interval", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 30 MINUTE WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def join_interval(spark, d):
    e = fx.direct(spark, d, "events", "pageheap").select("event_id", "ts", "event_type", "user_id")
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("from_ts"))
    b = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("at"))
    return a.join(b, "user_id").where("at BETWEEN from_ts AND from_ts + INTERVAL 30 MINUTES").select("click", "purchase")


@REG.query("join_asof", "SELECT a.event_id AS purchase, (SELECT max(b.ts) FROM events b WHERE b.event_type = 'click' AND b.user_id = a.user_id AND b.ts <= a.ts) AS click_ts FROM events a WHERE a.event_type = 'purchase'")
def join_asof(spark, d):
    e = fx.direct(spark, d, "events", "pageheap").select("event_id", "ts", "event_type", "user_id")
    return ranges.asof_join(e.where("event_type = 'purchase'"), e.where("event_type = 'click'").select("user_id", "ts", F.col("ts").alias("click_ts")), "user_id", "ts", ["click_ts"]).select(F.col("event_id").alias("purchase"), "click_ts")


# -- aggregation

G = "l_returnflag, l_linestatus, CAST(year(l_shipdate) AS INT) AS y"
many("agg", {
    "hash": f"SELECT l_returnflag, CAST(sum({CENTS}) AS BIGINT) AS s, count(*) AS n FROM {{lineitem}} GROUP BY l_returnflag",
    "sort": "SELECT p_type, max(p_name) AS top, min(p_name) AS low FROM {part} GROUP BY p_type",
    "global": f"SELECT CAST(sum({CENTS}) AS BIGINT) AS s, min(l_quantity) AS a, max(l_quantity) AS b, count(*) AS n FROM {{lineitem}}",
    "distinct": "SELECT count(DISTINCT l_partkey) AS n FROM {lineitem}",
    "multi_distinct": "SELECT l_returnflag, count(DISTINCT l_partkey) AS p, count(DISTINCT l_suppkey) AS s FROM {lineitem} GROUP BY l_returnflag",
    "rollup": f"SELECT l_returnflag, l_linestatus, y, count(*) AS n FROM (SELECT {G} FROM {{lineitem}}) t GROUP BY ROLLUP (l_returnflag, l_linestatus, y)",
    "cube": f"SELECT l_returnflag, l_linestatus, y, count(*) AS n FROM (SELECT {G} FROM {{lineitem}}) t GROUP BY CUBE (l_returnflag, l_linestatus, y)",
    "grouping_sets": f"SELECT l_returnflag, l_linestatus, y, count(*) AS n FROM (SELECT {G} FROM {{lineitem}}) t GROUP BY GROUPING SETS ((l_returnflag, y), (l_linestatus), ())",
    "filter": "SELECT l_returnflag, count(*) FILTER (WHERE l_quantity > 25) AS big, count(*) AS n FROM {lineitem} GROUP BY l_returnflag",
    "having": "SELECT l_suppkey, count(*) AS n FROM {lineitem} GROUP BY l_suppkey HAVING count(*) > 590",
    "percentile": ("SELECT l_returnflag, percentile(l_quantity, 0.5) AS p FROM {lineitem} GROUP BY l_returnflag", "SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS p FROM {lineitem} GROUP BY l_returnflag"),
    "stddev_corr": "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS s, round(corr(l_quantity, l_linenumber), 6) AS c FROM {lineitem} GROUP BY l_returnflag",
    "collect": ("SELECT n_regionkey, array_join(array_sort(collect_list(n_name)), ',') AS names FROM {nation} GROUP BY n_regionkey", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM {nation} GROUP BY n_regionkey"),
    "minmax_by": ("SELECT p_type, max_by(p_partkey, struct(p_retailprice, p_partkey)) AS top FROM {part} GROUP BY p_type", "SELECT p_type, arg_max(p_partkey, (p_retailprice, p_partkey)) AS top FROM {part} GROUP BY p_type"),
    "bool": "SELECT p_type, bool_and(p_size > 1) AS every, bool_or(p_size = 50) AS some FROM {part} GROUP BY p_type",
    "count_if": ("SELECT p_type, count_if(p_size > 25) AS n FROM {part} GROUP BY p_type", "SELECT p_type, CAST(count_if(p_size > 25) AS BIGINT) AS n FROM {part} GROUP BY p_type"),
})


@REG.query("agg_pivot", "SELECT l_linestatus, count(*) FILTER (WHERE l_returnflag = 'A') AS a, count(*) FILTER (WHERE l_returnflag = 'N') AS n, count(*) FILTER (WHERE l_returnflag = 'R') AS r FROM lineitem GROUP BY l_linestatus")
def agg_pivot(spark, d):
    return fx.direct(spark, d, "lineitem", "pageheap").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).count().fillna(0).toDF("l_linestatus", "a", "n", "r")


@REG.query("agg_approx_distinct", "SELECT count(DISTINCT l_partkey) AS exact, true AS near FROM lineitem")
def agg_approx_distinct(spark, d):
    """The exact number, and whether the estimate is within three of its standard errors."""
    df = fx.direct(spark, d, "lineitem", "pageheap", columns=["l_partkey"])
    return df.agg(F.approx_count_distinct("l_partkey", 0.02).alias("estimate"), F.count_distinct("l_partkey").alias("exact")).select("exact", (F.abs(F.col("estimate") - F.col("exact")) <= 0.06 * F.col("exact")).alias("near"))


# -- windows

W = "PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"
OC = "CAST(round(o_totalprice * 100) AS BIGINT)"
EW = "PARTITION BY user_id ORDER BY ts, event_id"
many("win", {
    "row_number": f"SELECT o_orderkey, CAST(row_number() OVER ({W}) AS BIGINT) AS x FROM {{orders}}",
    "rank": "SELECT o_orderkey, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS BIGINT) AS x FROM {orders}",
    "dense_rank": "SELECT o_orderkey, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS BIGINT) AS x FROM {orders}",
    "percent_rank": f"SELECT o_orderkey, round(percent_rank() OVER ({W}), 9) AS x FROM {{orders}}",
    "cume_dist": f"SELECT o_orderkey, round(cume_dist() OVER ({W}), 9) AS x FROM {{orders}}",
    "ntile": f"SELECT o_orderkey, CAST(ntile(4) OVER ({W}) AS BIGINT) AS x FROM {{orders}}",
    "lag_lead": f"SELECT event_id, lag(event_type) OVER ({EW}) AS a, lead(event_type, 2) OVER ({EW}) AS b FROM {{events}}",
    "first_last": f"SELECT event_id, first_value(event_id) OVER ({EW}) AS a, last_value(event_id) OVER ({EW} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS b FROM {{events}}",
    "nth_value": f"SELECT event_id, nth_value(event_id, 3) OVER ({EW}) AS a FROM {{events}}",
    "rows_running": f"SELECT o_orderkey, CAST(sum({OC}) OVER ({W} ROWS UNBOUNDED PRECEDING) AS BIGINT) AS x FROM {{orders}}",
    "rows_sliding": f"SELECT o_orderkey, CAST(sum({OC}) OVER ({W} ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS x FROM {{orders}}",
    "range_interval": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM {events}",
    "unbounded": f"SELECT o_orderkey, CAST(sum({OC}) OVER (PARTITION BY o_custkey) AS BIGINT) AS x FROM {{orders}}",
})

# -- sort, limit, sets, subqueries

many("sort", {
    "global": "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey",
    "nulls_first": f"SELECT event_id, e FROM {EV_NULL} t ORDER BY e NULLS FIRST, event_id",
    "multi": "SELECT p_partkey, p_type, p_size FROM {part} ORDER BY p_type, p_size DESC, p_partkey",
})
sql("limit", "SELECT o_orderkey FROM {orders} ORDER BY o_orderkey LIMIT 17")
sql("offset", "SELECT o_orderkey FROM {orders} ORDER BY o_orderkey LIMIT 17 OFFSET 100")
sql("topk_global", "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
sql("topk_group", f"SELECT o_custkey, o_orderkey, r FROM (SELECT o_custkey, o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY {OC} DESC, o_orderkey) AS BIGINT) AS r FROM {{orders}}) t WHERE r <= 3")
A, B = "SELECT o_orderkey AS k FROM {orders} WHERE o_orderkey % 3 = 0", "SELECT l_orderkey AS k FROM {lineitem} WHERE l_orderkey % 2 = 0"
for _n, _op in (("union_all", "UNION ALL"), ("union", "UNION"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    sql(f"set_{_n}", f"({A}) {_op} ({B})")
many("sub", {
    "scalar": "SELECT o_orderkey FROM {orders} WHERE o_totalprice > (SELECT max(o_totalprice) FROM {orders}) * 0.99",
    "in": "SELECT c_custkey FROM {customer} WHERE c_custkey IN (SELECT o_custkey FROM {orders} WHERE o_orderstatus = 'F')",
    "exists": "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')",
    "correlated": "SELECT o_orderkey FROM {orders} o WHERE o_totalprice = (SELECT max(i.o_totalprice) FROM {orders} i WHERE i.o_custkey = o.o_custkey)",
})
sql("cte", "WITH a AS (SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey), b AS (SELECT max(n) AS m FROM a) SELECT o_custkey, n FROM a JOIN b ON n = m")

# -- functions

many("fn", {
    "substr": "SELECT p_partkey, substr(p_name, 2, 4) AS x FROM {part}",
    "concat": "SELECT p_partkey, concat(p_name, '/', p_brand) AS x FROM {part}",
    "upper_lower": "SELECT p_partkey, upper(p_name) AS a, lower(p_brand) AS b FROM {part}",
    "trim_pad": "SELECT p_partkey, lpad(p_name, 20, '*') AS a, rtrim(concat(p_type, '  ')) AS b FROM {part}",
    "length_bytes": ("SELECT doc_id, CAST(length(text) AS BIGINT) AS c, CAST(octet_length(text) AS BIGINT) AS b FROM {documents}", "SELECT doc_id, CAST(length(text) AS BIGINT) AS c, CAST(strlen(text) AS BIGINT) AS b FROM {documents}"),
    "replace": "SELECT p_partkey, replace(p_name, 'e', 'E') AS x FROM {part}",
    "regexp_extract": "SELECT p_partkey, regexp_extract(p_brand, '#([0-9]+)', 1) AS x FROM {part}",
    "split": ("SELECT p_partkey, split(p_name, ' ')[1] AS x FROM {part}", "SELECT p_partkey, string_split(p_name, ' ')[2] AS x FROM {part}"),
    "date_trunc": "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS x FROM {orders}",
    "extract": "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(dayofmonth(o_orderdate) AS INT) AS dd FROM {orders}",
    "datediff": ("SELECT o_orderkey, CAST(datediff(DATE '2002-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) AS x FROM {orders}", "SELECT o_orderkey, CAST(datediff('day', CAST(o_orderdate AS DATE), DATE '2002-01-01') AS BIGINT) AS x FROM {orders}"),
    "date_add": ("SELECT o_orderkey, date_add(CAST(o_orderdate AS DATE), 10) AS x FROM {orders}", "SELECT o_orderkey, CAST(CAST(o_orderdate AS DATE) + 10 AS DATE) AS x FROM {orders}"),
    "format": ("SELECT o_orderkey, date_format(o_orderdate, 'yyyy-MM') AS x FROM {orders}", "SELECT o_orderkey, strftime(o_orderdate, '%Y-%m') AS x FROM {orders}"),
    "epoch": ("SELECT event_id, unix_micros(CAST(ts AS TIMESTAMP_LTZ)) AS x FROM {events}", "SELECT event_id, epoch_us(ts) AS x FROM {events}"),
    "round": "SELECT c_custkey, round(c_acctbal, 0) AS a, CAST(floor(c_acctbal) AS BIGINT) AS b, CAST(ceil(c_acctbal) AS BIGINT) AS c FROM {customer}",
    "mod": "SELECT c_custkey, c_custkey % 7 AS a FROM {customer}",
    "abs_sign": "SELECT c_custkey, abs(c_acctbal) AS a, CAST(sign(c_acctbal) AS INT) AS b FROM {customer}",
    "power_log": "SELECT c_custkey, round(power(c_custkey, 2), 0) AS a, round(ln(c_custkey + 1), 9) AS b FROM {customer}",
    "greatest_least": "SELECT c_custkey, greatest(c_custkey, 100, c_nationkey) AS a, least(c_custkey, 100, c_nationkey) AS b FROM {customer}",
    "bit_ops": ("SELECT c_custkey, c_custkey & 12 AS a, c_custkey | 3 AS b, c_custkey ^ 5 AS c FROM {customer}", "SELECT c_custkey, c_custkey & 12 AS a, c_custkey | 3 AS b, xor(c_custkey, 5) AS c FROM {customer}"),
    "array_ops": ("SELECT p_partkey, CAST(size(split(p_name, ' ')) AS BIGINT) AS n, array_contains(split(p_name, ' '), 'blue') AS b FROM {part}", "SELECT p_partkey, CAST(len(string_split(p_name, ' ')) AS BIGINT) AS n, list_contains(string_split(p_name, ' '), 'blue') AS b FROM {part}"),
    "explode": ("SELECT p_partkey, explode(split(p_name, ' ')) AS w FROM {part}", "SELECT p_partkey, unnest(string_split(p_name, ' ')) AS w FROM {part}"),
    "transform_filter": ("SELECT p_partkey, array_join(transform(filter(split(p_name, ' '), x -> length(x) > 3), x -> upper(x)), '-') AS x FROM {part}", "SELECT p_partkey, array_to_string(list_transform(list_filter(string_split(p_name, ' '), lambda x: length(x) > 3), lambda x: upper(x)), '-') AS x FROM {part}"),
    "map": ("SELECT p_partkey, map('t', p_type, 'b', p_brand)['b'] AS x FROM {part}", "SELECT p_partkey, p_brand AS x FROM {part}"),
    "get_json": ("SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM {events}", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM {events}"),
    "from_json": ("SELECT event_id, from_json(props, 'k BIGINT').k AS k FROM {events}", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM {events}"),
    "struct": ("SELECT p_partkey, named_struct('a', p_size, 'b', p_type).b AS x FROM {part}", "SELECT p_partkey, p_type AS x FROM {part}"),
    "md5": "SELECT c_custkey, md5(c_name) AS x FROM {customer}",
    "sha2": ("SELECT c_custkey, sha2(c_name, 256) AS x FROM {customer}", "SELECT c_custkey, sha256(c_name) AS x FROM {customer}"),
})

# -- what long text and binary values are good for after the page format

sql("doc_exact_dups", "SELECT md5(text) AS h, count(*) AS n, min(doc_id) AS first_doc FROM {documents} GROUP BY md5(text) HAVING count(*) > 1")
sql("conv_turn_counts", "SELECT conv_id, count(*) AS turns, count(DISTINCT role) AS roles FROM {conversations} GROUP BY conv_id")
sql("page_url_hosts", "SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, count(*) AS n FROM {pages} GROUP BY regexp_extract(url, '^https?://([^/]+)', 1)")


def _vectors(spark, d) -> DataFrame:
    from pagelift.workloads.scans import REG as SCANS

    return SCANS.queries["heap_scan_embeddings"](spark, d)


@REG.query("emb_norm", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))), 4) AS norm FROM embeddings")
def emb_norm(spark, d):
    return _vectors(spark, d).select("vec_id", F.round(F.sqrt(F.aggregate(F.col("embedding"), F.lit(0.0), lambda a, x: a + x.cast("double") * x)), 4).alias("norm"))


@REG.query("emb_cosine_top1", """WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS q FROM embeddings),
s AS (SELECT a.vec_id, b.vec_id AS nearest, CAST(list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2])) AS BIGINT) AS score FROM v a JOIN v b ON a.vec_id IN (SELECT min(vec_id) FROM embeddings GROUP BY label) AND a.vec_id <> b.vec_id)
SELECT vec_id, arg_min(nearest, (-score, nearest)) AS nearest, max(score) AS score FROM s GROUP BY vec_id""")
def emb_cosine_top1(spark, d):
    """Nearest other vectors of each label's first one, by whole-number inner products of the unit vectors: the queries
    are a broadcast block of a row a label against all rows."""
    v = _vectors(spark, d).select("vec_id", "label", F.transform("embedding", lambda x: F.floor(64 * x.cast("double"))).alias("q"))
    asked = v.groupBy("label").agg(F.min_by(F.struct("vec_id", "q"), "vec_id").alias("f")).select(F.col("f.vec_id").alias("k"), F.col("f.q").alias("p"))
    score = F.aggregate(F.zip_with("p", "q", lambda a, b: a * b), F.lit(0).cast("long"), lambda a, x: a + x)
    pairs = v.join(F.broadcast(asked), F.col("k") != F.col("vec_id")).select(F.col("k"), "vec_id", score.alias("score"))
    return pairs.groupBy("k").agg(F.min_by("vec_id", F.struct(-F.col("score"), "vec_id")).alias("nearest"), F.max("score").alias("score")).withColumnRenamed("k", "vec_id")


@REG.query("emb_label_counts", "SELECT label, count(*) AS n FROM embeddings GROUP BY label")
def emb_label_counts(spark, d):
    return _vectors(spark, d).groupBy("label").agg(F.count(F.lit(1)).alias("n"))
