"""Page functions and streams as queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from pagelift import scan
from pagelift.functions import pages as fn
from pagelift.streaming import tails
from pagelift.workloads import fixtures as fx
from pagelift.workloads.registry import Registry

REG = Registry()


def scalar(name, table, key, column, kind, sql, prepare=None):
    def run(spark, d):
        scan.register(spark)
        df = fx.direct(spark, d, table, "pageheap")
        raw = fn.encoded(prepare(df) if prepare else df, key, column, kind)
        return raw.select(key, fn.SCALARS[name]("raw").alias("v"))

    REG.add(name, run, sql)


day = lambda df: df.withColumn("o_orderdate", F.col("o_orderdate").cast("date"))
scalar("udf_numeric", "customer", "c_custkey", "c_acctbal", "numeric", "SELECT c_custkey, c_acctbal AS v FROM customer")
scalar("udf_packed_decimal", "customer", "c_custkey", "c_acctbal", "packed_decimal", "SELECT c_custkey, c_acctbal AS v FROM customer")
scalar("udf_packed_date", "orders", "o_orderkey", "o_orderdate", "packed_date", "SELECT o_orderkey, CAST(o_orderdate AS DATE) AS v FROM orders", day)
scalar("udf_heap_date", "orders", "o_orderkey", "o_orderdate", "heap_date", "SELECT o_orderkey, CAST(o_orderdate AS DATE) AS v FROM orders", day)
scalar("udf_varlena", "part", "p_partkey", "p_name", "varlena", "SELECT p_partkey, p_name AS v FROM part")
scalar("udf_ordered_float", "events", "event_id", "value", "ordered_float", "SELECT event_id, value AS v FROM events")
scalar("udf_biased_int", "events", "event_id", "user_id", "biased_int", "SELECT event_id, user_id AS v FROM events")

ND = " UNION ALL ".join(f"SELECT '{c}' AS name, count({c}) AS n, count(DISTINCT {c}) AS ndv, min(CAST({c} AS VARCHAR)) AS low, max(CAST({c} AS VARCHAR)) AS high FROM orders" for c in ("o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority"))


@REG.query("udaf_column_profile", ND)
def column_profile(spark, d):
    scan.register(spark)
    return fn.profile(fx.direct(spark, d, "orders", "pageheap", columns=["o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority"]))


def blocks(spark, d, table, kind):
    """A relation's pages in blocks of bounded size, as binary values."""
    scan.register(spark)
    fn.register(spark)
    return scan.scan(spark, kind, fx.base(spark, d, table, kind), **{"as": "blocks"})


@REG.query("udtf_page_inspect", "SELECT CAST(count(*) AS BIGINT) AS n_rows, true AS whole FROM orders")
def page_inspect(spark, d):
    """Line pointers of all pages; each page's directory ends where its header says."""
    blocks(spark, d, "orders", "pageheap").createOrReplaceTempView("pl_page_blocks")
    return spark.sql("SELECT CAST(sum(normal) AS BIGINT) AS n_rows, bool_and(lower = 24 + 4 * pointers AND lower <= upper AND special = 8192) AS whole FROM pl_page_blocks, LATERAL udtf_page_inspect(content) i")


@REG.query("udtf_record_inspect", "SELECT CAST(count(*) AS BIGINT) AS n_rows, CAST(0 AS BIGINT) AS others FROM orders")
def record_inspect(spark, d):
    """Records on leaf pages of the clustered index, and on other pages."""
    blocks(spark, d, "orders", "pagetree").createOrReplaceTempView("pl_tree_blocks")
    return spark.sql("SELECT CAST(sum(IF(level = 0 AND index_id = 40, records, 0)) AS BIGINT) AS n_rows, CAST(sum(IF(level = 0 AND index_id = 40, 0, records)) AS BIGINT) AS others FROM pl_tree_blocks, LATERAL udtf_record_inspect(content) i")


@REG.query("udtf_brin_inspect", "SELECT true AS consecutive, true AS one_width")
def brin_inspect(spark, d):
    """The ranges of an index follow each other and are of one width."""
    from pagelift.workloads.scans import indexed

    scan.register(spark)
    fn.register(spark)
    path, _ = indexed(spark, d, "events", "ts")
    spark.read.format("binaryFile").load(f"{path}/index.brin").createOrReplaceTempView("pl_index_files")
    return spark.sql("SELECT count(*) = max(range_no) + 1 AND min(range_no) = 0 AS consecutive, min(pages_per_range) = 8 AND max(pages_per_range) = 8 AS one_width FROM pl_index_files, LATERAL udtf_brin_inspect(content) i")


@REG.query("src_pages_raw", "SELECT CAST(count(*) AS BIGINT) AS n_rows, true AS whole FROM lineitem")
def src_pages_raw(spark, d):
    """Page headers as columns, read block by block."""
    scan.register(spark)
    pages = scan.scan(spark, "pageheap", fx.base(spark, d, "lineitem", "pageheap"), **{"as": "headers"})
    return pages.selectExpr("CAST(sum(normal) AS BIGINT) AS n_rows", "bool_and(lower = 24 + 4 * pointers AND lower <= upper) AND count(DISTINCT page) = max(page) + 1 AS whole")


# -- streams

EVENTS = "SELECT * FROM events"


def grown(spark, d, parts: int = 4) -> str:
    """The events, written in appends."""
    scan.register(spark)
    path = f"{tails.place(spark)}/events"
    df = fx.table(spark, d, "events")
    top = df.agg(F.max("event_id")).first()[0] + 1
    for k in range(parts):
        scan.write(df.where((F.col("event_id") >= top * k // parts) & (F.col("event_id") < top * (k + 1) // parts)).coalesce(1), "pageheap", path, fx.SPECS["events"], mode="append")
    return path


def stream(spark, d):
    return tails.tail(spark, fx.base(spark, d, "events", "pageheap"))


def bounded(df):
    """A window as two columns."""
    return tails.naive(df.select(F.col("w.start").alias("start_ts"), F.col("w.end").alias("end_ts"), *[c for c in df.columns if c != "w"]))


@REG.query("st_tail_last_page", EVENTS)
def st_tail_last_page(spark, d):
    """The relation's last page is filled up between two runs, and pages follow it: each row comes once."""
    scan.register(spark)
    path, at = f"{tails.place(spark)}/filled", tails.place(spark)
    ordered = fx.table(spark, d, "events").coalesce(1).sortWithinPartitions("event_id")
    half = fx.table(spark, d, "events").agg(F.floor(F.avg("event_id"))).first()[0]
    # the same rows in the same pages, but the first run sees only those up to the half
    scan.write(ordered.where(F.col("event_id") <= half), "pageheap", path, fx.SPECS["events"])
    tails.finish(tails.tail(spark, path), at=at)
    whole = f"{path}-whole"
    scan.write(ordered, "pageheap", whole, fx.SPECS["events"])
    tails.replace_files(whole, path)
    return tails.naive(tails.finish(tails.tail(spark, path), at=at))


REG.add("st_tail", lambda s, d: tails.naive(tails.finish(tails.tail(s, grown(s, d)))), EVENTS)
CENTS = "CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents"
REG.add("st_tumbling", lambda s, d: bounded(tails.finish(tails.windowed(stream(s, d), "ts", "10 minutes", F.window("ts", "1 hour").alias("w"), "event_type"), "complete")),
        f"SELECT date_trunc('hour', ts) AS start_ts, date_trunc('hour', ts) + INTERVAL 1 HOUR AS end_ts, event_type, count(*) AS n, {CENTS} FROM events GROUP BY 1, 2, 3")
REG.add("st_sliding", lambda s, d: bounded(tails.finish(tails.windowed(stream(s, d), "ts", "10 minutes", F.window("ts", "2 hours", "1 hour").alias("w")), "complete")),
        f"SELECT h - INTERVAL 1 HOUR * k AS start_ts, h - INTERVAL 1 HOUR * k + INTERVAL 2 HOUR AS end_ts, count(*) AS n, {CENTS} FROM (SELECT date_trunc('hour', ts) AS h, value FROM events) e, (SELECT unnest([0, 1]) AS k) o GROUP BY 1, 2")
REG.add("st_session", lambda s, d: bounded(tails.finish(tails.windowed(stream(s, d), "ts", "10 minutes", F.session_window("ts", "2 hours").alias("w"), "user_id"), "complete")),
        f"""WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g)
SELECT min(ts) AS start_ts, max(ts) + INTERVAL 2 HOUR AS end_ts, user_id, count(*) AS n, {CENTS} FROM s GROUP BY user_id, sid""")  # fmt: skip
REG.add("st_dedup", lambda s, d: tails.naive(tails.finish(stream(s, d).withWatermark("ts", "10 minutes").dropDuplicatesWithinWatermark(["event_id"]))), EVENTS)


LATE = """WITH early AS (SELECT * FROM events WHERE event_id % 10 <> 0)
SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start_ts, CAST(date_trunc('day', ts) AS TIMESTAMP) + INTERVAL 1 DAY AS end_ts, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents
FROM early GROUP BY 1, 2 HAVING CAST(date_trunc('day', ts) AS TIMESTAMP) + INTERVAL 1 DAY <= (SELECT max(ts) FROM early) - INTERVAL 10 MINUTE"""


@REG.query("st_late_drop", LATE)
def st_late_drop(spark, d):
    """A tenth of the rows comes after the watermark has passed nearly all of their windows: those windows stay as they are."""
    path, at = f"{tails.place(spark)}/late", tails.place(spark)
    scan.register(spark)
    df = fx.table(spark, d, "events")
    for part in (df.where("event_id % 10 BETWEEN 1 AND 8"), df.where("event_id % 10 = 9"), df.where("event_id % 10 = 0")):
        scan.write(part.coalesce(1), "pageheap", path, fx.SPECS["events"], mode="append")
        done = tails.finish(tails.windowed(tails.tail(spark, path), "ts", "10 minutes", F.window("ts", "1 day").alias("w")), at=at)
    return bounded(done)


def with_state(spark, query, at=None):
    """Run a stateful query with the state store that it needs."""
    key = "spark.sql.streaming.stateStore.providerClass"
    old = spark.conf.get(key, None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return tails.finish(query, at=at)
    finally:
        spark.conf.set(key, old) if old else spark.conf.unset(key)


IDLE = """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g),
e AS (SELECT user_id, epoch_us(min(ts)) AS "first", epoch_us(max(ts)) AS "last", count(*) AS n FROM s GROUP BY user_id, sid)
SELECT * FROM e WHERE "last" < (SELECT epoch_us(max(ts)) FROM events WHERE event_id < (SELECT max(event_id) FROM events)) - 7200000000 - 600000000 OR "last" < (SELECT max(o."last") FROM e o WHERE o.user_id = e.user_id)"""


@REG.query("st_idle_sessions", IDLE)
def st_idle_sessions(spark, d):
    """Sessions that a timer or a later row has ended; those that may go on stay in the state."""
    scan.register(spark)
    path, at = f"{tails.place(spark)}/idle", tails.place(spark)
    df = fx.table(spark, d, "events")
    top = df.agg(F.max("event_id")).first()[0]
    for part in (df.where(F.col("event_id") < top), df.where(F.col("event_id") == top)):  # the first run's watermark ends sessions in the second
        scan.write(part.coalesce(1), "pageheap", path, fx.SPECS["events"], mode="append")
        rows = tails.tail(spark, path).withWatermark("ts", "10 minutes").select("user_id", "ts", F.unix_micros("ts").alias("micros"))
        out = with_state(spark, rows.groupBy("user_id").transformWithStateInPandas(tails.IdleSessions(7_200_000_000), "user_id long, first long, last long, n long", "Append", "EventTime"), at)
    return out


@REG.query("st_stateful", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def st_stateful(spark, d):
    done = with_state(spark, stream(spark, d).groupBy("user_id").transformWithStateInPandas(tails.RunningCount(), "user_id long, n long", "Append", "None"))
    return done.groupBy("user_id").agg(F.max("n").alias("n"))


REG.add("st_join_static", lambda s, d: tails.finish(stream(s, d).join(F.broadcast(fx.direct(s, d, "customer", "pageheap")), F.expr("user_id = c_custkey")).select("event_id", "c_name")), "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")


@REG.query("st_join_stream", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 30 MINUTE WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def st_join_stream(spark, d):
    a = stream(spark, d).where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", "10 minutes")
    b = stream(spark, d).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", "10 minutes")
    return tails.finish(a.join(b, F.expr("u1 = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL 30 MINUTES")).select("click", "purchase"))


@REG.query("st_foreach_batch", "SELECT event_id, event_type FROM events")
def st_foreach_batch(spark, d):
    at = tails.place(spark)

    def keep(batch, number):
        batch.select("event_id", "event_type").write.mode("overwrite").parquet(f"{at}/out/batch={number}")

    stream(spark, d).writeStream.foreachBatch(keep).option("checkpointLocation", f"{at}/c").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{at}/out").select("event_id", "event_type")
