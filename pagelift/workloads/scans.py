"""Scan, type, visibility, pruning and extraction workloads over page files made from the given tables."""

from __future__ import annotations

import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift import extract, scan, wire
from pagelift.plans import pages as plan
from pagelift.schema import StorageSchema
from pagelift.session import scratch
from pagelift.workloads import fixtures as fx
from pagelift.workloads.registry import Registry

REG = Registry()
q = REG.query
BOTH = ("pageheap", "pagetree")
SHORT = {"pageheap": "heap", "pagetree": "tree"}


def reread(spark: SparkSession, df: DataFrame) -> DataFrame:
    """Extract to Parquet and read that."""
    path = scratch(spark, "etl")
    df.write.parquet(path)
    return spark.read.parquet(path)


# -- extraction to Parquet, direct and by protocol


def _etl(kind):
    return lambda spark, d: reread(spark, fx.direct(spark, d, "lineitem", kind))


for _k in BOTH:
    REG.add(f"etl_{SHORT[_k]}_lineitem", _etl(_k), "SELECT * FROM lineitem")


def jdbc_address(spark: SparkSession, d: str) -> str:
    """The embedded database, with the lineitem table in it."""
    return wire.load_jdbc(fx.table(spark, d, "lineitem"), f"{fx.place(spark, d, 'jdbc', {'form': 'archive'})}.jar", "lineitem")


def jdbc_lineitem(spark: SparkSession, d: str, relation: str = "lineitem", **how) -> DataFrame:
    r = wire.jdbc(spark, jdbc_address(spark, d), relation, **how)
    return r.select(*(F.col(c).alias(c.lower()) for c in r.columns))


REG.add("etl_jdbc_lineitem", lambda s, d: reread(s, jdbc_lineitem(s, d, fetchsize=10_000)), "SELECT * FROM lineitem")
REG.add("jdbc_row_at_a_time", lambda s, d: reread(s, jdbc_lineitem(s, d, fetchsize=1)), "SELECT * FROM lineitem")
REG.add("jdbc_partitioned", lambda s, d: jdbc_lineitem(s, d, fetchsize=10_000, partition_column="L_ORDERKEY", bounds=wire.bounds(fx.table(s, d, "lineitem"), "l_orderkey")), "SELECT * FROM lineitem")
REG.add("jdbc_server_filter", lambda s, d: jdbc_lineitem(s, d, fetchsize=10_000).where("l_quantity >= 40 AND l_suppkey < 20"), "SELECT * FROM lineitem WHERE l_quantity >= 40 AND l_suppkey < 20")


def wire_lineitem(spark: SparkSession, d: str, text: bool) -> DataFrame:
    wire.register(scan.register(spark))
    path, spec = fx.place(spark, d, f"wire-{'text' if text else 'binary'}", {}), fx.SPECS["lineitem"]
    if not plan.exists(f"{path}/{plan.MANIFEST}"):
        wire.encode_copy(fx.table(spark, d, "lineitem").repartition(8), path, StorageSchema.parse(spec), text)
    return spark.read.format("wiretext" if text else "wirebinary").option("path", path).option("columns_spec", spec).load()


REG.add("etl_wire_binary_lineitem", lambda s, d: reread(s, wire_lineitem(s, d, False)), "SELECT * FROM lineitem")
REG.add("etl_wire_text_lineitem", lambda s, d: reread(s, wire_lineitem(s, d, True)), "SELECT * FROM lineitem")


@q("etl_rows_one_client", "SELECT * FROM lineitem")
def etl_rows_one_client(spark, d):
    """One client that takes rows of the text protocol one by one, as a database's own connector does: each becomes a tuple
    of values, then part of a batch, then of a Parquet file."""
    wire_lineitem(spark, d, True)
    schema = pa.schema([(c.name, c.arrow_type()) for c in StorageSchema.parse(fx.SPECS["lineitem"]).columns])
    parts = extract.row_batches(fx.place(spark, d, "wire-text", {}), fx.SPECS["lineitem"], text=True)
    at = f"{scratch(spark, 'etl')}/rows.parquet"
    fs, path = plan.file_system(at)
    fs.create_dir(path.rsplit("/", 1)[0], recursive=True)
    with fs.open_output_stream(path) as out, pq.ParquetWriter(out, schema) as w:
        for batch in parts:
            w.write_batch(batch)
    return spark.read.schema(StorageSchema.parse(fx.SPECS["lineitem"]).spark()).parquet(at)


def _consumed(kind, consumer):
    def run(spark, d):
        """One process from pages to Parquet, by a consumer other than Spark."""
        at = f"{scratch(spark, 'etl')}/{consumer}.parquet"
        plan.write_bytes(f"{at}.place", b"")  # makes the folder
        extract.etl(extract.batches(fx.base(spark, d, "lineitem", kind), kind), consumer, plan.file_system(at)[1])
        return spark.read.schema(StorageSchema.parse(fx.SPECS["lineitem"]).spark()).parquet(at)

    return run


for _k in BOTH:
    for _c in ("pyarrow", "duckdb"):
        REG.add(f"etl_{SHORT[_k]}_{_c}", _consumed(_k, _c), "SELECT * FROM lineitem")


@q("access_compare", "SELECT CAST(count(*) AS BIGINT) AS n_rows, CAST(0 AS BIGINT) AS only_direct, CAST(0 AS BIGINT) AS only_protocol FROM lineitem")
def access_compare(spark, d):
    """Rows of the direct scans that the protocol doesn't give, and the other way round: none."""
    a = fx.direct(spark, d, "lineitem", "pageheap")
    b = jdbc_lineitem(spark, d, fetchsize=10_000).select(*a.columns)
    one = a.groupBy(*a.columns).agg(F.count(F.lit(1)).alias("n1"))
    two = b.groupBy(*a.columns).agg(F.count(F.lit(1)).alias("n2"))
    both = one.join(two, a.columns, "full")
    n1, n2 = F.coalesce("n1", F.lit(0)), F.coalesce("n2", F.lit(0))
    return both.agg(F.sum(n1).alias("n_rows"), F.sum(F.greatest(n1 - n2, F.lit(0))).alias("only_direct"), F.sum(F.greatest(n2 - n1, F.lit(0))).alias("only_protocol"))


# -- whole tables both ways

for _t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "labels", "benchmark", "conversations", "documents", "pages"):
    for _k in BOTH:
        REG.add(f"{SHORT[_k]}_scan_{_t}", lambda s, d, t=_t, k=_k: fx.direct(s, d, t, k), f"SELECT * FROM {_t}")


def made(spark, d, label, kind, frame, spec, **options):
    """Scan of a fixture whose rows are made by an expression over a given table."""
    read = options.pop("read", {})
    return scan.scan(spark, kind, fx.ensure(spark, d, label, kind, lambda: frame, spec, recipe=label, **options), **read)


def _embeddings(kind):
    def run(spark, d):
        import pyarrow as pa
        import numpy as np

        def pack(batches):
            for b in batches:
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([np.array(x, "<f4").tobytes() for x in b.column(1).to_pylist()], pa.binary()), b.column(2)], names=["vec_id", "embedding", "label"])

        def unpack(batches):
            for b in batches:
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([np.frombuffer(x, "<f4").tolist() for x in b.column(1).to_pylist()], pa.list_(pa.float32())), b.column(2)], names=["vec_id", "embedding", "label"])

        raw = fx.table(spark, d, "embeddings").select("vec_id", "embedding", "label").mapInArrow(pack, "vec_id long, embedding binary, label int")
        return made(spark, d, "embeddings", kind, raw, fx.SPECS["embeddings"], pk=fx.KEYS["embeddings"] if kind == "pagetree" else ()).mapInArrow(unpack, "vec_id long, embedding array<float>, label int")

    return run


for _k in BOTH:
    REG.add(f"{SHORT[_k]}_scan_embeddings", _embeddings(_k), "SELECT vec_id, embedding, label FROM embeddings")

# -- variable width

q("heap_short_documents", "SELECT * FROM documents WHERE strlen(text) <= 7000")(
    lambda s, d: made(s, d, "short-documents", "pageheap", fx.table(s, d, "documents").where("octet_length(text) <= 7000"), fx.SPECS["documents"])
)
q("heap_varlena_boundary", "SELECT conv_id, turn, substr(text, 1, CAST(124 + (conv_id + turn) % 6 AS INTEGER)) AS t, CASE WHEN turn % 2 = 0 THEN '' ELSE 'é' END AS u FROM conversations")(
    lambda s, d: made(s, d, "varlena", "pageheap", fx.table(s, d, "conversations").select("conv_id", "turn", F.expr("substr(text, 1, cast(124 + (conv_id + turn) % 6 as int)) AS t"), F.expr("CASE WHEN turn % 2 = 0 THEN '' ELSE 'é' END AS u")), "conv_id:int8,turn:int8,t:text,u:text")
)
q("heap_bpchar_strip", "SELECT o_orderkey, rtrim(o_orderstatus) AS s, rtrim(o_orderpriority) AS p FROM orders")(
    lambda s, d: made(s, d, "bpchar", "pageheap", fx.table(s, d, "orders").select("o_orderkey", F.col("o_orderstatus").alias("s"), F.col("o_orderpriority").alias("p")), "o_orderkey:int8,s:bpchar(10),p:bpchar(40)")
)
q("tree_len_1byte", "SELECT p_partkey, p_name, p_type FROM part")(
    lambda s, d: made(s, d, "len1", "pagetree", fx.table(s, d, "part").select("p_partkey", "p_name", "p_type"), "p_partkey:int8!,p_name:varchar(255),p_type:varchar(25)", pk=("p_partkey",))
)
q("tree_len_2byte", "SELECT conv_id, turn, text FROM conversations")(
    lambda s, d: made(s, d, "len2", "pagetree", fx.table(s, d, "conversations").select("conv_id", "turn", "text"), "conv_id:int8!,turn:int8!,text:varchar(8000)", pk=("conv_id", "turn"))
)
q("tree_len_adaptive", "SELECT conv_id, turn, text FROM conversations")(
    lambda s, d: made(s, d, "len-adaptive", "pagetree", fx.table(s, d, "conversations").select("conv_id", "turn", "text"), "conv_id:int8!,turn:int8!,text:varchar(8000)", pk=("conv_id", "turn"), prefix="adaptive")
)

# -- all types, nulls

TYPES = "k:int8!,b:bool,i2:int2,i4:int4,i8:int8,f4:float4,f8:float8,d:date,t:timestamp,n:numeric(15,2),c:bpchar(3),v:varchar(40),x:text"
TYPE_EXPRS = [
    "o_orderkey AS k", "o_orderkey % 2 = 0 AS b", "CAST(o_custkey % 30000 - 15000 AS SMALLINT) AS i2", "CAST(o_custkey - 700 AS INT) AS i4", "o_orderkey * 1000003 - 5000000000 AS i8", "CAST(o_totalprice AS FLOAT) AS f4",
    "-o_totalprice AS f8", "CAST(o_orderdate AS DATE) AS d", "o_orderdate AS t", "o_totalprice AS n", "o_orderstatus AS c", "o_orderpriority AS v", "concat(o_orderstatus, '-', o_orderpriority) AS x",
]
TYPE_SQL = "SELECT o_orderkey AS k, o_orderkey % 2 = 0 AS b, CAST(o_custkey % 30000 - 15000 AS SMALLINT) AS i2, CAST(o_custkey - 700 AS INTEGER) AS i4, o_orderkey * 1000003 - 5000000000 AS i8, CAST(o_totalprice AS FLOAT) AS f4, -o_totalprice AS f8, CAST(o_orderdate AS DATE) AS d, o_orderdate AS t, o_totalprice AS n, o_orderstatus AS c, o_orderpriority AS v, concat(o_orderstatus, '-', o_orderpriority) AS x FROM orders"
NULL_COLS = "event_id, {0} AS ts, {1} AS user_id, {2} AS event_type, {3} AS value, {4} AS props"
NULL_EXPR = NULL_COLS.format(*(f"CASE WHEN event_id % 11 = 0 OR event_id % {m} = 1 THEN NULL ELSE {c} END" for c, m in (("ts", 2), ("user_id", 3), ("event_type", 4), ("value", 5), ("props", 7))))
for _k in BOTH:
    REG.add(f"{SHORT[_k]}_types_all", lambda s, d, k=_k: made(s, d, "types", k, fx.table(s, d, "orders").selectExpr(*TYPE_EXPRS), TYPES, pk=("k",) if k == "pagetree" else ()), TYPE_SQL)
    REG.add(f"{SHORT[_k]}_nulls", lambda s, d, k=_k: made(s, d, "nulls", k, fx.table(s, d, "events").selectExpr(*[x.strip() for x in _split(NULL_EXPR)]), fx.SPECS["events"], pk=("event_id",) if k == "pagetree" else ()), f"SELECT {NULL_EXPR} FROM events")


def _split(text: str) -> list[str]:
    """Select items of a list whose items have no commas of their own."""
    return text.split(",")


# -- visibility


def marked(spark, d, label, state, policy="delete_only", kind="pageheap"):
    rows = fx.table(spark, d, "orders").withColumn("__state", F.when(F.col("o_orderkey") % 7 == 0, state).otherwise(0).cast("short"))
    return made(spark, d, label, kind, rows, fx.SPECS["orders"], pk=("o_orderkey",) if kind == "pagetree" else (), read={"visibility": policy} if kind == "pageheap" else {})


LIVE = "SELECT * FROM orders WHERE o_orderkey % 7 <> 0"
REG.add("heap_deleted", lambda s, d: marked(s, d, "deleted", 1), LIVE)
REG.add("heap_deleted_shown", lambda s, d: marked(s, d, "deleted", 1, "none"), "SELECT * FROM orders")
REG.add("heap_lock_only", lambda s, d: marked(s, d, "locked", 2), "SELECT * FROM orders")
REG.add("heap_rolled_back_delete", lambda s, d: marked(s, d, "rolled-back", 3), "SELECT * FROM orders")
REG.add("heap_aborted_insert", lambda s, d: marked(s, d, "aborted", 4), "SELECT * FROM orders")
REG.add("heap_aborted_insert_hint", lambda s, d: marked(s, d, "aborted", 4, "insert_hint"), LIVE)
REG.add("tree_deleted", lambda s, d: marked(s, d, "deleted", 1, kind="pagetree"), LIVE)
REG.add("heap_dead_pointers", lambda s, d: made(s, d, "dead", "pageheap", fx.table(s, d, "nation"), fx.SPECS["nation"], dead_pointers=3), "SELECT * FROM nation")
REG.add("heap_multi_segment", lambda s, d: made(s, d, "segments", "pageheap", fx.table(s, d, "lineitem"), fx.SPECS["lineitem"], segment_pages=64, read={"split_bytes": 1 << 18}), "SELECT * FROM lineitem")
REG.add("tree_nonleaf_skipped", lambda s, d: made(s, d, "interior", "pagetree", fx.table(s, d, "orders"), fx.SPECS["orders"], pk=("o_orderkey",), interior_levels=3), "SELECT * FROM orders")
REG.add("tree_decoy_index", lambda s, d: made(s, d, "decoy", "pagetree", fx.table(s, d, "orders"), fx.SPECS["orders"], pk=("o_orderkey",), decoy_index=True), "SELECT * FROM orders")


def spelled_out(spark, d, table, hidden):
    """A tree whose columns the user gives in their order on disk, with the hidden bytes as raw ones."""
    key, spec = fx.KEYS[table], fx.SPECS[table]
    columns = StorageSchema.parse(spec, key)
    text = ",".join(columns.text([c]) for c in columns.physical())
    assert f"_hidden:raw({hidden})!" in text
    return scan.scan(spark, "pagetree", fx.base(spark, d, table, "pagetree"), columns_spec=text)


REG.add("tree_hidden_pk", lambda s, d: spelled_out(s, d, "orders", 13), "SELECT * FROM orders")
REG.add("tree_hidden_nopk", lambda s, d: spelled_out(s, d, "lineitem", 19), "SELECT * FROM lineitem")

# -- numbers and dates at their edges

NUM = "SELECT c_custkey, c_acctbal AS a, -c_acctbal AS m, CAST(0 AS DOUBLE) AS z, CAST(c_custkey * 10000 AS DOUBLE) AS w, c_acctbal * 100 AS h FROM customer"
NUM_EXPRS = ["c_custkey", "c_acctbal AS a", "-c_acctbal AS m", "CAST(0 AS DOUBLE) AS z", "CAST(c_custkey * 10000 AS DOUBLE) AS w", "c_acctbal * 100 AS h"]
NUM_SPEC = "c_custkey:int8,a:numeric(15,2),m:numeric(15,2),z:numeric(15,2),w:numeric(18,0),h:numeric(18,4)"


def _numbers(label, sql, exprs=None, **more):
    REG.add(label, lambda s, d: made(s, d, label, "pageheap", fx.table(s, d, "customer").selectExpr(*(exprs or NUM_EXPRS)).withColumn("h", F.round("h", 4)), NUM_SPEC, **more), sql.replace("c_acctbal * 100 AS h", "round(c_acctbal * 100, 4) AS h"))


_numbers("heap_numeric_short", NUM)
_numbers("heap_numeric_long", NUM, long_numeric=True)
REG.add("heap_numeric_negative", lambda s, d: made(s, d, "negative", "pageheap", fx.table(s, d, "customer").selectExpr("c_custkey", "-abs(c_acctbal) AS a"), "c_custkey:int8,a:numeric(15,2)").where("a <= 0"), "SELECT c_custkey, -abs(c_acctbal) AS a FROM customer")
for _k in BOTH:
    REG.add(f"{SHORT[_k]}_numeric_decimal", lambda s, d, k=_k: scan.scan(s, k, fx.base(s, d, "orders", k), columns=["o_orderkey", "o_totalprice"], numeric_as="decimal"), "SELECT o_orderkey, CAST(o_totalprice AS DECIMAL(15,2)) AS o_totalprice FROM orders")
EDGE_DATES = "o_orderkey, CAST(o_orderdate - INTERVAL 480 MONTH AS DATE) AS d, o_orderdate - INTERVAL 480 MONTH AS t, CAST(o_orderdate + INTERVAL 480 MONTH AS DATE) AS e"
DATE_SPEC = "o_orderkey:int8!,d:date,t:timestamp,e:date"
REG.add("heap_epoch_edges", lambda s, d: made(s, d, "epochs", "pageheap", fx.table(s, d, "orders").selectExpr(*_split(EDGE_DATES)), DATE_SPEC), f"SELECT {EDGE_DATES} FROM orders")
REG.add("tree_date", lambda s, d: made(s, d, "dates", "pagetree", fx.table(s, d, "orders").selectExpr(*_split(EDGE_DATES)), DATE_SPEC, pk=("o_orderkey",)), f"SELECT {EDGE_DATES} FROM orders")
INTS = "o_orderkey, CAST(CASE o_orderkey % 4 WHEN 0 THEN -2147483648 WHEN 1 THEN 2147483647 WHEN 2 THEN 0 ELSE -1 END AS INT) AS a, CAST(CASE o_orderkey % 3 WHEN 0 THEN -32768 WHEN 1 THEN 32767 ELSE 0 END AS SMALLINT) AS b, CASE o_orderkey % 3 WHEN 0 THEN -9223372036854775807 - 1 WHEN 1 THEN 9223372036854775807 ELSE 0 END AS c"
REG.add("tree_int_edges", lambda s, d: made(s, d, "ints", "pagetree", fx.table(s, d, "orders").selectExpr(*_split(INTS)), "o_orderkey:int8!,a:int4,b:int2,c:int8", pk=("o_orderkey",)), f"SELECT {INTS.replace(' AS INT)', ' AS INTEGER)')} FROM orders")
FLOATS = "event_id, value AS a, -value AS b, CAST(value AS FLOAT) AS c, CAST(0 AS DOUBLE) AS z"
REG.add("tree_float_sign", lambda s, d: made(s, d, "floats", "pagetree", fx.table(s, d, "events").selectExpr(*_split(FLOATS)), "event_id:int8!,a:float8,b:float8,c:float4,z:float8", pk=("event_id",)), f"SELECT {FLOATS} FROM events")
REG.add("tree_float_raw", lambda s, d: made(s, d, "floats-raw", "pagetree", fx.table(s, d, "events").selectExpr(*_split(FLOATS)), "event_id:int8!,a:float8,b:float8,c:float4,z:float8", pk=("event_id",), float_codec="raw_le"), f"SELECT {FLOATS} FROM events")
DECS = "c_custkey, c_acctbal AS a, -c_acctbal AS b, round(c_acctbal, 0) AS c"
REG.add("tree_decimal_neg", lambda s, d: made(s, d, "decimals", "pagetree", fx.table(s, d, "customer").selectExpr("c_custkey", "c_acctbal AS a", "-c_acctbal AS b", "round(c_acctbal, 0) AS c"), "c_custkey:int8!,a:numeric(15,2),b:numeric(18,4),c:numeric(9,0)", pk=("c_custkey",)), f"SELECT {DECS} FROM customer")

# -- projection

for _k in BOTH:
    REG.add(f"projection_{SHORT[_k]}", lambda s, d, k=_k: scan.scan(s, k, fx.base(s, d, "lineitem", k), columns=["l_shipdate", "l_orderkey", "l_tax"]), "SELECT l_shipdate, l_orderkey, l_tax FROM lineitem")

# -- block-range pruning


def indexed(spark, d, table, column, pages_per_range=8, frame=None, label=None, tail=0, cluster=(), spec=None, **read):
    rows = frame if frame is not None else fx.table(spark, d, table)
    path = fx.ensure(spark, d, label or f"{table}-{column}", "pageheap", lambda: rows if cluster else rows.coalesce(1), spec or fx.SPECS[table], cluster_by=cluster, index={"column": column, "pages_per_range": pages_per_range, "unsummarised_tail": tail}, recipe=label or "")
    return path, scan.scan(spark, "pageheap", path, index_path=f"{path}/index.brin", **read)


EV = "SELECT * FROM events"


@q("brin_range_ts", EV + " WHERE ts BETWEEN TIMESTAMP '2024-01-05 00:00:00' AND TIMESTAMP '2024-01-09 12:00:00'")
def brin_range_ts(spark, d):
    return indexed(spark, d, "events", "ts", range="ts:timestamp:2024-01-05 00:00:00:2024-01-09 12:00:00")[1].where("ts BETWEEN TIMESTAMP_NTZ '2024-01-05 00:00:00' AND TIMESTAMP_NTZ '2024-01-09 12:00:00'")


def _orders_range(text):
    return lambda s, d: indexed(s, d, "orders", "o_orderkey", range=f"o_orderkey:int8:{text}")[1]


REG.add("brin_lower_only", lambda s, d: _orders_range("12000:")(s, d).where("o_orderkey >= 12000"), "SELECT * FROM orders WHERE o_orderkey >= 12000")
REG.add("brin_upper_only", lambda s, d: _orders_range(":700")(s, d).where("o_orderkey <= 700"), "SELECT * FROM orders WHERE o_orderkey <= 700")
REG.add("brin_empty", lambda s, d: _orders_range("-50:-10")(s, d).where("o_orderkey BETWEEN -50 AND -10"), "SELECT * FROM orders WHERE o_orderkey BETWEEN -50 AND -10")
REG.add("brin_all", lambda s, d: _orders_range(":")(s, d), "SELECT * FROM orders")


def _null_blocks(spark, d, whole: bool):
    hole = "floor(event_id / 500) % 2 = 0" if whole else "event_id % 50 = 0"
    frame = fx.table(spark, d, "events").withColumn("ts", F.expr(f"CASE WHEN {hole} THEN NULL ELSE ts END")).select("event_id", "ts", "value")
    return indexed(spark, d, "events", "ts", 1, frame, f"events-{'null-blocks' if whole else 'some-null'}", spec="event_id:int8,ts:timestamp,value:float8", range="ts:timestamp:2024-01-03 00:00:00:2024-01-20 00:00:00")


for _n, _w, _h in (("brin_all_null_range", True, "floor(event_id / 500) % 2 = 0"), ("brin_some_null_range", False, "event_id % 50 = 0")):
    REG.add(_n, lambda s, d, w=_w: _null_blocks(s, d, w)[1].where("ts BETWEEN TIMESTAMP_NTZ '2024-01-03 00:00:00' AND TIMESTAMP_NTZ '2024-01-20 00:00:00'"), f"SELECT event_id, ts, value FROM events WHERE NOT ({_h}) AND ts BETWEEN TIMESTAMP '2024-01-03 00:00:00' AND TIMESTAMP '2024-01-20 00:00:00'")
REG.add("brin_unsummarized_tail", lambda s, d: indexed(s, d, "events", "ts", 8, label="events-tail", tail=2, range="ts:timestamp:2024-01-20 00:00:00:")[1].where("ts >= TIMESTAMP_NTZ '2024-01-20 00:00:00'"), EV + " WHERE ts >= TIMESTAMP '2024-01-20 00:00:00'")
SHIP = "l_shipdate BETWEEN TIMESTAMP{} '1997-01-01' AND TIMESTAMP{} '1997-03-31'"
for _n, _c in (("brin_date_sorted_lineitem", ("l_shipdate",)), ("brin_unsorted_lineitem", ())):
    REG.add(_n, lambda s, d, c=_c, n=_n: indexed(s, d, "lineitem", "l_shipdate", 8, label=n, cluster=c, range="l_shipdate:timestamp:1997-01-01:1997-03-31")[1].where(SHIP.format("_NTZ", "_NTZ")), "SELECT * FROM lineitem WHERE " + SHIP.format("", ""))
REG.add("brin_int_eq", lambda s, d: indexed(s, d, "orders", "o_orderkey", pushdown=True, index_column="o_orderkey")[1].where("o_orderkey = 777"), "SELECT * FROM orders WHERE o_orderkey = 777")
REG.add("brin_in_list", lambda s, d: indexed(s, d, "orders", "o_orderkey", pushdown=True, index_column="o_orderkey")[1].where("o_orderkey IN (1, 500, 1400)"), "SELECT * FROM orders WHERE o_orderkey IN (1, 500, 1400)")
REG.add("brin_text", lambda s, d: indexed(s, d, "part", "p_name", 1, cluster=("p_name",), pushdown=True, index_column="p_name")[1].where("p_name >= 'blue' AND p_name < 'green'"), "SELECT * FROM part WHERE p_name >= 'blue' AND p_name < 'green'")
REG.add("brin_float", lambda s, d: indexed(s, d, "events", "value", 8, cluster=("value",), pushdown=True, index_column="value")[1].where("value > 50.0"), EV + " WHERE value > 50.0")
REG.add("brin_pushdown_ts", lambda s, d: indexed(s, d, "events", "ts", pushdown=True, index_column="ts")[1].where("ts >= TIMESTAMP_NTZ '2024-01-05 00:00:00' AND ts < TIMESTAMP_NTZ '2024-01-06 00:00:00'"), EV + " WHERE ts >= TIMESTAMP '2024-01-05 00:00:00' AND ts < TIMESTAMP '2024-01-06 00:00:00'")
REG.add("tree_key_bounds", lambda s, d: scan.scan(s, "pagetree", fx.base(s, d, "orders", "pagetree"), range="o_orderkey:int8:100:900").where("o_orderkey BETWEEN 100 AND 900"), "SELECT * FROM orders WHERE o_orderkey BETWEEN 100 AND 900")
REG.add("brin_no_prune_baseline", lambda s, d: indexed(s, d, "orders", "o_orderkey", range="o_orderkey:int8:12000:", prune=False)[1].where("o_orderkey >= 12000"), "SELECT * FROM orders WHERE o_orderkey >= 12000")


@q("sample_pages", "SELECT CAST(0 AS BIGINT) AS foreign_rows, true AS fewer")
def sample_pages(spark, d):
    """A deterministic tenth of the blocks, for a cheap profile: rows of the table, and fewer."""
    path, part = fx.base(spark, d, "lineitem", "pageheap"), {"sample_pages": 0.1, "pages_per_read": 4}
    sample, whole = scan.scan(spark, "pageheap", path, **part), fx.table(spark, d, "lineitem")
    key = ["l_orderkey", "l_linenumber", "l_partkey"]
    foreign = sample.join(whole, key, "left_anti").agg(F.count(F.lit(1)).alias("foreign_rows"))
    sizes = sample.agg(F.count(F.lit(1)).alias("n")).crossJoin(whole.agg(F.count(F.lit(1)).alias("of")))  # one row each
    return foreign.crossJoin(sizes).select("foreign_rows", (F.col("n") < F.col("of") / 2).alias("fewer"))


@q("prune_metrics", "SELECT * FROM (VALUES ('all', true, false), ('week', false, false), ('none', false, true)) t(predicate, reads_all, reads_none)")
def prune_metrics(spark, d):
    """Planned ranges and pages of three predicates."""
    path, _ = indexed(spark, d, "events", "ts")
    rows = []
    for label, text in (("all", "ts:timestamp::"), ("week", "ts:timestamp:2024-01-05:2024-01-12"), ("none", "ts:timestamp:1990-01-01:1990-01-02")):
        m = scan.metrics(path, index_path=f"{path}/index.brin", range=text)
        rows.append((label, m["pages_read"] == m["pages_total"] and m["ranges_kept"] == m["ranges_total"], m["pages_read"] == m["ranges_kept"] == m["bytes_read"] == 0))
    return spark.createDataFrame(rows, "predicate string, reads_all boolean, reads_none boolean")


def summarised(spark, d) -> str:
    """The events with a table of summaries beside them."""
    path = fx.ensure(spark, d, "events-table", "pageheap", lambda: fx.table(spark, d, "events").coalesce(1), fx.SPECS["events"])
    at = f"{path}/summaries"
    if not plan.exists(f"{at}/{plan.SUMMARIES}"):
        scan.build_index(spark, path, "ts", 8, index_path=at, form="table")
    return path


WEEK = "ts BETWEEN TIMESTAMP{0} '2024-01-05 00:00:00' AND TIMESTAMP{0} '2024-01-09 00:00:00'"


@q("prune_distributed", "SELECT * FROM events WHERE " + WEEK.format(""))
def prune_distributed(spark, d):
    """Pages to read are found by a Spark job over a table of summaries; the scan reads those only."""
    path = summarised(spark, d)
    return scan.scan(spark, "pageheap", path, index_path=f"{path}/summaries", range="ts:timestamp:2024-01-05:2024-01-09", where=WEEK.format("_NTZ"))


@q("prune_table_pushdown", "SELECT * FROM events WHERE " + WEEK.format(""))
def prune_table_pushdown(spark, d):
    """The same summaries, pruned by a filter that Spark pushes."""
    path = summarised(spark, d)
    return scan.scan(spark, "pageheap", path, index_path=f"{path}/summaries", index_column="ts", pushdown=True, where=WEEK.format("_NTZ"))


# -- relations that grow or change


def appended(spark, d, table, kind, by, **options) -> str:
    """A table written in two halves, the second appended to the first."""
    scan.register(spark)
    path, df = scratch(spark, "appended"), fx.table(spark, d, table)
    for k, mode in enumerate(("overwrite", "append")):
        scan.write(df.where(F.col(by) % 2 == k), kind, path, fx.SPECS[table], mode=mode, pk=fx.KEYS[table] if kind == "pagetree" else (), **options)
    return path


for _k in BOTH:
    REG.add(f"{SHORT[_k]}_overflow_append", lambda s, d, k=_k: scan.scan(s, k, appended(s, d, "documents", k, "doc_id", overflow=True), on_overflow="resolve"), "SELECT * FROM documents")
    REG.add(f"{SHORT[_k]}_overflow_union", lambda s, d, k=_k: scan.scan(s, k, [fx.base(s, d, "pages", k), appended(s, d, "pages", k, "page_id", overflow=True)], on_overflow="resolve"), "SELECT * FROM pages UNION ALL SELECT * FROM pages")
    WIDE = "numeric(38,2)"
    REG.add(f"{SHORT[_k]}_numeric_wide", lambda s, d, k=_k: made(s, d, "wide", k, fx.table(s, d, "customer").selectExpr("c_custkey", "CAST(CAST(c_custkey AS DECIMAL(8,0)) * CAST(c_custkey AS DECIMAL(8,0)) * 123456789012345678901.25BD AS DECIMAL(38,2)) * IF(c_custkey % 2 = 0, -1BD, 1BD) AS w").selectExpr("c_custkey", "CAST(w AS DECIMAL(38,2)) AS w"), f"c_custkey:int8!,w:{WIDE}", pk=("c_custkey",) if k == "pagetree" else (), read={"numeric_as": "decimal"}).selectExpr("c_custkey", "CAST(CAST(replace(CAST(w AS STRING), '.', '') AS DECIMAL(38,0)) AS STRING) AS hundredths"),
            "SELECT c_custkey, CAST(CAST(c_custkey AS HUGEINT) * c_custkey * 12345678901234567890125 * CASE WHEN c_custkey % 2 = 0 THEN -1 ELSE 1 END AS VARCHAR) AS hundredths FROM customer")


def grown_index(spark, d, mode):
    """An index over half of the orders, which the relation outgrows, or which is left over from an earlier relation."""
    scan.register(spark)
    path, df = scratch(spark, "grown"), fx.table(spark, d, "orders")
    scan.write(df.where("o_orderkey % 2 = 0").coalesce(1), "pageheap", path, fx.SPECS["orders"])
    index = scan.build_index(spark, path, "o_orderkey", 8)
    scan.write(df if mode == "overwrite" else df.where("o_orderkey % 2 = 1").coalesce(1), "pageheap", path, fx.SPECS["orders"], mode=mode)
    return scan.scan(spark, "pageheap", path, index_path=index, range="o_orderkey:int8:100:900").where("o_orderkey BETWEEN 100 AND 900")


for _n, _m in (("brin_after_append", "append"), ("brin_after_overwrite", "overwrite")):
    REG.add(_n, lambda s, d, m=_m: grown_index(s, d, m), "SELECT * FROM orders WHERE o_orderkey BETWEEN 100 AND 900")
