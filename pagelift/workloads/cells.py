"""Scans of database files that a database's own library has written."""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from pagelift import scan
from pagelift.formats import cell
from pagelift.plans import pages as plan
from pagelift.schema import StorageSchema
from pagelift.workloads import fixtures as fx
from pagelift.workloads.registry import Registry

REG = Registry()


def written(df: DataFrame, path: str, table: str, spec: str, key: str | None, page_size: int = 4096) -> str:
    """The rows as database files, one a partition; each holds another table too."""
    storage = StorageSchema.parse(spec)

    def put(batches):
        data = cell.database(batches, storage, table, key, page_size)
        if data:
            plan.write_bytes(f"{path}/{table}-{TaskContext.get().partitionId():05d}.db", data)
        yield pa.RecordBatch.from_arrays([pa.array([data is not None])], names=["written"])

    df.select(*storage.names).mapInArrow(put, "written boolean").collect()
    plan.write_bytes(f"{path}/_done", b"")
    return path


def base(spark: SparkSession, d: str, name: str, frame: DataFrame | None = None, spec: str | None = None, key: str | None = None, label: str = "", **how) -> str:
    """Database files of a table, made once."""
    scan.register(spark)
    spec = spec or fx.SPECS[name]
    path = fx.place(spark, d, f"pagecell-{name}{label}", {"spec": spec, "key": key, **how})
    if not plan.exists(f"{path}/_done"):
        written(frame if frame is not None else fx.table(spark, d, name).repartition(2), path, name, spec, key, **how)
    return path


def row_key(name: str) -> str | None:
    """The column that is the row number: a table's only key column, if that is a whole number."""
    keys = fx.KEYS[name]
    return keys[0] if len(keys) == 1 and re.search(rf"\b{keys[0]}:int", fx.SPECS[name]) else None


def scanned(name: str, **options):
    def run(spark, d):
        key = row_key(name)
        return scan.scan(spark, "pagecell", base(spark, d, name, key=key), table=name, columns_spec=fx.SPECS[name], pk=key or "", **options)

    return run


for _t in ("nation", "customer", "orders", "lineitem", "events", "conversations"):
    REG.add(f"cell_scan_{_t}", scanned(_t), f"SELECT * FROM {_t}")
for _t in ("documents", "pages"):  # rows that go on along overflow pages
    REG.add(f"cell_scan_{_t}", scanned(_t, on_overflow="resolve"), f"SELECT * FROM {_t}")
REG.add("cell_projection", scanned("lineitem", columns=["l_shipdate", "l_orderkey", "l_tax"]), "SELECT l_shipdate, l_orderkey, l_tax FROM lineitem")


@REG.query("cell_declared_schema", "SELECT o_orderkey, o_custkey, o_totalprice, o_orderpriority FROM orders")
def cell_declared_schema(spark, d):
    """Without a specification the columns are those of the table's definition in the file."""
    return scan.scan(spark, "pagecell", base(spark, d, "orders", key="o_orderkey"), table="orders").select("o_orderkey", "o_custkey", "o_totalprice", "o_orderpriority")


@REG.query("cell_large_pages", "SELECT * FROM customer")
def cell_large_pages(spark, d):
    path = base(spark, d, "customer", label="-64k", page_size=65_536)
    return scan.scan(spark, "pagecell", path, table="customer", columns_spec=fx.SPECS["customer"])


BOUNDS = "o_orderkey BETWEEN 700 AND 1900"
REG.add("cell_key_range", lambda s, d: scanned("orders", range="o_orderkey:int8:700:1900")(s, d).where(BOUNDS), f"SELECT * FROM orders WHERE {BOUNDS}")
REG.add("cell_key_pushdown", lambda s, d: scanned("orders", pushdown=True)(s, d).where("o_orderkey IN (3, 1200) OR o_orderkey > 14000").where("o_orderkey >= 1000"), "SELECT * FROM orders WHERE (o_orderkey IN (3, 1200) OR o_orderkey > 14000) AND o_orderkey >= 1000")

NULLS = "event_id, CASE WHEN event_id % 3 = 0 THEN NULL ELSE ts END AS ts, CASE WHEN event_id % 5 = 0 THEN NULL ELSE value END AS value, CASE WHEN event_id % 2 = 0 THEN NULL ELSE event_type END AS event_type, event_id * event_id * event_id * 1000003 - 7 AS big, CASE WHEN event_id % 4 = 0 THEN NULL ELSE event_id % 2 = 1 END AS odd"


@REG.query("cell_nulls", f"SELECT {NULLS} FROM events")
def cell_nulls(spark, d):
    """Nulls, whole numbers of all widths, and truth values."""
    spec = "event_id:int8,ts:timestamp,value:float8,event_type:text,big:int8,odd:bool"
    frame = fx.table(spark, d, "events").selectExpr(*re.split(r", (?=CASE|event_id \*)", NULLS))
    return scan.scan(spark, "pagecell", base(spark, d, "events", frame, spec, label="-nulls"), table="events", columns_spec=spec)
