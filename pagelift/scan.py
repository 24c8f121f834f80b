"""Entry points for users: register the sources, scan page files, resolve overflow values, build range indexes."""

from __future__ import annotations

import json
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.formats import brin
from pagelift.formats.brin import RangePredicate
from pagelift.plans import pages as plan
from pagelift.schema import StorageSchema
from pagelift.session import scratch, ship
from pagelift.sources.paged import HeapReader, PageCellSource, PageHeapSource, PageTreeSource, TreeReader

PUSHDOWN = "spark.sql.python.filterPushdown.enabled"


def register(spark: SparkSession) -> SparkSession:
    """Make the sources known to a session, once."""
    if not getattr(spark, "_pagelift_sources", False):
        ship(spark)
        spark.dataSource.register(PageHeapSource)
        spark.dataSource.register(PageTreeSource)
        spark.dataSource.register(PageCellSource)
        spark._pagelift_sources = True
    return spark


def scan(spark: SparkSession, kind: str, path: str | list[str], columns: list[str] | None = None, where: str | None = None, pushdown: bool = False, **options) -> DataFrame:
    """A DataFrame over the files at path.  columns: decode these only.  where: a SQL filter, applied above the scan and,
    with pushdown, to the range index.  on_overflow="resolve" joins values kept elsewhere."""
    register(spark)
    path = ",".join(path) if isinstance(path, list) else path
    if options.get("on_overflow") == "resolve" and len(relations := plan.expand(path)) > 1:  # values are numbered by relation
        parts = [scan(spark, kind, one, columns, where, pushdown, **options) for one in relations]
        return reduce(DataFrame.unionByName, parts)
    if pushdown:
        spark.conf.set(PUSHDOWN, "true")
    if options.get("index_path") and options.get("range") and kind == "pageheap" and plan.exists(f"{options['index_path']}/{plan.SUMMARIES}"):
        options = options | {"runs": runs_by_job(spark, path, options["index_path"], RangePredicate.parse(options["range"]))}
    reader = spark.read.format(kind).option("path", path).option("pushdown", str(pushdown).lower())
    for k, v in options.items():
        reader = reader.option(k, str(v).lower() if isinstance(v, bool) else v)
    if columns:
        reader = reader.option("columns", ",".join(columns))
    df = reader.load()
    if options.get("on_overflow") == "resolve" and kind == "pageheap":
        df = resolve(spark, df, path)
    return df.where(where) if where else df


def scan_heap(spark: SparkSession, path, **options) -> DataFrame:
    return scan(spark, "pageheap", path, **options)


def scan_tree(spark: SparkSession, path, **options) -> DataFrame:
    return scan(spark, "pagetree", path, **options)


def resolve(spark: SparkSession, df: DataFrame, path: str) -> DataFrame:
    """Join the chunks of one relation's overflow values to the rows that point to them: chunks are laid together by value
    first, and columns that no row needs are dropped by the optimiser."""
    parts = [p for p in (f"{p.rstrip('/')}/_overflow" for p in plan.expand(path)) if plan.exists(f"{p}/{plan.MANIFEST}")]
    marks = [c for c in df.columns if c.startswith("__overflow_")]
    if parts:
        chunks = spark.read.format("pageheap").option("path", ",".join(parts)).load()
        values = chunks.groupBy("value_id").agg(F.array_sort(F.collect_list(F.struct("seq", "data"))).alias("c"))
        values = values.select(F.col("value_id").cast("long").alias("value_id"), F.expr("aggregate(c, cast('' as binary), (a, x) -> concat(a, x.data))").alias("data"))
        for mark in marks:
            name = mark.removeprefix("__overflow_")
            kind = df.schema[name].dataType.simpleString()
            if kind not in ("string", "binary"):
                continue
            side = values.select(F.col("value_id").alias(mark), F.col("data").cast(kind).alias("__long"))
            df = df.join(side, mark, "left").withColumn(name, F.coalesce("__long", name)).drop("__long")
    return df.drop(*marks)


def write(df: DataFrame, kind: str, path: str, columns_spec: str | None = None, mode: str = "overwrite", pk: tuple[str, ...] = (), cluster_by: tuple[str, ...] = (), partitions: int | None = None, **options) -> str:
    """Write page files.  A tree is always clustered by its key; a heap by cluster_by, where that is given."""
    spark = register(df.sparkSession)
    order = pk if kind == "pagetree" and pk else cluster_by
    if order:
        n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
        df = (df.repartitionByRange(n, *order) if n > 1 else df.coalesce(1)).sortWithinPartitions(*order)
    elif partitions:
        df = df.coalesce(partitions)
    writer = df.write.format(kind).mode(mode).option("path", path)
    if columns_spec:
        writer = writer.option("columns_spec", columns_spec)
    if pk:
        writer = writer.option("pk", ",".join(pk))
    for k, v in options.items():
        writer = writer.option(k, str(v).lower() if isinstance(v, bool) else v)
    writer.save()
    return path


def summaries(spark: SparkSession, path: str, column: str, pages_per_range: int) -> DataFrame:
    """range_no, low, high, n (values that aren't null), rows: one aggregate over the scan, without the ranges of no rows."""
    df = scan_heap(spark, path, columns=[column], with_page=True, visibility="none")
    return df.groupBy(F.floor(F.col("_page") / pages_per_range).alias("range_no")).agg(F.min(column).alias("low"), F.max(column).alias("high"), F.count(column).alias("n"), F.count(F.lit(1)).alias("rows"))


def build_index(spark: SparkSession, path: str, column: str, pages_per_range: int = 128, index_path: str | None = None, unsummarised_tail: int = 0, null_flags: str = "paired", form: str = "auto") -> str:
    """Write a block-range index of a heap relation's column.

    Up to DRIVER_RANGES ranges the driver gets the summaries as vectors and writes an index file.  Beyond (or with form
    "table") executors write them as a Parquet table, and scans with a range prune by a job over that.  Either tells the
    relation and the pages that it covers: ranges that have grown since, and relations written anew, are read whole.
    """
    found = plan.manifest(path)
    storage = StorageSchema.from_json(found["columns"])
    pages = sum(s.pages for s in plan.list_segments(path))
    total, kind = -(-pages // pages_per_range), storage[column].kind
    at = index_path or f"{path.rstrip('/')}/index_{column}.brin"
    grouped = summaries(spark, path, column, pages_per_range)
    if form == "table" or (form == "auto" and total > plan.DRIVER_RANGES):
        grouped.where(F.col("range_no") < total - unsummarised_tail).write.mode("overwrite").parquet(f"{at}/ranges")
        plan.write_bytes(f"{at}/{plan.SUMMARIES}", json.dumps({"column": column, "pages_per_range": pages_per_range, "pages": pages, "relation": found["relation"]}).encode())
        return at
    rows = grouped.toArrow()
    where = rows.column("range_no").to_numpy()
    present = np.zeros(total, bool)
    present[where] = True
    every, some = np.zeros(total, bool), np.zeros(total, bool)
    n, of = (rows.column(c).to_numpy() for c in ("n", "rows"))
    every[where], some[where] = n == 0, (n > 0) & (n < of)
    bounds = [_bounds(rows.column(c), where, total, kind) for c in ("low", "high")]
    present[max(0, total - unsummarised_tail) :] = False
    plan.write_bytes(at, brin.write_ranges(present, *bounds, every, some, storage[column], pages_per_range, null_flags, pages, found["relation"]))
    return at


def _bounds(column, where: np.ndarray, total: int, kind: str):
    """Comparable bounds of all ranges: a vector, or a list for text."""
    if kind not in brin.BOUNDS:
        out: list = [None] * total
        for i, v in zip(where.tolist(), column.to_pylist()):
            out[i] = brin.comparable(v, kind)
        return out
    whole = {"date": pa.int32(), "timestamp": pa.int64()}.get(kind)
    column = column.cast(whole) if whole else column
    values = column.cast(pa.float64() if kind in ("float4", "float8", "numeric") else pa.int64()).fill_null(0).to_numpy()
    out = np.zeros(total, values.dtype)
    out[where] = values
    return out


def range_condition(predicate: RangePredicate, kind: str) -> Column:
    """Ranges of a summaries table that a predicate can't exclude; bounds as the index compares them."""
    literal = {
        "timestamp": lambda v: F.expr(f"timestampadd(MICROSECOND, {v}, TIMESTAMP_NTZ '1970-01-01 00:00:00')"),
        "date": lambda v: F.expr(f"date_from_unix_date({v})"),
    }.get(kind, lambda v: F.lit(v).cast("string") if isinstance(v, bytes) else F.lit(v))
    if isinstance(predicate.low, bytes) or isinstance(predicate.high, bytes):
        literal = lambda v: F.lit(v.decode())  # noqa: E731 - Spark compares text bytewise, too
    out = F.lit(True)
    if predicate.low is not None:
        out &= ~(F.col("high") < literal(predicate.low))
    if predicate.high is not None:
        out &= ~(F.col("low") > literal(predicate.high))
    return out


def runs_by_job(spark: SparkSession, path: str, index: str, predicate: RangePredicate) -> str:
    """Prune by a summaries table, in executors; the file of the page runs that have to be read."""
    found, relation = json.loads(plan.read_bytes(f"{index}/{plan.SUMMARIES}")), plan.manifest(path)
    pages, per = sum(s.pages for s in plan.list_segments(path)), found["pages_per_range"]
    at = f"{scratch(spark, 'runs')}/runs.bin"
    if found["relation"] != relation["relation"] or found["column"] != predicate.column:
        kept = np.array([[0, pages]], "<i8")
    else:
        kind = StorageSchema.from_json(relation["columns"])[predicate.column].kind
        whole = -(-found["pages"] // per) if pages == found["pages"] else found["pages"] // per  # the last may have grown
        told = spark.read.parquet(f"{index}/ranges").where((F.col("range_no") < whole) & (F.col("n") > 0))
        # ranges without rows, without values or without summary are read as well: what is listed here is what is not
        gone = plan.prune_distributed(told.withColumn("usable", F.lit(True)), ~F.coalesce(range_condition(predicate, kind), F.lit(True)), per).orderBy("first_page").toArrow()
        first, n = (gone.column(c).to_numpy().astype(np.int64) for c in ("first_page", "n_pages"))
        starts, ends = np.append(0, first + n), np.append(first, pages)
        kept = np.column_stack([starts, ends - starts])[ends > starts].astype("<i8")
    plan.write_bytes(at, kept.tobytes())
    return at


def metrics(path: str, kind: str = "pageheap", **options) -> dict:
    """Ranges and pages that a scan with these options is planned to read; the plan is all it takes to know."""
    found = plan.manifest(plan.expand(path)[0])
    storage = StorageSchema.from_json(found["columns"]) if found else StorageSchema.parse(options["columns_spec"])
    reader = (HeapReader if kind == "pageheap" else TreeReader)(storage.spark(), {k: str(v) for k, v in options.items()} | {"path": path}, storage, found)
    _, counts = reader.plan()
    counts["bytes_read"] = counts["pages_read"] * reader.page_size
    return counts

__all__ = ["RangePredicate", "build_index", "metrics", "register", "resolve", "scan", "scan_heap", "scan_tree", "write"]
