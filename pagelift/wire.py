"""Client-protocol baselines: how an engine gets rows when it may not read the files.

* JDBC against an embedded database: row at a time, batched, partitioned, or with a filter that the server applies.
* A binary bulk-copy stream and a text row protocol, encoded once and decoded row by row, as a client does.

They leave out the network and a server's own scan, so their times are lower bounds of what a protocol costs.
"""

from __future__ import annotations

import contextlib
import datetime
import os
import shutil
import struct
import tempfile
import uuid
import zipfile
from concurrent.futures import ThreadPoolExecutor

import pyarrow as pa
import pyarrow.csv as csv
import pyarrow.fs as pafs
from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import TimestampNTZType

from pagelift.plans import pages as plan
from pagelift.schema import StorageSchema

BLOCK = 1 << 20
SIGNATURE = b"ROWCOPY\n\xff\r\n\0"
EPOCH = datetime.datetime(1970, 1, 1)
FORMATS = {"bool": ">?", "int2": ">h", "int4": ">i", "int8": ">q", "float4": ">f", "float8": ">d", "numeric": ">d", "date": ">i", "timestamp": ">q"}


DRIVER = "org.apache.derby.jdbc.EmbeddedDriver"
PAGE = 32_768
#: A relation is a view of so many tables at most, so many of them being filled at a time.  Rows go into an empty table
#: without a log and without the locks of others, and each table is a file of its own.
TABLES, WRITERS = 32, 4


def jdbc_url(path: str) -> str:
    """Address of a loaded database.  An archive is read-only, so every process of the cluster may have it open."""
    return f"jdbc:derby:jar:({path})db"


def shared_path(spark: SparkSession, path: str) -> str:
    """The path as the embedded database opens it, which knows no stores: a mounted folder, or a local session's own."""
    fs, at = plan.file_system(path)
    if isinstance(fs, pafs.LocalFileSystem):
        return at
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("the embedded database needs a spark.checkpoint.dir that is a mounted folder")
    return os.path.join(tempfile.gettempdir(), "pagelift", *at.strip("/").split("/"))


def load_jdbc(df: DataFrame, path: str, table: str) -> str:
    """Fill an embedded database, the stand-in for a server, and put it where all processes see it.  Returns its address.

    Only one process may write to such a database.  So executors write rows as text into files that the driver's database
    imports, a few at a time, on the driver's disk; its files become an archive that appears in one move.  The database has
    no days that the calendar of 1582 left out, and no times that the driver's zone skips: it moves them on.
    """
    spark = df.sparkSession
    path = shared_path(spark, path)
    if os.path.exists(path):
        return jdbc_url(path)
    os.makedirs(os.path.dirname(path), exist_ok=True)
    with tempfile.TemporaryDirectory(prefix="pagelift-db-") as folder:
        try:
            _import(df, f"jdbc:derby:{folder}/db;create=true", table, f"{path}.{uuid.uuid4().hex[:8]}.rows")
        finally:
            _shut(spark, f"{folder}/db")
        draft = f"{path}.{uuid.uuid4().hex[:8]}"
        with zipfile.ZipFile(draft, "w", zipfile.ZIP_STORED) as z:  # stored: a page is found without unpacking what precedes it
            for at, _, names in os.walk(f"{folder}/db"):
                for name in names:
                    z.write(f"{at}/{name}", os.path.relpath(f"{at}/{name}", folder))
                    os.remove(f"{at}/{name}")  # else the disk holds the database twice
        os.replace(draft, path)
    return jdbc_url(path)


def _import(df: DataFrame, url: str, table: str, folder: str) -> None:
    """A relation with the columns that Spark's own writer makes, and its rows."""

    def send(batches):
        name = f"{folder}/{uuid.uuid4().hex}.csv"
        with contextlib.ExitStack() as stack:
            out = None
            for batch in batches:
                if batch.num_rows:
                    out = out or stack.enter_context(csv.CSVWriter(name, batch.schema, write_options=csv.WriteOptions(include_header=False)))
                    out.write_batch(batch)
        yield pa.RecordBatch.from_arrays([pa.array([name] if out else [], pa.string())], names=["file"])

    sc = df.sparkSession.sparkContext
    sc._jvm.org.apache.spark.sql.execution.datasources.jdbc.DriverRegistry.register(DRIVER)

    def run(*statements: str) -> None:
        c = sc._jvm.java.sql.DriverManager.getConnection(url)
        try:
            for x in statements:
                c.createStatement().execute(x)
        finally:
            c.close()

    def fill(k: int) -> None:
        for name in sc.runJob(files, lambda rows: [r[0] for r in rows], [k]):
            at = name.replace("'", "''")
            run(f"CALL SYSCS_UTIL.SYSCS_IMPORT_TABLE(NULL, '{table.upper()}_{k}', '{at}', NULL, NULL, 'UTF-8', 0)")
            os.remove(name)

    os.makedirs(folder)
    try:
        files = df.coalesce(TABLES).mapInArrow(send, "file string").rdd
        parts = [f"{table}_{k}" for k in range(max(1, files.getNumPartitions()))]
        run(*(f"CALL SYSCS_UTIL.SYSCS_SET_DATABASE_PROPERTY('derby.storage.{k}', '{v}')" for k, v in (("pageSize", PAGE), ("pageReservedSpace", 0))))
        df.limit(0).write.format("jdbc").mode("overwrite").option("url", url).option("dbtable", parts[0]).option("driver", DRIVER).save()
        run(*(f"CREATE TABLE {x} AS SELECT * FROM {parts[0]} WITH NO DATA" for x in parts[1:]), f"CREATE VIEW {table} AS {' UNION ALL '.join(f'SELECT * FROM {x}' for x in parts)}")
        with ThreadPoolExecutor(WRITERS) as pool:
            list(pool.map(fill, range(files.getNumPartitions())))
    finally:
        shutil.rmtree(folder)


def _shut(spark: SparkSession, path: str) -> None:
    try:
        spark.sparkContext._jvm.java.sql.DriverManager.getConnection(f"jdbc:derby:{path};shutdown=true")
    except Py4JJavaError:
        return  # how the database says that it is down


def jdbc(spark: SparkSession, url: str, table: str, fetchsize: int = 1, partition_column: str | None = None, bounds: tuple | None = None, parts: int = 8) -> DataFrame:
    """fetchsize 1: a row a round trip; larger: batched; partition_column: several connections, each with a key range."""
    r = spark.read.format("jdbc").option("url", url).option("dbtable", table).option("driver", DRIVER).option("fetchsize", fetchsize).option("preferTimestampNTZ", "true")
    if partition_column and None not in bounds:  # without keys there is nothing to divide
        r = r.option("partitionColumn", partition_column).option("lowerBound", str(bounds[0])).option("upperBound", str(bounds[1])).option("numPartitions", parts)
    out = r.load()
    # as text: Spark takes timestamps for instants in the zone of the process, which would move those without a zone
    local = [f.name for f in out.schema if f.dataType == TimestampNTZType()]
    if not local:
        return out
    texts = r.option("customSchema", ", ".join(f"`{c}` STRING" for c in local)).load()
    return texts.withColumns({c: F.col(f"`{c}`").cast("timestamp_ntz") for c in local})


def _wire_value(v, kind: str) -> bytes:
    if kind == "timestamp":
        v = int((v - EPOCH) / datetime.timedelta(microseconds=1))
    elif kind == "date":
        v = (v - EPOCH.date()).days
    elif kind == "numeric":
        v = float(v)
    if kind in FORMATS:
        return struct.pack(FORMATS[kind], v)
    return v.encode() if isinstance(v, str) else bytes(v)


def encode_copy(df: DataFrame, path: str, schema: StorageSchema, text: bool = False) -> str:
    """What a server would send, one file a partition: a binary copy stream, or text rows that repeat column names."""

    def send(batches):
        name = f"{uuid.uuid4().hex}.{'txt' if text else 'bin'}"
        fs, at = plan.file_system(f"{path}/{name}")
        fs.create_dir(os.path.dirname(at), recursive=True)
        with fs.open_output_stream(at) as out:
            out.write(b"" if text else SIGNATURE)
            for batch in batches:
                out.write(encoded(batch))
        yield pa.RecordBatch.from_arrays([pa.array([name])], names=["file"])

    def encoded(batch):
        data = bytearray()
        for row in batch.to_pylist():
            if text:
                data += ("\x1f".join(f"{c.name}={'' if row[c.name] is None else row[c.name]}" + ("\x00" if row[c.name] is None else "") for c in schema.columns) + "\x1e").encode()
                continue
            data += struct.pack(">h", len(schema.columns))
            for c in schema.columns:
                v = row[c.name]
                if v is None:
                    data += struct.pack(">i", -1)
                else:
                    raw = _wire_value(v, c.kind)
                    data += struct.pack(">i", len(raw)) + raw
        return data

    files = [r[0] for r in df.select(*schema.names).mapInArrow(send, "file string").collect()]
    plan.write_bytes(f"{path}/{plan.MANIFEST}", ("\n".join(sorted(files))).encode())
    return path


def received(path: str):
    """A file as a client receives it: a block after the other."""
    fs, at = plan.file_system(path)
    with fs.open_input_stream(at) as f:
        while block := f.read(BLOCK):
            yield block


def decode_copy(blocks, schema: StorageSchema):
    """Rows of a binary copy stream.  No more of it is held than a block and what a row needs."""
    kinds = [c.kind for c in schema.columns]
    unpack = {k: struct.Struct(f).unpack for k, f in FORMATS.items()}
    blocks, data, at = iter(blocks), b"", 0

    def have(n: int) -> bool:
        nonlocal data, at
        if at + n > len(data):
            held, size = [data[at:]], len(data) - at
            while size < n and (block := next(blocks, None)) is not None:
                held.append(block)
                size += len(block)
            data, at = b"".join(held), 0
        return at + n <= len(data)

    def whole(n: int) -> None:
        if not have(n):
            raise ValueError("the copy stream ends within a row")

    whole(len(SIGNATURE))
    at += len(SIGNATURE)
    while have(1):
        whole(2)
        (n,) = struct.unpack_from(">h", data, at)
        at += 2
        row = []
        for k in range(n):
            whole(4)
            (size,) = struct.unpack_from(">i", data, at)
            at += 4
            if size < 0:
                row.append(None)
                continue
            whole(size)
            raw, kind = data[at : at + size], kinds[k]
            at += size
            if kind in unpack:
                v = unpack[kind](raw)[0]
                row.append(EPOCH + datetime.timedelta(microseconds=v) if kind == "timestamp" else (EPOCH + datetime.timedelta(days=v)).date() if kind == "date" else v)
            else:
                row.append(raw.decode() if kind != "binary" else raw)
        yield tuple(row)


def lines(blocks):
    """Rows of text as bytes; a row may span blocks."""
    held = []
    for block in blocks:
        first, *more = block.split(b"\x1e")
        held.append(first)
        if more:
            yield b"".join(held)
            yield from more[:-1]
            held = more[-1:]
    if any(held):
        raise ValueError("the text rows end within a row")


def decode_text(blocks, schema: StorageSchema):
    """Rows of the text protocol."""
    read = {"bool": lambda x: x == "True", "int2": int, "int4": int, "int8": int, "float4": float, "float8": float, "numeric": float, "date": datetime.date.fromisoformat, "timestamp": datetime.datetime.fromisoformat}
    kinds = [c.kind for c in schema.columns]
    for line in lines(blocks):
        row = []
        for k, cell in enumerate(line.decode().split("\x1f")):
            v = cell.partition("=")[2]
            row.append(None if v.endswith("\x00") else read[kinds[k]](v) if kinds[k] in read else v)
        yield tuple(row)


class _File(InputPartition):
    def __init__(self, path):
        self.path = path


class _WireReader(DataSourceReader):
    def __init__(self, options, decode):
        self.path, self.storage, self.decode = options["path"], StorageSchema.parse(options["columns_spec"]), decode

    def partitions(self):
        return [_File(f"{self.path}/{f}") for f in plan.read_bytes(f"{self.path}/{plan.MANIFEST}").decode().split("\n")]

    def read(self, partition):
        yield from self.decode(received(partition.path), self.storage)


class _Wire(DataSource):
    def schema(self):
        return StorageSchema.parse(self.options["columns_spec"]).spark()


class WireBinarySource(_Wire):
    @classmethod
    def name(cls):
        return "wirebinary"

    def reader(self, schema):
        return _WireReader(self.options, decode_copy)


class WireTextSource(_Wire):
    @classmethod
    def name(cls):
        return "wiretext"

    def reader(self, schema):
        return _WireReader(self.options, decode_text)


def register(spark: SparkSession) -> None:
    if not getattr(spark, "_pagelift_wire", False):
        spark.dataSource.register(WireBinarySource)
        spark.dataSource.register(WireTextSource)
        spark._pagelift_wire = True


def bounds(df: DataFrame, column: str) -> tuple:
    return tuple(df.agg(F.min(column), F.max(column)).first())


