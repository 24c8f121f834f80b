"""SQL-visible decoders of single storage values, a column profile aggregate, and table functions that show page headers.

The scalar functions take binary columns and work on Arrow batches; registering them makes them SQL functions.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DateType, DoubleType, LongType, StringType

from pagelift.formats import brin, codec, heap, tree


def _spans(values: pd.Series) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    valid = values.notna().to_numpy()
    raw = [bytes(v) if ok else b"" for v, ok in zip(values, valid)]
    lengths = np.array([len(x) for x in raw], np.int64)
    flat = np.frombuffer(b"".join(raw) + b"\0" * 16, np.uint8)
    return flat, np.concatenate([[0], np.cumsum(lengths)[:-1]]).astype(np.int64) if len(raw) else np.zeros(0, np.int64), lengths, valid


def _rows(values: pd.Series, width: int) -> tuple[np.ndarray, np.ndarray]:
    valid = values.notna().to_numpy()
    raw = b"".join(bytes(v) if ok else b"\0" * width for v, ok in zip(values, valid))
    return np.frombuffer(raw, np.uint8).reshape(-1, width).copy(), valid


def _nullable(values: np.ndarray, valid: np.ndarray) -> pd.Series:
    return pd.Series(values).where(pd.Series(valid), None) if not valid.all() else pd.Series(values)


@pandas_udf(DoubleType())
def udf_numeric(v: pd.Series) -> pd.Series:
    """Base-10000 number (header and digit groups) -> double."""
    flat, starts, lengths, valid = _spans(v)
    return _nullable(codec.numeric_double(flat, starts, np.where(valid, lengths, 2)), valid)


@pandas_udf(StringType())
def udf_varlena(v: pd.Series) -> pd.Series:
    """A datum with its short or long header -> text."""
    flat, starts, _, valid = _spans(v)
    out = []
    for at, ok in zip(starts.tolist(), valid):
        head, size = (1, flat[at] >> 1) if flat[at] & 1 else (4, int.from_bytes(flat[at : at + 4].tobytes(), "little") >> 2)
        out.append(flat[at + head : at + int(size)].tobytes().decode() if ok else None)
    return pd.Series(out, dtype=object)


@pandas_udf(DateType())
def udf_heap_date(v: pd.Series) -> pd.Series:
    """Days since 2000-01-01 (4 bytes, little-endian) -> date."""
    raw, valid = _rows(v, 4)
    return _nullable(codec.heap_fixed("date", raw).astype("datetime64[D]").astype(object), valid)


@pandas_udf(DateType())
def udf_packed_date(v: pd.Series) -> pd.Series:
    """Three bytes of year, month and day -> date."""
    raw, valid = _rows(v, 3)
    return _nullable(codec.packed_date(raw).astype("datetime64[D]").astype(object), valid)


@pandas_udf(DoubleType())
def udf_ordered_float(v: pd.Series) -> pd.Series:
    """Eight order-preserving bytes -> double."""
    raw, valid = _rows(v, 8)
    return _nullable(codec.tree_float(raw), valid)


@pandas_udf(LongType())
def udf_biased_int(v: pd.Series) -> pd.Series:
    """Eight big-endian bytes with the sign bit flipped -> long."""
    raw, valid = _rows(v, 8)
    return _nullable(codec.tree_int(raw), valid)


@pandas_udf(DoubleType())
def udf_packed_decimal(v: pd.Series) -> pd.Series:
    """DECIMAL(15,2) in packed groups -> double."""
    raw, valid = _rows(v, codec.decimal_width(15, 2))
    return _nullable(codec.packed_double(raw, 15, 2), valid)


SCALARS = {f.__name__: f for f in (udf_numeric, udf_varlena, udf_heap_date, udf_packed_date, udf_ordered_float, udf_biased_int, udf_packed_decimal)}


def encoder(kind: str, precision: int = 15, scale: int = 2):
    """The opposite of a scalar decoder, to make its inputs: an Arrow-batch function on one column."""

    def encode(column: pa.Array) -> list[bytes]:
        if kind == "numeric":
            lengths, rows = codec.numeric_bytes(codec.scaled_ints(column, scale), scale)
            return [r[:n].tobytes() for r, n in zip(rows, lengths)]
        if kind == "varlena":
            return [(bytes([((len(x) + 1) << 1) | 1]) if len(x) < 127 else ((len(x) + 4) << 2).to_bytes(4, "little")) + x for x in (v.encode() for v in column.to_pylist())]
        rows = {
            "heap_date": lambda: codec.heap_fixed_bytes("date", codec.column_values(column, "date")),
            "packed_date": lambda: codec.packed_date_bytes(codec.column_values(column, "date")),
            "ordered_float": lambda: codec.tree_float_bytes(codec.column_values(column, "float8"), 8),
            "biased_int": lambda: codec.tree_int_bytes(codec.column_values(column, "int8"), 8),
            "packed_decimal": lambda: codec.packed_bytes(codec.scaled_ints(column, scale), precision, scale),
        }[kind]()
        return [r.tobytes() for r in rows]

    return encode


def encoded(df: DataFrame, key: str, column: str, kind: str) -> DataFrame:
    """key and raw: the column's storage bytes."""
    encode = encoder(kind)

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(encode(b.column(1)), pa.binary())], names=[key, "raw"])

    return df.select(F.col(key).cast("long"), column).mapInArrow(stream, f"{key} long, raw binary")


def profile(df: DataFrame) -> DataFrame:
    """One row a column: its name, non-null values, distinct values, smallest and largest as text.

    Values are turned to (column, text) rows, pre-aggregated to distinct ones, and each column's distinct values are then
    folded in two steps, so that no column's values meet in one task before they are partial results.
    """
    cells = df.select(F.posexplode(F.array(*[F.struct(F.lit(c).alias("name"), F.col(c).cast("string").alias("v")) for c in df.columns])).alias("i", "c")).select("c.name", "c.v")
    distinct = cells.where("v IS NOT NULL").groupBy("name", "v").agg(F.count(F.lit(1)).alias("n"))
    fold = "name string, n long, ndv long, low string, high string"

    def reduce(table: pa.Table) -> pa.Table:
        v = table.column("v")
        low, high = pc.min(v), pc.max(v)
        return pa.table({"name": table.column("name")[:1], "n": pa.array([pc.sum(table.column("n")).as_py()]), "ndv": pa.array([table.num_rows]), "low": pa.array([low.as_py()], pa.string()), "high": pa.array([high.as_py()], pa.string())})

    parts = distinct.withColumn("salt", F.pmod(F.xxhash64("v"), F.lit(16))).groupBy("name", "salt").applyInArrow(reduce, fold)
    return parts.groupBy("name").agg(F.sum("n").alias("n"), F.sum("ndv").alias("ndv"), F.min("low").alias("low"), F.max("high").alias("high"))


@udtf(returnType="page int, lower int, upper int, special int, pointers int, normal int")
class PageInspect:
    """Headers of the heap pages in a binary value: a block of pages, as the sources give them `as` blocks."""

    def eval(self, content):
        pages = np.frombuffer(content, np.uint8).reshape(-1, heap.PAGE)
        lower, upper, special = heap.page_headers(pages)
        page, _, state, _ = heap.line_pointers(pages)
        every, normal = np.bincount(page, minlength=len(pages)), np.bincount(page[state == heap.NORMAL], minlength=len(pages))
        yield from zip(range(len(pages)), *(x.tolist() for x in (lower, upper, special, every, normal)))


@udtf(returnType="page int, kind int, level int, index_id long, records int")
class RecordInspect:
    """Headers of tablespace pages in a binary value, with the records that the list of each leaf page holds."""

    def eval(self, content):
        pages = np.frombuffer(content, np.uint8).reshape(-1, tree.PAGE)
        leaves = np.flatnonzero(tree.index_pages(pages) & tree.leaf_pages(pages))
        page, _ = tree.record_origins(pages, leaves)
        columns = (tree._u16(pages, 24), tree._u16(pages, 64), tree.index_ids(pages), np.bincount(page, minlength=len(pages)))
        yield from zip(range(len(pages)), *(x.tolist() for x in columns))


@udtf(returnType="range_no int, block int, slot int, pages_per_range int")
class IndexInspect:
    """The range map of a block-range index in a binary value."""

    def eval(self, content):
        per, _ = brin.meta(content)
        for i, (block, slot) in enumerate(brin.pointers(content).tolist()):
            if slot:
                yield i, block, slot, per


TABLES = {"udtf_page_inspect": PageInspect, "udtf_record_inspect": RecordInspect, "udtf_brin_inspect": IndexInspect}


def register(spark: SparkSession) -> None:
    for name, f in SCALARS.items():
        spark.udf.register(name, f)
    for name, f in TABLES.items():
        spark.udtf.register(name, f)
