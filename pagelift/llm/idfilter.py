"""A Bloom filter over ids, of a fixed largest size, to keep rows from a shuffle that surely have no partner in it; beyond
that size a join by id does the same."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.llm.common import mix

MOST_BITS = 1 << 29  # 64 MB, for 33 million ids
CHUNK = 1 << 16
HASHES = 4


def _places(ids: np.ndarray, bits: int) -> np.ndarray:
    h = mix(ids.astype(np.int64).view(np.uint64) + np.uint64(0x9E3779B97F4A7C15))
    step = (h >> np.uint64(32)) | np.uint64(1)
    return np.concatenate([(h + np.uint64(k) * step) & np.uint64(bits - 1) for k in range(HASHES)]).astype(np.int64)


class IdFilter:
    def __init__(self, bits: int, data: np.ndarray):
        self.bits, self.data = bits, data

    def may_hold(self, ids: np.ndarray) -> np.ndarray:
        at = _places(ids, self.bits)
        return ((self.data[at >> 3] >> (at & 7)) & 1).reshape(HASHES, -1).all(axis=0)


def narrowed(spark: SparkSession, rows: DataFrame, ids: DataFrame, column: str):
    """rows, and a broadcast IdFilter to be applied to them; where the ids are too many for one, the rows of these ids, and
    None."""
    n = ids.count()
    if 16 * n > MOST_BITS:
        return rows.join(ids, column, "left_semi"), None
    return rows, _build(spark, ids, column, 1 << max(16, (16 * n - 1).bit_length()))


def _build(spark: SparkSession, ids: DataFrame, column: str, bits: int):
    """A broadcast IdFilter of a column of ids: each task marks its own bitmap, chunks are joined by OR."""

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        data = np.zeros(bits >> 3, np.uint8)
        for batch in batches:
            at = _places(np.asarray(batch.column(0).drop_null()), bits)
            np.bitwise_or.at(data, at >> 3, (1 << (at & 7)).astype(np.uint8))
        chunks = data.reshape(-1, CHUNK >> 3)
        used = np.flatnonzero(chunks.any(axis=1))
        yield pa.RecordBatch.from_arrays([pa.array(used, pa.int64()), pa.array([chunks[i].tobytes() for i in used], pa.binary())], names=["chunk", "data"])

    def unite(table: pa.Table) -> pa.Table:
        out = np.bitwise_or.reduce(np.vstack([np.frombuffer(x, np.uint8) for x in table.column("data").to_pylist()]), axis=0)
        return pa.table([table.column("chunk")[:1], pa.array([out.tobytes()], pa.binary())], names=["chunk", "data"])

    kind = "chunk long, data binary"
    data = np.zeros((bits // CHUNK, CHUNK >> 3), np.uint8)
    for chunk, part in ids.select(F.col(column).cast("long")).mapInArrow(mark, kind).groupBy("chunk").applyInArrow(unite, kind).collect():
        data[chunk] = np.frombuffer(part, np.uint8)
    return spark.sparkContext.broadcast(IdFilter(bits, data.ravel()))
