"""Batch-to-shard exchange: corpus statistics of hashed items without a row per occurrence.

Documents are grouped into batches of bounded text.  Each batch sends every hash shard the sorted set of its
distinct item hashes (delta-coded, a few bytes an item) with a count; the shard adds up or compares what all
batches sent and answers each batch with one number an item, in the order of the batch's own sorted set.  The
batch then reads its documents again and finds the answer to each of its occurrences by position.

* an item that occurs millions of times reaches its shard once a batch, so no shard has a hot key;
* there are as many shards as batches, both sized from the measured text, so no task grows with the corpus: a shard takes
  in about what one batch holds, whatever their number;
* a batch sends a row to those shards only that it has items for, so there are never more rows than items, and what is
  sent stays in proportion to the corpus even where rows get as small as one item;
* answers carry no hashes, and documents cross the network as compressed text, never as item rows.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from pagelift.llm.common import BATCH_BYTES, cut, drop, text_bytes

#: Most text in a batch; a worker needs some twenty times this.
MOST_BYTES = 64 << 20


def batch_count(docs: DataFrame, target: int | None = None, multiple: int = 1) -> int:
    """Batches grow with the root of the corpus (6 MB of text at 1 GB, 64 MB from 100 GB on), so that what one of them
    sends to one shard doesn't shrink to a few bytes as both grow in number."""
    n, size = text_bytes(docs)
    target = target or min(MOST_BYTES, max(BATCH_BYTES, int(200 * math.sqrt(size))))
    wanted = max(1, math.ceil(size / target), math.ceil(n / 200_000))
    return multiple * math.ceil(wanted / multiple)


def shard_bits(batches: int) -> int:
    """Shards are a power of two, so that each is a run of a sorted hash vector: as many as batches, or up to twice."""
    return max(0, math.ceil(math.log2(max(1, batches))))


def hashed_batches(docs: DataFrame, batches: int) -> DataFrame:
    """By id and text, so that rows without id, or of one id, spread too."""
    return docs.withColumn("batch", F.pmod(F.xxhash64("doc_id", "text"), F.lit(batches)).cast("int"))


#: Documents whose running sum of bytes one task makes.
RANGE_ROWS = 1_000_000
NO_ID = np.iinfo(np.int64).min


def ordered_batches(spark: SparkSession, docs: DataFrame, batches: int) -> tuple[DataFrame, int]:
    """Batches that are runs in the order of doc_id, null ids first, and of a hash of the text (the added column `spot`)
    among rows that share an id; so rows without id, or of one id, spread too.  All have about equal text bytes.

    The running sum of bytes, in order, is made range by range; from it come the batches' first places, 16 bytes for the 6
    to 64 MB of text of a batch.
    """
    docs = docs.withColumn("spot", F.xxhash64("text"))
    if batches == 1:
        return docs.withColumn("batch", F.lit(0)), 1
    known = docs.select(F.coalesce("doc_id", F.lit(NO_ID)).alias("id"), "spot", (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).alias("size"))
    sizes = cut(spark, known.groupBy("id", "spot").agg(F.sum("size").alias("size")), "sizes")
    n, total = (int(x or 0) for x in sizes.agg(F.count(F.lit(1)), F.sum("size")).first())
    ranged = cut(spark, sizes.repartitionByRange(max(1, math.ceil(n / RANGE_ROWS)), "id", "spot").withColumn("part", F.spark_partition_id()), "ranges")
    drop(spark, sizes)
    parts = ranged.groupBy("part").agg(F.sum("size").alias("bytes"))
    before = parts.select("part", (F.sum("bytes").over(Window.orderBy("part")) - F.col("bytes")).alias("before"))  # a row for RANGE_ROWS documents
    within = F.sum("size").over(Window.partitionBy("part").orderBy("id", "spot")) - F.col("size")
    placed = ranged.withColumn("within", within).join(F.broadcast(before), "part").select("id", "spot", F.floor((F.col("before") + F.col("within")) / max(1, math.ceil(total / batches))).alias("batch"))
    firsts = placed.groupBy("batch").agg(F.min(F.struct("id", "spot")).alias("f")).orderBy("batch").select("f.id", "f.spot").toArrow()
    ids, spots = (firsts.column(c).to_numpy()[1:] for c in ("id", "spot"))

    @pandas_udf("int")
    def batch_of(id_: pd.Series, spot: pd.Series) -> pd.Series:
        return pd.Series(place(ids, spots, id_.to_numpy(), spot.to_numpy()).astype(np.int32))

    return docs.withColumn("batch", batch_of(F.coalesce("doc_id", F.lit(NO_ID)), "spot")), len(ids) + 1


def place(ids: np.ndarray, spots: np.ndarray, id_: np.ndarray, spot: np.ndarray) -> np.ndarray:
    """How many of the sorted pairs (ids, spots) are not beyond each pair (id_, spot)."""
    low, high = np.searchsorted(ids, id_, "left"), np.searchsorted(ids, id_, "right")
    for a in np.unique(low[low < high]):  # ids at which several batches meet
        mine = np.flatnonzero((low == a) & (low < high))
        high[mine] = a + np.searchsorted(spots[a : high[mine[0]]], spot[mine], "right")
    return high


def pack_sorted(values: np.ndarray) -> bytes:
    """A sorted uint64 vector as deltas of the fewest whole bytes."""
    if not len(values):
        return b""
    delta = np.diff(values, prepend=np.uint64(0)).astype("<u8")
    first, rest = int(delta[0]), delta[1:]
    width = max(1, (int(rest.max()).bit_length() + 7) // 8) if len(rest) else 1
    body = np.ascontiguousarray(rest.view(np.uint8).reshape(-1, 8)[:, :width]).tobytes()
    return bytes([width]) + first.to_bytes(8, "little") + body


def unpack_sorted(data: bytes) -> np.ndarray:
    if not data:
        return np.array([], dtype=np.uint64)
    width = data[0]
    body = np.frombuffer(data, np.uint8, offset=9).reshape(-1, width)
    delta = np.zeros((len(body) + 1, 8), np.uint8)
    delta[1:, :width] = body
    delta[0] = np.frombuffer(data, np.uint8, 8, 1)
    return np.cumsum(delta.view("<u8").ravel(), dtype=np.uint64)


def pack_counts(values: np.ndarray) -> bytes:
    top = int(values.max()) if len(values) else 0
    kind = "<u1" if top < 1 << 8 else "<u4" if top < 1 << 32 else "<u8"
    return kind[2].encode() + zstandard.compress(values.astype(kind).tobytes(), 1)


def unpack_counts(data: bytes) -> np.ndarray:
    return np.frombuffer(zstandard.decompress(data[1:]), f"<u{data[:1].decode()}").astype(np.int64)


def slices(values: np.ndarray, bits: int) -> np.ndarray:
    """Bounds of the shards' runs in a sorted uint64 vector."""
    if not bits:
        return np.array([0, len(values)])
    edges = np.arange(1, 1 << bits, dtype=np.uint64) << np.uint64(64 - bits)
    return np.concatenate([[0], np.searchsorted(values, edges), [len(values)]]).astype(np.int64)
