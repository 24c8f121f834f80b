"""Helpers shared by the corpus operators: table access, bucket planning, lineage cuts, word coding."""

from __future__ import annotations

import atexit
import gc
import uuid

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.session import shared_dir

#: Text bytes that one exchange batch aims at; a worker holds a few numpy vectors of this many words.
BATCH_BYTES = 6 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cut(spark: SparkSession, df: DataFrame, label: str) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back, so that a lost executor costs no recomputation."""
    path = f"{shared_dir(spark)}/pagelift-{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._pagelift_path = path
    atexit.register(drop, spark, out)
    return out


def drop(spark: SparkSession, df: DataFrame) -> None:
    """Delete the files of a cut that no later step reads."""
    path, df._pagelift_path = getattr(df, "_pagelift_path", None), None
    if path is None:
        return
    try:
        jvm = spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session has ended; the folder goes with it
        return


def release(spark: SparkSession) -> None:
    """Let the driver collect its garbage, so that shuffle files of finished steps leave the executors' disks."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def text_bytes(df: DataFrame, col: str = "text") -> tuple[int, int]:
    """Rows and text bytes of the whole table: one aggregate over one column."""
    n, b = df.agg(F.count(F.lit(1)), F.sum(F.octet_length(col))).first()
    return int(n), int(b or 0)


def documents(df: DataFrame) -> DataFrame:
    """The two columns the operators work on, whatever else the table carries."""
    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def names_of(ddl: str) -> list[str]:
    """Column names of a flat schema text."""
    return [part.split()[0] for part in ddl.split(", ")]


def thrifty(batches, rows: int = 500):
    """The batches in slices of few rows; what Arrow has set aside goes back after each batch, as workers live on."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)
        pa.default_memory_pool().release_unused()


def raw(column: pa.Array | pa.ChunkedArray) -> list[bytes | None]:
    """The UTF-8 bytes of a string column, without decoding."""
    kind = column.type
    if pa.types.is_large_string(kind):
        return column.cast(pa.large_binary()).to_pylist()
    return column.cast(pa.binary()).to_pylist()


class WordIds(dict):
    """Word bytes -> dense local number; hashes[i] is the 64-bit hash of word i."""

    def __init__(self):
        super().__init__()
        self.hashes: list[int] = []

    def __missing__(self, word: bytes) -> int:
        n = self[word] = len(self.hashes)
        self.hashes.append(xxhash.xxh64_intdigest(word))
        return n

    def code(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), dtype=np.int64, count=len(words))

    def table(self) -> np.ndarray:
        return np.array(self.hashes, dtype=np.uint64)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (murmur-style) over a vector."""
    h = h ^ (h >> np.uint64(33))
    h *= np.uint64(0xFF51AFD7ED558CCD)
    h ^= h >> np.uint64(33)
    h *= np.uint64(0xC4CEB9FE1A85EC53)
    h ^= h >> np.uint64(33)
    return h


def pair_hash(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Hash of an ordered pair of hashes."""
    return mix(left * np.uint64(0x9E3779B97F4A7C15) + right)


def crc_mod(col: str, n: int):
    """crc32(col as text) mod n, as a Column."""
    return F.pmod(F.crc32(F.col(col).cast("string").cast("binary")), F.lit(n).cast("long"))
