"""Streams over page files and what can be run on them.

A stream reads the tail of a heap relation that grows at its end.  `finish` runs a streaming DataFrame to its end over
what is there now, into Parquet, and gives the result as a table.
"""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from pagelift import scan
from pagelift.plans import pages as plan
from pagelift.session import scratch


def tail(spark: SparkSession, path: str, **options) -> DataFrame:
    scan.register(spark)
    reader = spark.readStream.format("pageheap").option("path", path).option("timestamp_as", "ltz")  # watermarks need instants
    for k, v in options.items():
        reader = reader.option(k, v)
    return reader.load()


def replace_files(source: str, target: str) -> None:
    """Put one relation's bytes in another's place, file by file in order, as a server changes its files."""
    files = [plan.list_segments(x) for x in (source, target)]
    manifest = plan.manifest(target)
    manifest["files"] = []
    for k, new in enumerate(files[0]):
        path = files[1][k].path if k < len(files[1]) else f"{target}/{new.path.rsplit('/', 1)[1]}"
        plan.write_bytes(path, plan.read_bytes(new.path))
        manifest["files"].append({"path": path.rsplit("/", 1)[1], "size": new.size})
    plan.write_bytes(f"{target}/{plan.MANIFEST}", json.dumps(manifest).encode())


def place(spark: SparkSession) -> str:
    return scratch(spark, "streams")


def finish(stream: DataFrame, mode: str = "append", at: str | None = None) -> DataFrame:
    """Run to the end of the available input and read what was written; from an earlier run's place, go on from there."""
    spark, at = stream.sparkSession, at or place(stream.sparkSession)
    writer = stream.writeStream.option("checkpointLocation", f"{at}/checkpoint").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{at}/out").outputMode("append").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{at}/out")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out")

    writer.foreachBatch(keep).outputMode(mode).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


def naive(df: DataFrame) -> DataFrame:
    """Instants as date and time in UTC, whatever the session's zone."""
    at = lambda c: F.expr(f"timestampadd(MICROSECOND, unix_micros(`{c}`), TIMESTAMP_NTZ '1970-01-01 00:00:00')").alias(c)
    return df.select(*[at(f.name) if f.dataType.typeName() == "timestamp" else F.col(f.name) for f in df.schema.fields])


def windowed(stream: DataFrame, at: str, late: str, *keys) -> DataFrame:
    """Counts and sums of whole-number cents by windows (or sessions) that are columns, after a watermark."""
    return stream.withWatermark(at, late).groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))


class RunningCount(StatefulProcessor):
    """For each user: events so far.  The state is kept as long as the stream runs: it grows with the users, not the events."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.count = handle.getValueState("n", "n long")

    def handleInputRows(self, key, rows, timerValues):
        n = (self.count.get() or (0,))[0] if self.count.exists() else 0
        for pdf in rows:
            n += len(pdf)
        self.count.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    def close(self) -> None:
        pass


class IdleSessions(StatefulProcessor):
    """For each user: sessions that end when nothing comes for a while, given out once they have ended.

    A later row tells the end of a session, or an event-time timer does: the watermark has passed its last row by the gap.
    Then the user's state goes, so the state grows with the users that are active, not with all.
    """

    def __init__(self, gap_micros: int):
        self.gap = gap_micros

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle, self.open = handle, handle.getValueState("open", "first long, last long, n long")

    def _told(self, key, sessions: list[tuple[int, int, int]]) -> pd.DataFrame:
        return pd.DataFrame([(key[0], *x) for x in sessions], columns=["user_id", "first", "last", "n"])

    def handleInputRows(self, key, rows, timerValues):
        held = self.open.get() if self.open.exists() else None
        done = []
        for at in sorted(int(x) for pdf in rows for x in pdf["micros"]):
            if held is not None and at - held[1] >= self.gap:
                done.append(tuple(held))
                held = None
            held = (at, at, 1) if held is None else (min(held[0], at), max(held[1], at), held[2] + 1)
        for timer in list(self.handle.listTimers()):
            self.handle.deleteTimer(timer)
        self.open.update(held)
        self.handle.registerTimer((held[1] + self.gap) // 1000)
        yield self._told(key, done)

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):
        held = self.open.get()
        self.open.clear()
        yield self._told(key, [tuple(held)])

    def close(self) -> None:
        pass
