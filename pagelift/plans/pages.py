"""Planning of page scans: relations, page runs, splits, and pruning."""

from __future__ import annotations

import glob
import json
import os
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
from pyarrow.dataset import dataset
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pagelift.formats.brin import RangePredicate, Ranges, keep
from pagelift.formats.heap import Segment, segment_order
from pagelift.schema import StorageColumn

MANIFEST = "_manifest.json"
SUMMARIES = "_summaries.json"  # tells that an index is a table of summaries
#: Above this many ranges an index is a table that executors write, and a scan with a range prunes by a Spark job over it.
DRIVER_RANGES = 1_000_000


@dataclass(frozen=True)
class PageRun:
    """Pages first..first+count-1 of a file; base is the file's first page number in the relation."""

    path: str
    first: int
    count: int
    base: int
    size: int = 0
    changed: int = 0
    window: tuple[int, int] | None = None  # of line pointers, see heap.tuples


def file_system(path: str) -> tuple[pafs.FileSystem, str]:
    if "://" in path or path.startswith("file:"):
        return pafs.FileSystem.from_uri(path if "://" in path else "file://" + path[5:])
    return pafs.LocalFileSystem(), os.path.abspath(path)


def read_bytes(path: str) -> bytes:
    fs, at = file_system(path)
    with fs.open_input_file(at) as f:
        return f.read()


def write_bytes(path: str, data: bytes) -> None:
    fs, at = file_system(path)
    fs.create_dir(os.path.dirname(at), recursive=True)
    with fs.open_output_stream(at) as f:
        f.write(data)


def exists(path: str) -> bool:
    fs, at = file_system(path)
    return fs.get_file_info([at])[0].type != pafs.FileType.NotFound


def expand(path: str) -> list[str]:
    """A path, several with commas between, or a glob: relations that are read as one."""
    out = []
    for p in path.split(","):
        out += sorted(glob.glob(p)) if "*" in p and "://" not in p else [p]
    if not out:
        raise FileNotFoundError(f"no relation at {path}")
    return out


def manifest(path: str) -> dict | None:
    at = f"{path.rstrip('/')}/{MANIFEST}"
    return json.loads(read_bytes(at)) if exists(at) else None


def list_segments(path: str) -> list[Segment]:
    """Files of one relation in page order: those of the manifest, or a base file and its numbered segments."""
    fs, at = file_system(path)
    info = fs.get_file_info([at])[0]
    if info.type == pafs.FileType.NotFound:
        raise FileNotFoundError(path)
    if info.type == pafs.FileType.Directory:
        m = manifest(path)
        found = fs.get_file_info(pafs.FileSelector(at))
        if m is not None:
            changed = {os.path.basename(f.path): f.mtime_ns or 0 for f in found}
            return [Segment(f"{path.rstrip('/')}/{f['path']}", f["size"], changed.get(f["path"], 0)) for f in m["files"]]
        files = [f for f in found if f.type == pafs.FileType.File and not os.path.basename(f.path).startswith(("_", "."))]
        prefix = path.rstrip("/")
        ordered = sorted(files, key=lambda f: segment_order(f.path))
        return [Segment(f"{prefix}/{os.path.basename(f.path)}", f.size, f.mtime_ns or 0) for f in ordered]
    folder, name = os.path.split(at)
    found = [f for f in fs.get_file_info(pafs.FileSelector(folder)) if segment_order(os.path.basename(f.path))[0] == name and f.type == pafs.FileType.File]
    prefix = path[: len(path) - len(name)]
    return [Segment(prefix + os.path.basename(f.path), f.size, f.mtime_ns or 0) for f in sorted(found, key=lambda f: segment_order(f.path))]


def split_pages(segments: list[Segment], page_size: int, target_bytes: int) -> list[PageRun]:
    """Even runs of about target_bytes, none over a file's end.  Bytes after a file's last whole page are an error later."""
    out, base, per = [], 0, max(1, target_bytes // page_size)
    for s in segments:
        pages = s.size // page_size
        parts = max(1, -(-pages // per))
        for k in range(parts if pages else 0):
            a, b = pages * k // parts, pages * (k + 1) // parts
            out.append(PageRun(s.path, a, b - a, base, s.size, s.changed))
        base += pages
    return out


def runs(mask: np.ndarray) -> list[tuple[int, int]]:
    """(first, count) of the true stretches."""
    edges = np.flatnonzero(np.diff(np.r_[0, mask.astype(np.int8), 0]))
    return [(int(a), int(b - a)) for a, b in zip(edges[::2], edges[1::2])]


def clip(splits: list[PageRun], kept: list[tuple[int, int]], pages_per_range: int) -> list[PageRun]:
    """The parts of splits that lie in kept ranges; pages that aren't kept are never opened."""
    spans = [(a * pages_per_range, (a + n) * pages_per_range) for a, n in kept]
    out, k = [], 0
    for s in splits:
        lo, hi = s.base + s.first, s.base + s.first + s.count
        while k < len(spans) and spans[k][1] <= lo:
            k += 1
        j = k
        while j < len(spans) and spans[j][0] < hi:
            a, b = max(lo, spans[j][0]), min(hi, spans[j][1])
            if a < b:
                out.append(PageRun(s.path, a - s.base, b - a, s.base, s.size, s.changed))
            j += 1
    return out


def prune(splits: list[PageRun], ranges: Ranges, predicate: RangePredicate | None) -> tuple[list[PageRun], dict]:
    mask = ~ranges.usable if isinstance(ranges, Excluded) else keep(ranges, predicate)
    kept = clip(splits, runs(mask), ranges.pages_per_range)
    return kept, {"ranges_total": len(ranges), "ranges_kept": int(mask.sum()), "pages_total": sum(s.count for s in splits), "pages_read": sum(s.count for s in kept)}


def prune_distributed(ranges: DataFrame, predicate: Column, pages_per_range: int, gap: int = 0) -> DataFrame:
    """Page runs (first_page, n_pages) to read, from a summaries table (range_no, usable and the columns that the
    predicate is on), without bringing summaries to the driver.  Ranges at most gap apart are read as one run.

    Runs are found within blocks of ranges and so never need a global sort; a run that crosses a block's border is
    reported in two parts.
    """
    kept = ranges.where(F.coalesce(~F.col("usable"), F.lit(True)) | F.coalesce(predicate, F.lit(True))).select("range_no")
    block = F.floor(F.col("range_no") / 65_536)
    w = Window.partitionBy("block").orderBy("range_no")
    starts = kept.withColumn("block", block).withColumn("new", F.when(F.col("range_no") - F.lag("range_no").over(w) <= gap + 1, 0).otherwise(1))
    islands = starts.withColumn("island", F.sum("new").over(w)).groupBy("block", "island").agg(F.min("range_no").alias("a"), F.max("range_no").alias("b"))
    return islands.select((F.col("a") * pages_per_range).alias("first_page"), ((F.col("b") - F.col("a") + 1) * pages_per_range).alias("n_pages"))


def ranges_of_table(index: str, found: dict | None, column: StorageColumn, pages: int, predicate: RangePredicate | None) -> Ranges | None:
    """What a pushed filter leaves of a table of summaries: its ranges stream by, and one bit of each is kept."""
    told = json.loads(read_bytes(f"{index}/{SUMMARIES}"))
    if told["relation"] != (found or {}).get("relation") or told["column"] != column.name:
        return None
    per = told["pages_per_range"]
    n = -(-pages // per)
    usable = np.zeros(n, bool)
    if predicate is not None:
        whole = -(-told["pages"] // per) if pages == told["pages"] else told["pages"] // per  # the last may have grown
        kind = column.arrow_type()
        value = lambda v: pa.scalar(v.decode() if isinstance(v, bytes) and not pa.types.is_binary(kind) else v, pa.int64() if pa.types.is_timestamp(kind) else pa.int32() if pa.types.is_date(kind) else kind).cast(kind)
        gone = pc.scalar(False)
        if predicate.low is not None:
            gone |= pc.field("high") < value(predicate.low)
        if predicate.high is not None:
            gone |= pc.field("low") > value(predicate.high)
        if predicate.values is not None:
            among = pc.scalar(False)
            for v in predicate.values:
                among |= (pc.field("low") <= value(v)) & (pc.field("high") >= value(v))
            gone |= ~among
        fs, at = file_system(f"{index}/ranges")
        table = dataset(at, filesystem=fs, format="parquet")
        for batch in table.to_batches(columns=["range_no"], filter=(pc.field("n") > 0) & (pc.field("range_no") < whole) & gone):
            usable[np.asarray(batch.column(0))] = True
    # a usable range here is one that the predicate excludes: bounds that nothing meets
    top, bottom = np.full(n, np.inf), np.full(n, -np.inf)
    return Excluded(per, usable, top, bottom, np.zeros(n, bool), np.zeros(n, bool))


class Excluded(Ranges):
    """Ranges whose predicate is settled: usable ones are excluded."""
