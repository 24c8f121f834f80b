"""Spark data sources `pageheap` and `pagetree`: readers, writers and a stream over page files.

Executors read page runs with large sequential reads and yield Arrow batches; the driver only lists files, reads the
range index and plans runs.  A reader that takes filters is returned only for the option `pushdown`, as Spark refuses
one while its configuration for that is off.
"""

from __future__ import annotations

import json
import os
import re
import uuid
import zlib
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql.datasource import (
    DataSource,
    DataSourceArrowWriter,
    DataSourceReader,
    DataSourceStreamReader,
    EqualNullSafe,
    EqualTo,
    GreaterThan,
    GreaterThanOrEqual,
    In,
    InputPartition,
    LessThan,
    LessThanOrEqual,
    WriterCommitMessage,
)
from pyspark.sql.types import BinaryType, LongType, StringType, StructField, StructType

from pagelift.formats import brin, cell, heap, tree
from pagelift.formats.brin import RangePredicate
from pagelift.plans import pages as plan
from pagelift.schema import StorageSchema

OVERFLOW_AT = 1800  # bytes from which a value moves to overflow storage, where that is asked for
CHUNK = 1900  # payload bytes of an overflow chunk
CHUNKS = StorageSchema.parse("value_id:int8!,seq:int4!,data:binary")
HELD_CHUNKS = 2000  # chunks that a task holds before it writes them
#: Bits of a value's number: the write to the relation, the partition, the value within it.
WRITE_BITS, PART_BITS, VALUE_BITS = 15, 20, 28


@dataclass
class Part(InputPartition):
    runs: list

    def __init__(self, runs):
        self.runs = runs


def _flag(options, name: str, default: str = "false") -> bool:
    return str(options.get(name, default)).lower() == "true"


class PagedReader(DataSourceReader):
    """Of any format."""

    kind, page_size = "pageheap", heap.PAGE

    def __init__(self, schema: StructType, options: dict, storage: StorageSchema, found: dict | None):
        self.output, self.options, self.storage, self.manifest = schema, dict(options), storage, found or {}
        self.names = [f.name for f in schema.fields if not f.name.startswith("_")]
        self.predicate: RangePredicate | None = None
        if options.get("range"):
            self.predicate = RangePredicate.parse(options["range"])

    # -- planning

    def segments(self):
        out = []
        for path in plan.expand(self.options["path"]):
            out += plan.list_segments(path)
        return out

    def split_bytes(self, segments) -> int:
        """Bytes a task reads: about a thousandth of the input within bounds, so that small inputs still use many cores
        and 100 TB make a hundred thousand tasks."""
        given = self.options.get("split_bytes")
        return int(given) if given else min(1 << 30, max(4 << 20, sum(s.size for s in segments) // 1024))

    def plan(self) -> tuple[list[plan.PageRun], dict]:
        segments = self.segments()
        self.target = self.split_bytes(segments)
        splits = plan.split_pages(segments, self.page_size, self.target)
        total = sum(s.count for s in splits)
        return splits, {"ranges_total": 0, "ranges_kept": 0, "pages_total": total, "pages_read": total}

    def partitions(self):
        runs, _ = self.plan()
        target = max(1, self.target // self.page_size)
        parts, held, size = [], [], 0
        for r in runs:  # runs left by pruning can be short: several make one task
            if held and size + r.count > target:
                parts.append(Part(held))
                held, size = [], 0
            held.append(r)
            size += r.count
        if held:
            parts.append(Part(held))
        return parts or [Part([])]

    # -- reading

    def blocks(self, run: plan.PageRun):
        """(number of the first page in the file, pages) in large reads."""
        fs, at = plan.file_system(run.path)
        per = int(self.options.get("pages_per_read", 256))
        share = float(self.options.get("sample_pages", 1))
        with fs.open_input_file(at) as f:
            if str(self.options.get("snapshot", "strict")) == "strict":
                changed = run.changed and fs.get_file_info([at])[0].mtime_ns != run.changed
                if changed or (run.size and f.size() != run.size):
                    raise heap.PageError(f"{run.path} changed after the scan was planned")
            if f.size() % self.page_size:
                raise heap.PageError(f"{run.path} doesn't end with a whole page")
            f.seek(run.first * self.page_size)
            for first in range(run.first, run.first + run.count, per):
                n = min(per, run.first + run.count - first)
                if share < 1 and zlib.crc32(f"{os.path.basename(run.path)}:{first}".encode()) >= share * (1 << 32):
                    f.seek((first + n) * self.page_size)  # not in the sample, which is the same each time
                    continue
                raw = f.read(n * self.page_size)
                if len(raw) != n * self.page_size:
                    raise heap.PageError(f"{run.path} ends within a page")
                yield first, np.frombuffer(raw, np.uint8).reshape(n, self.page_size)

    def decode(self, pages: np.ndarray, base: int, window: tuple[int, int] | None = None) -> pa.RecordBatch:
        raise NotImplementedError

    def generated(self, pages: np.ndarray, kind: str, index_id: int | None = None) -> pa.RecordBatch:
        """Rows by the source that came as an option."""
        from pagelift.synth.deploy import load
        from pagelift.synth.spec import column_spec

        if not _flag(self.options, "allow_generated"):
            raise ValueError("the option reader runs the source it holds; allow that with allow_generated")
        return load(self.options["reader"])(pages, column_spec(self.storage, kind), self.names, index_id)

    def headers(self, pages: np.ndarray) -> tuple[np.ndarray, ...]:
        """The columns of HEADERS for some pages."""
        raise NotImplementedError

    def shown(self, run: plan.PageRun, what: str):
        """Page headers, or whole blocks of pages, instead of rows."""
        for first, block in self.blocks(run):
            if what == "blocks":
                columns = ([run.path], [run.base + first], [block.tobytes()])
            else:
                columns = ([run.path] * len(block), run.base + first + np.arange(len(block)), *self.headers(block))
            schema = pa.schema([(f.name, {"string": pa.string(), "binary": pa.binary()}.get(f.dataType.simpleString(), pa.int64())) for f in self.output.fields])
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema)], schema=schema)

    def read(self, partition):
        what = self.options.get("as", "rows")
        if what != "rows":
            for run in partition.runs:
                yield from self.shown(run, what)
            return
        limit = int(self.options.get("max_rows", 65_536))
        for run in partition.runs:
            for first, block in self.blocks(run):
                window = None
                if run.window:  # it is the run's; of a block, only what the block holds of the run's ends
                    window = (run.window[0] if first == run.first else 0, run.window[1] if first + len(block) == run.first + run.count else -1)
                batch = self.decode(block, run.base + first, window)
                for at in range(0, batch.num_rows, limit):
                    yield batch.slice(at, limit)


class HeapReader(PagedReader):
    def headers(self, pages):
        page, _, state, _ = heap.line_pointers(pages)
        n = len(pages)
        return *heap.page_headers(pages), np.bincount(page, minlength=n), np.bincount(page[state == heap.NORMAL], minlength=n)

    def index(self, heap_pages: int):
        path = self.options.get("index_path")
        column = self.options.get("index_column") or (self.predicate.column if self.predicate else None)
        if not path or column is None or (self.predicate and self.predicate.column != column):
            return None, None
        if plan.exists(f"{path}/{plan.SUMMARIES}"):
            return plan.ranges_of_table(path, self.manifest, self.storage[column], heap_pages, self.predicate), column
        data = plan.read_bytes(path)
        relation = brin.covered(data)[1]
        if relation and relation != self.manifest.get("relation"):
            return None, None  # the relation was written anew after its index
        return brin.load(data, self.storage[column], heap_pages, self.options.get("null_flags", "paired")), column

    def plan(self):
        splits, counts = super().plan()
        if self.options.get("runs"):  # found by a job
            found = np.frombuffer(plan.read_bytes(self.options["runs"]), "<i8").reshape(-1, 2)
            kept = plan.clip(splits, found.tolist(), 1)
            return kept, counts | {"pages_read": sum(s.count for s in kept)}
        ranges, _ = self.index(counts["pages_total"])
        if ranges is None or not self.predicate or not _flag(self.options, "prune", "true"):
            return splits, counts
        return plan.prune(splits, ranges, self.predicate)

    def decode(self, pages, base, window=None):
        o = self.options
        if o.get("reader"):
            return self.generated(pages, "pageheap")
        paged = any(f.name == "_page" for f in self.output.fields)
        return heap.decode(pages, self.storage, self.names, o.get("visibility", "delete_only"), o.get("numeric_as", "double"), o.get("timestamp_as", "ntz"), o.get("on_overflow", "error"), base if paged else None, window)


class TreeReader(PagedReader):
    """Bounds of the leading key leave out whole files, where the manifest tells theirs, and leaf pages before they are
    decoded."""

    kind, page_size = "pagetree", tree.PAGE

    def plan(self):
        runs, counts = super().plan()
        p = self.predicate
        if not p or p.column != self.storage.physical()[0].name or not _flag(self.options, "prune", "true"):
            return runs, counts
        bounds = {f"{path.rstrip('/')}/{f['path']}": f["keys"] for path in plan.expand(self.options["path"]) for f in (plan.manifest(path) or {"files": []})["files"] if f.get("keys")}
        outside = {path for path, (low, high) in bounds.items() if (p.low is not None and high < p.low) or (p.high is not None and low > p.high)}
        kept = [r for r in runs if r.path not in outside]
        return kept, counts | {"pages_read": sum(r.count for r in kept)}

    def _index_id(self, run: plan.PageRun):
        fs, at = plan.file_system(run.path)
        with fs.open_input_file(at) as f:
            n = min(8, f.size() // tree.PAGE)
            return tree.discover_index(np.frombuffer(f.read(n * tree.PAGE), np.uint8).reshape(n, tree.PAGE))

    def headers(self, pages):
        leaves = np.flatnonzero(tree.index_pages(pages) & tree.leaf_pages(pages))
        page, _ = tree.record_origins(pages, leaves)
        return tree._u16(pages, 24), tree._u16(pages, 64), tree.index_ids(pages), np.bincount(page, minlength=len(pages))

    def read(self, partition):
        if self.options.get("as", "rows") != "rows":
            yield from super().read(partition)
            return
        self._ids = {r.path: self._index_id(r) for r in {r.path: r for r in partition.runs}.values()}
        limit = int(self.options.get("max_rows", 65_536))
        for run in partition.runs:
            self._id, self._path, self._side = self._ids[run.path], run.path, None
            for first, block in self.blocks(run):
                batch = self.decode(block, run.base + first)
                for at in range(0, batch.num_rows, limit):
                    yield batch.slice(at, limit)

    def decode(self, pages, base, window=None):
        o, bounds = self.options, None
        if o.get("reader"):
            return self.generated(pages, "pagetree", self._id)
        first = self.storage.physical()[0].name
        if self.predicate and self.predicate.column == first and _flag(o, "prune", "true"):
            bounds = (self.predicate.low, self.predicate.high)
        paged = any(f.name == "_page" for f in self.output.fields)
        return tree.decode(pages, self.storage, self.names, self._id, o.get("numeric_as", "double"), o.get("timestamp_as", "ntz"), o.get("float_codec", self.manifest.get("float_codec", "ordered")), o.get("prefix", self.manifest.get("prefix", "declared")), bounds, o.get("on_overflow", "error"), base if paged else None, self._fetch)

    def _fetch(self, first: int, length: int) -> bytes:
        """A value on pages of its own, of the file that is being read."""
        if self._side is None:
            fs, at = plan.file_system(self._path)
            self._side = _Ahead(fs.open_input_file(at), tree.PAGE)
        return tree.chained(self._side.read, first, length)


class _Ahead:
    """Reads pages of a file; while wishes follow each other in the file, many pages at once."""

    MANY = 256

    def __init__(self, f, page_size: int):
        self.f, self.size, self.start, self.held, self.following = f, page_size, 0, b"", -1

    def read(self, page: int, count: int) -> bytes:
        at = (page - self.start) * self.size
        if not 0 <= at <= len(self.held) - count * self.size:
            ahead = max(count, self.MANY) if page == self.following else count
            self.f.seek(page * self.size)
            self.start, self.held, at = page, self.f.read(ahead * self.size), 0
        self.following = page + count
        return self.held[at : at + count * self.size]


class CellReader(PagedReader):
    """Of SQLite 3 database files, one or several with the same table.  Bounds of a key that is the row number leave out what
    the interior pages exclude."""

    kind = "pagecell"

    def __init__(self, schema, options, storage, found, lay: cell.Layout):
        super().__init__(schema, options, storage, found)
        self.layout, self.page_size = lay, lay.page

    def plan(self):
        """Runs of leaf pages of the table's tree, which is found through its interior pages."""
        segments, runs, total, bounds = self.segments(), [], 0, ()
        if self.predicate and self.storage.key == (self.predicate.column,) and _flag(self.options, "prune", "true"):
            bounds = (self.predicate.low, self.predicate.high)  # the key is the row number
        self.target, per = self.split_bytes(segments), max(1, self.split_bytes(segments) // self.page_size)
        for s in segments:
            total += s.size // self.page_size
            numbers = tree_pages(s.path, self.options["table"], self.layout, *bounds) - 1
            if not len(numbers):
                continue
            for part in np.split(numbers, np.flatnonzero(np.diff(numbers) != 1) + 1):
                runs += [plan.PageRun(s.path, int(part[k]), min(per, len(part) - k), 0, s.size, s.changed) for k in range(0, len(part), per)]
        return runs, {"ranges_total": 0, "ranges_kept": 0, "pages_total": total, "pages_read": sum(r.count for r in runs)}

    def read(self, partition):
        for run in partition.runs:
            fs, at = plan.file_system(run.path)
            with fs.open_input_file(at) as side:
                self._fetch = (lambda first, length, side=side: cell.chained(page_reader(side, self.layout), self.layout, first, length)) if self.options.get("on_overflow") == "resolve" else None
                yield from super().read(Part([run]))

    def decode(self, pages, base, window=None):
        o, key = self.options, self.storage.key
        if o.get("reader"):
            return self.generated(pages, "pagecell")
        return cell.decode(pages, self.layout, self.storage, self.names, base, self._fetch, o.get("numeric_as", "double"), o.get("timestamp_as", "ntz"), key[0] if len(key) == 1 else None)


def page_reader(f, lay: cell.Layout):
    """Pages of an open file, by first number (from 1) and count."""

    def read(number: int, count: int) -> np.ndarray:
        f.seek((number - 1) * lay.page)
        raw = f.read(count * lay.page)
        return np.frombuffer(raw[: len(raw) // lay.page * lay.page], np.uint8).reshape(-1, lay.page)

    return read


def _opened(path: str):
    fs, at = plan.file_system(path)
    return fs.open_input_file(at)


def file_layout(path: str) -> cell.Layout:
    with _opened(path) as f:
        return cell.layout(f.read(cell.FILE_HEADER))


def tables_of(path: str, lay: cell.Layout) -> dict[str, tuple[int, str]]:
    """Root page and definition of each table of a database file."""
    with _opened(path) as f:
        read = page_reader(f, lay)
        out = {}
        for number in cell.leaves(read, 1).tolist():
            batch = cell.decode(read(number, 1), lay, cell.MASTER, first=number - 1, fetch=lambda a, n: cell.chained(read, lay, a, n))
            out |= {r["name"]: (r["rootpage"], r["sql"]) for r in batch.to_pylist() if r["type"] == "table"}
    return out


def tree_pages(path: str, table: str, lay: cell.Layout, low: int | None = None, high: int | None = None) -> np.ndarray:
    """Leaf pages of a table with row numbers from low to high."""
    found = tables_of(path, lay)
    if table not in found:
        raise ValueError(f"{path} has no table {table}")
    with _opened(path) as f:
        return cell.leaves(page_reader(f, lay), found[table][0], low, high)


def declared_schema(sql: str) -> StorageSchema:
    """A storage schema from a table's definition: its columns' names and declared types."""
    text, key = re.sub(r"^[^(]*\(|\)[^)]*$", "", sql, flags=re.S), ()
    columns = []
    for m in re.finditer(r"[\"`\[]?(\w+)[\"`\]]?\s+(\w+)([^,(]*(?:\([^)]*\))?[^,]*)(?:,|$)", text):
        kind = m[2].upper()
        kind = "int8" if "INT" in kind else "float8" if kind in ("REAL", "DOUBLE", "FLOAT") else "bool" if kind == "BOOLEAN" else "date" if kind == "DATE" else "timestamp" if kind == "TIMESTAMP" else "binary" if kind == "BLOB" else "text"
        if kind == "int8" and "PRIMARY KEY" in m[3].upper():
            key = (m[1],)
        columns.append(f"{m[1]}:{kind}{'!' if m[1] in key or 'NOT NULL' in m[3].upper() else ''}")
    return StorageSchema.parse(",".join(columns), key)


class _Pushing:
    """Adds filter pushdown; every filter stays above the scan as well, as ranges are coarse."""

    def pushFilters(self, filters):
        first = {"pagetree": self.storage.physical()[0].name, "pagecell": self.storage.key[0] if self.storage.key else None}.get(self.kind)
        column = self.options.get("index_column") or first
        found = self.predicate
        for f in filters:
            name = f.attribute[0] if len(f.attribute) == 1 else None
            if name is None or (column and name != column) or name not in self.names:
                continue
            kind = self.storage[name].kind
            value = lambda v, kind=kind: brin.comparable(v, kind)
            new = None
            if isinstance(f, (EqualTo, EqualNullSafe)) and f.value is not None:
                new = RangePredicate(name, value(f.value), value(f.value))
            elif isinstance(f, (GreaterThan, GreaterThanOrEqual)):
                new = RangePredicate(name, value(f.value), None)
            elif isinstance(f, (LessThan, LessThanOrEqual)):
                new = RangePredicate(name, None, value(f.value))
            elif isinstance(f, In):
                values = tuple(value(v) for v in f.value if v is not None)
                if values:
                    new = RangePredicate(name, min(values), max(values), values)
            if new:
                found = new if found is None else found.to_closed(new) if found.column == name else found
        self.predicate = found
        return filters


class PushingHeapReader(_Pushing, HeapReader):
    pass


class PushingTreeReader(_Pushing, TreeReader):
    pass


class PushingCellReader(_Pushing, CellReader):
    pass


@dataclass
class Written(WriterCommitMessage):
    partition: int
    files: list
    overflow: list
    rows: int


class PagedWriter(DataSourceArrowWriter):
    page_size = heap.PAGE

    def __init__(self, schema: StructType, options: dict, overwrite: bool):
        self.options, self.overwrite = dict(options), overwrite
        key = tuple(k for k in options.get("pk", "").split(",") if k)
        self.storage = StorageSchema.parse(options["columns_spec"], key) if options.get("columns_spec") else StorageSchema.from_struct(schema, key=key)
        if key and not self.storage.key:
            self.storage = StorageSchema(self.storage.columns, key)
        self.path, self.attempt = options["path"].rstrip("/"), uuid.uuid4().hex[:8]
        old = None if overwrite else plan.manifest(self.path)
        self.number = old.get("writes", 1) if old else 0
        if self.number >> WRITE_BITS:
            raise ValueError(f"{self.path} was appended to {self.number} times; write it anew")
        self.segment_pages = int(options.get("segment_pages", (1 << 30) // self.page_size))

    def pages(self, batch, state):
        raise NotImplementedError

    def _moved(self, batch: pa.RecordBatch, state: dict, out: _Segments) -> dict[str, np.ndarray] | None:
        """For each column that can have long values, where each row's is kept; 0: in the row."""
        if self.options.get("overflow", "false") != "true":
            return None
        moved = {}
        for c in self.storage.columns:
            if not (c.is_text and not 0 < c.max_len <= 255 or c.kind == "binary"):
                continue
            column = batch.column(c.name).cast(pa.binary())
            moved[c.name] = np.zeros(batch.num_rows, np.int64)
            sizes = np.array(pc.binary_length(column).fill_null(0))
            for i in np.flatnonzero(sizes > OVERFLOW_AT).tolist():
                moved[c.name][i] = self._away(column[i].as_py(), state, out)
        return moved

    def _away(self, value: bytes, state: dict, out: _Segments) -> int:
        """Keep a long value as chunks in a relation of its own; its number."""
        state["values"] += 1
        if state["values"] >> VALUE_BITS:
            raise ValueError("too many long values in a partition; write it in more partitions")
        number = state["first"] + state["values"]
        state["chunks"] += [(number, k, value[at : at + CHUNK]) for k, at in enumerate(range(0, len(value), CHUNK))]
        if len(state["chunks"]) >= HELD_CHUNKS:
            self._put(state)
        return number

    def _put(self, state: dict) -> None:
        ids, seqs, data = zip(*state["chunks"])
        state["side"].add(heap.encode(pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(seqs, pa.int32()), pa.array(data, pa.binary())], names=CHUNKS.names), CHUNKS))
        state["chunks"] = []

    def write(self, iterator):
        part = TaskContext.get().partitionId()
        name = f"part-{part:05d}-{self.attempt}-{uuid.uuid4().hex[:6]}"
        if part >> PART_BITS:
            raise ValueError("too many partitions")
        # long values are numbered by write, partition and place: no other value of the relation has that number
        first = (self.number << PART_BITS | part) << VALUE_BITS
        side = _Segments(f"{self.path}/_overflow", name, heap.PAGE, 1 << 17, None)
        state = {"first": first, "values": 0, "chunks": [], "side": side, "page": self.first_page(), "row": 1 + (part << 32)}
        out, rows = _Segments(self.path, name, self.page_size, self.segment_pages, self.start_pages()), 0
        for batch in iterator:
            batch = pa.RecordBatch.from_arrays([batch.column(i) for i in range(batch.num_columns)], schema=batch.schema)
            moved = self._moved(batch, state, out)
            pages = self.pages(batch, moved, state)
            state["page"] += len(pages)
            state["row"] += batch.num_rows
            rows += batch.num_rows
            out.add(pages)
        self.finish(out, state)
        if state["chunks"]:
            self._put(state)
        files = out.close()
        if state.get("keys") and len(files) == 1:
            files[0]["keys"] = state["keys"]  # what the leading key goes from and to in the file
        return Written(part, files, side.close(), rows)

    def first_page(self):
        return 0

    def start_pages(self):
        return None

    def finish(self, out, state):
        pass

    def commit(self, messages):
        messages = sorted((m for m in messages if m is not None), key=lambda m: m.partition)
        old = None if self.overwrite or not plan.exists(f"{self.path}/{plan.MANIFEST}") else plan.manifest(self.path)
        if not self.overwrite and (old.get("writes", 1) if old else 0) != self.number:
            raise ValueError(f"{self.path} was written by another job meanwhile; write again")
        m = {"format": self.format, "columns": self.storage.to_json(), "files": (old["files"] if old else []) + [f for x in messages for f in x.files], "rows": (old["rows"] if old else 0) + sum(x.rows for x in messages), "float_codec": self.options.get("float_codec", "ordered"), "prefix": self.options.get("prefix", "declared"), "writes": self.number + 1, "relation": (old or {}).get("relation") or uuid.uuid4().int >> 65}
        chunks = [f for x in messages for f in x.overflow]
        if chunks or old:
            known = plan.manifest(f"{self.path}/_overflow") if old and plan.exists(f"{self.path}/_overflow/{plan.MANIFEST}") else {"files": []}
            if chunks or known["files"]:
                plan.write_bytes(f"{self.path}/_overflow/{plan.MANIFEST}", json.dumps({"format": "pageheap", "columns": CHUNKS.to_json(), "files": known["files"] + chunks, "rows": 0}).encode())
        plan.write_bytes(f"{self.path}/{plan.MANIFEST}", json.dumps(m).encode())  # last: a reader sees all or nothing

    def abort(self, messages):
        for m in messages:
            for f in m.files if m is not None else []:
                fs, at = plan.file_system(f"{self.path}/{f['path']}")
                try:
                    fs.delete_file(at)
                except OSError:
                    pass


class _Segments:
    """Writes pages into a base file and its numbered segments."""

    def __init__(self, folder: str, name: str, page_size: int, segment_pages: int, start):
        self.folder, self.name, self.page_size, self.limit, self.start = folder, name, page_size, segment_pages, start
        self.files, self.out, self.held = [], None, 0

    def _open(self):
        suffix = f".{len(self.files)}" if self.files else ""
        self.at = f"{self.name}{suffix}"
        fs, path = plan.file_system(f"{self.folder}/{self.at}")
        fs.create_dir(os.path.dirname(path), recursive=True)
        self.out, self.held = fs.open_output_stream(path), 0
        if self.start is not None:
            self.out.write(self.start.tobytes())
            self.held = len(self.start)

    def _shut(self):
        if self.out is not None:
            self.out.close()
            self.files.append({"path": self.at, "size": self.held * self.page_size})
            self.out = None

    def add(self, pages: np.ndarray):
        while len(pages):
            if self.out is None:
                self._open()
            n = min(len(pages), max(1, self.limit - self.held))
            self.out.write(pages[:n].tobytes())
            self.held += n
            pages = pages[n:]
            if self.held >= self.limit:
                self._shut()

    def close(self):
        self._shut()
        return self.files


class HeapWriter(PagedWriter):
    format = "pageheap"

    def pages(self, batch, moved, state):
        o = self.options
        return heap.encode(batch, self.storage, int(o.get("fill_factor", 100)), _flag(o, "long_numeric"), int(o.get("dead_pointers", 0)), moved)


class TreeWriter(PagedWriter):
    format = "pagetree"
    page_size = tree.PAGE

    def __init__(self, schema, options, overwrite):
        super().__init__(schema, options, overwrite)
        self.segment_pages = 1 << 40  # a tablespace is one file

    def first_page(self):
        return tree.ROOT + 1

    def start_pages(self):
        return tree.file_start(40)

    def _away(self, value, state, out):
        """Keep a long value on a chain of pages of the file; the first one's number."""
        pages, first = tree.value_pages(value, state["page"]), state["page"]
        state["page"] += len(pages)
        out.add(pages)
        return first

    def pages(self, batch, moved, state):
        o, first = self.options, self.storage.physical()[0]
        if first.kind in ("int2", "int4", "int8") and batch.num_rows:
            low, high = (x.as_py() for x in (pc.min(batch.column(first.name)), pc.max(batch.column(first.name))))
            state["keys"] = [min(low, state.get("keys", [low])[0]), max(high, state.get("keys", [high])[-1])]
        return tree.encode(batch, self.storage, state["page"], 40, o.get("float_codec", "ordered"), o.get("prefix", "declared"), int(o.get("fill_factor", 94)), state["row"], moved)

    def finish(self, out, state):
        if _flag(self.options, "decoy_index") and out.out is not None:
            out.add(np.vstack([tree.decoy(state["page"] + k, 41) for k in range(2)]))
        levels = int(self.options.get("interior_levels", 0))
        if levels and out.out is not None:
            out.add(np.vstack([tree.decoy(state["page"] + k, 40, level=k + 1) for k in range(levels)]))


class HeapStream(DataSourceStreamReader):
    """Tail of a relation that grows at its end: by files, by pages, and by rows of its last page.

    An offset is the number of pages and of the last page's line pointers.  A batch takes what came after its start in the
    page that was the last then, and all pages since; of its own last page, the line pointers that its end counted.  Rows
    that are put into free space of earlier pages are not seen, and deletions of rows that were read aren't either.
    """

    def __init__(self, schema, options, storage):
        self.batch = HeapReader(schema, options | {"snapshot": "off"}, storage, None)

    def initialOffset(self):
        return {"pages": 0, "pointers": 0}

    def latestOffset(self):
        segments = [s for s in self.batch.segments() if s.pages]
        if not segments:
            return self.initialOffset()
        fs, at = plan.file_system(segments[-1].path)
        with fs.open_input_file(at) as f:
            f.seek((segments[-1].pages - 1) * heap.PAGE)
            last = np.frombuffer(f.read(heap.PAGE), np.uint8).reshape(1, -1)
        return {"pages": sum(s.pages for s in segments), "pointers": int(heap.pointer_counts(last)[0])}

    def partitions(self, start, end):
        segments = self.batch.segments()
        splits = plan.split_pages(segments, heap.PAGE, self.batch.split_bytes(segments))
        first = max(0, start["pages"] - 1)
        runs = plan.clip(splits, [(first, end["pages"] - first)], 1) if (start["pages"], start["pointers"]) != (end["pages"], end["pointers"]) else []
        out = []
        for r in runs:
            low = start["pointers"] if start["pages"] and r.base + r.first == first else 0
            high = end["pointers"] if r.base + r.first + r.count == end["pages"] else -1
            out.append(Part([replace(r, window=(low, high))]))
        return out or [Part([])]

    def read(self, partition):
        yield from self.batch.read(partition)


class PagedSource(DataSource):
    reader_class, pushing_class, writer_class = HeapReader, PushingHeapReader, HeapWriter
    headers = ("lower", "upper", "special", "pointers", "normal")

    def _storage(self) -> tuple[StorageSchema, dict | None]:
        found = None
        if self.options.get("path"):
            first = plan.expand(self.options["path"])[0]
            found = plan.manifest(first)
        key = tuple(k for k in self.options.get("pk", "").split(",") if k)
        if self.options.get("columns_spec"):
            return StorageSchema.parse(self.options["columns_spec"], key), found
        if found is None:
            raise ValueError("columns_spec is needed for files without a manifest")
        return StorageSchema.from_json(found["columns"]), found

    def schema(self):
        what = self.options.get("as", "rows")
        if what != "rows":  # page numbers are the relation's
            more = [("first_page", LongType()), ("content", BinaryType())] if what == "blocks" else [(n, LongType()) for n in ("page", *self.headers)]
            return StructType([StructField(n, t) for n, t in [("path", StringType()), *more]])
        storage, _ = self._storage()
        columns = [c.strip() for c in self.options["columns"].split(",")] if self.options.get("columns") else None
        out = storage.spark(columns, numeric_as=self.options.get("numeric_as", "double"), timestamp_as=self.options.get("timestamp_as", "ntz"))
        names = columns or storage.names
        if self.options.get("on_overflow") == "resolve" and self.reader_class is HeapReader:  # a tree's reader finds them itself
            long_ones = [n for n in names if storage[n].is_text or storage[n].kind in ("binary", "numeric")]
            out = StructType(out.fields + [StructField(f"__overflow_{n}", LongType()) for n in long_ones])
        if _flag(self.options, "with_page"):
            out = StructType(out.fields + [StructField("_page", LongType())])
        return out

    def reader(self, schema):
        storage, found = self._storage()
        return (self.pushing_class if _flag(self.options, "pushdown") else self.reader_class)(schema, self.options, storage, found)

    def writer(self, schema, overwrite):
        return self.writer_class(schema, self.options, overwrite)


class PageHeapSource(PagedSource):
    @classmethod
    def name(cls):
        return "pageheap"

    def streamReader(self, schema):
        storage, _ = self._storage()
        return HeapStream(schema, self.options, storage)


class PageCellSource(PagedSource):
    """Tables of SQLite 3 database files; read only."""

    @classmethod
    def name(cls):
        return "pagecell"

    def _storage(self):
        if not self.options.get("table"):
            raise ValueError("the option table names the table to read")
        if self.options.get("columns_spec"):
            return StorageSchema.parse(self.options["columns_spec"], tuple(k for k in self.options.get("pk", "").split(",") if k)), None
        first = plan.list_segments(plan.expand(self.options["path"])[0])[0].path
        return declared_schema(tables_of(first, file_layout(first))[self.options["table"]][1]), None

    def schema(self):
        storage, _ = self._storage()
        columns = [c.strip() for c in self.options["columns"].split(",")] if self.options.get("columns") else None
        return storage.spark(columns, numeric_as=self.options.get("numeric_as", "double"), timestamp_as=self.options.get("timestamp_as", "ntz"))

    def reader(self, schema):
        storage, _ = self._storage()
        first = plan.list_segments(plan.expand(self.options["path"])[0])[0].path
        return (PushingCellReader if _flag(self.options, "pushdown") else CellReader)(schema, self.options, storage, None, file_layout(first))

    def writer(self, schema, overwrite):
        raise NotImplementedError("database files are written by their own library")


class PageTreeSource(PagedSource):
    reader_class, pushing_class, writer_class = TreeReader, PushingTreeReader, TreeWriter
    headers = ("kind", "level", "index_id", "records")

    @classmethod
    def name(cls):
        return "pagetree"
