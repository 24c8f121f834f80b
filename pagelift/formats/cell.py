"""Table b-trees of SQLite 3 database files (big-endian): vectorised decoding of their leaf pages.

The format is public.  A table's rows are cells of leaf pages: payload length, row number and record, the two numbers and the
record's header as variable-length integers.  As in the other formats a cursor of every cell moves one column at a time.
Payloads that don't fit their page go on along a chain of overflow pages, which `fetch` follows.
"""

from __future__ import annotations

import datetime
import sqlite3
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

from pagelift.formats import codec
from pagelift.formats.heap import PageError
from pagelift.schema import StorageSchema

#: Fixed values of the file format.
MAGIC, FILE_HEADER = b"SQLite format 3\0", 100
LEAF, INTERIOR = 0x0D, 0x05
UTF8 = 1
#: Bytes of the serial types 0 to 9; types from 12 on are blobs (even) and texts (odd).
SIZES = np.array([0, 1, 2, 3, 4, 6, 8, 8, 0, 0, 0, 0], np.int64)
MASTER = StorageSchema.parse("type:text,name:text,tbl_name:text,rootpage:int8,sql:text")


@dataclass(frozen=True)
class Layout:
    """Bytes of a page, and how many of them the tree uses."""

    page: int
    usable: int


def layout(head: bytes) -> Layout:
    if len(head) < FILE_HEADER or head[:16] != MAGIC:
        raise PageError("not an SQLite 3 database file")
    if head[18] == 2 or head[19] == 2:
        raise PageError("the database is in write-ahead mode: its newest rows may lie in another file")
    if int.from_bytes(head[56:60], "big") not in (0, UTF8):
        raise PageError("texts aren't in UTF-8")
    size = int.from_bytes(head[16:18], "big")
    size = 65_536 if size == 1 else size
    return Layout(size, size - head[20])


def varint(flat: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values of big-endian groups of seven bits, the ninth byte a whole one; and the places after them."""
    value, size = np.zeros(len(at), np.int64), np.ones(len(at), np.int64)
    live = np.arange(len(at))
    for k in range(9):
        byte = flat[at[live] + k].astype(np.int64)
        value[live] = value[live] << 8 | byte if k == 8 else value[live] << 7 | byte & 0x7F
        size[live] = k + 1
        live = live[byte >= 0x80]
        if not len(live):
            break
    return value, at + size


def big_endian(flat: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
    """Signed whole numbers of a width."""
    raw = codec.take(flat, at, width)
    out = raw[:, 0].astype(np.int8).astype(np.int64)
    for k in range(1, width):
        out = out << 8 | raw[:, k]
    return out


def kinds(pages: np.ndarray, first: int) -> tuple[np.ndarray, np.ndarray]:
    """Kind of each page, and where its header begins: after the file's on the first page."""
    start = np.where(np.arange(len(pages)) + first == 0, FILE_HEADER, 0)
    return pages[np.arange(len(pages)), start], start


def children(page: np.ndarray, number: int) -> tuple[np.ndarray, np.ndarray]:
    """Page numbers that an interior page of a table points to, and the largest row number below all but the last."""
    at = FILE_HEADER if number == 1 else 0
    count = int.from_bytes(page[at + 3 : at + 5].tobytes(), "big")
    pointers = np.ascontiguousarray(page[at + 12 : at + 12 + 2 * count]).view(">u2").astype(np.int64)
    left = np.ascontiguousarray(codec.take(page, pointers, 4)).view(">u4").ravel() if count else np.zeros(0, np.uint32)
    keys, _ = varint(np.concatenate([page, np.zeros(16, np.uint8)]), pointers + 4)
    return np.append(left, int.from_bytes(page[at + 8 : at + 12].tobytes(), "big")).astype(np.int64), keys


def leaves(read: Callable[[int, int], np.ndarray], root: int, low: int | None = None, high: int | None = None) -> np.ndarray:
    """Numbers (from 1) of the leaf pages of the tree with the given root, in the file's order; read gives pages by first
    number and count.  Only interior pages are read, about one page in some hundreds, and of these only those that lead to
    row numbers from low to high."""
    found, level = [], [root]
    while level:
        below = []
        for number in level:
            page = read(number, 1)[0]
            kind = page[FILE_HEADER if number == 1 else 0]
            if kind == LEAF:
                found.append(number)
                continue
            if kind != INTERIOR:
                raise PageError(f"page {number} is no page of a table")
            nodes, keys = children(page, number)
            on = np.ones(len(nodes), bool)
            if low is not None:
                on[:-1] &= keys >= low
            if high is not None:
                on[1:] &= keys < high
            if not on.any():
                continue
            nodes = nodes[on].tolist()
            if read(nodes[0], 1)[0][0] == LEAF:  # all pages of a level are of one kind
                found += nodes
            else:
                below += nodes
        level = below
    return np.sort(np.array(found, np.int64))


def cells(pages: np.ndarray, first: int) -> np.ndarray:
    """Where the cells of leaf pages begin, in the flat bytes."""
    size = pages.shape[1]
    kind, start = kinds(pages, first)
    if (kind != LEAF).any():
        raise PageError("a page isn't a leaf of a table")
    base = np.arange(len(pages)) * size
    flat = pages.reshape(-1)
    count = (flat[base + start + 3].astype(np.int64) << 8) | flat[base + start + 4]
    page = np.repeat(np.arange(len(pages)), count)
    slot = np.arange(len(page)) - np.repeat(np.cumsum(count) - count, count)
    at = page * size + start[page] + 8 + 2 * slot
    return page * size + ((flat[at].astype(np.int64) << 8) | flat[at + 1])


def decode(pages: np.ndarray, lay: Layout, schema: StorageSchema, columns: list[str] | None = None, first: int = 1, fetch: Callable[[int, int], bytes] | None = None, numeric_as: str = "double", timestamp_as: str = "ntz", row_number: str | None = None) -> pa.RecordBatch:
    """The rows of some leaf pages.  first: number of the first page, from 0; fetch gives what a chain holds, by first page and
    length; row_number: the column that is the row number itself.  Dates are days and timestamps microseconds since 1970."""
    at = cells(pages, first)
    flat = np.concatenate([pages.reshape(-1), np.zeros(16, np.uint8)])
    size, at = varint(flat, at)
    number, at = varint(flat, at)
    most = lay.usable - 35
    if (size > most).any():
        flat, at = _whole(flat, at, size, lay, most, fetch)
    head, cursor = varint(flat, at)
    body, end, n = at + head, at + head, len(at)
    wanted = list(columns if columns is not None else schema.names)
    last = max((i for i, c in enumerate(schema.columns) if c.name in wanted), default=-1)
    out = {}
    for c in schema.columns[: last + 1]:
        there = cursor < end  # columns that were added later are missing in older rows
        kind, after = varint(flat, np.where(there, cursor, 0))
        kind = np.where(there, kind, 0)
        cursor = np.where(there, after, cursor)
        length = np.where(kind >= 12, (kind - 12) >> 1, SIZES[np.minimum(kind, 11)])
        if c.name == row_number:
            out[c.name] = codec.fixed_array(c.arrow_type(), number.astype(c.arrow_type().to_pandas_dtype()), np.ones(n, bool))
        elif c.name in wanted:
            out[c.name] = _column(c, flat, body, kind, length, numeric_as, timestamp_as)
        body = body + length
    if not wanted:
        return pa.RecordBatch.from_struct_array(pa.array([{}] * n, pa.struct([])))
    return pa.RecordBatch.from_arrays([out[c] for c in wanted], names=wanted)


def _whole(flat: np.ndarray, at: np.ndarray, size: np.ndarray, lay: Layout, most: int, fetch):
    """Payloads that go on elsewhere, put together behind the pages' bytes."""
    long_ = np.flatnonzero(size > most)
    if fetch is None:
        raise PageError("a row goes on along overflow pages; read it with on_overflow resolve")
    least = (lay.usable - 12) * 32 // 255 - 23
    here = least + (size[long_] - least) % (lay.usable - 4)
    here = np.where(here <= most, here, least)
    extra, at, end = [], at.copy(), len(flat)
    for i, k in zip(long_.tolist(), here.tolist()):
        start = int(at[i])
        page = int.from_bytes(flat[start + k : start + k + 4].tobytes(), "big")
        extra.append(flat[start : start + k].tobytes() + fetch(page, int(size[i]) - k))
        at[i], end = end, end + len(extra[-1])
    return np.concatenate([flat, np.frombuffer(b"".join(extra), np.uint8), np.zeros(16, np.uint8)]), at


def chained(read: Callable[[int, int], np.ndarray], lay: Layout, first: int, length: int) -> bytes:
    """What a chain of overflow pages holds.  Pages that lie in a row are read at once."""
    per, out, page = lay.usable - 4, [], first
    while length > 0:
        if not page:
            raise PageError("an overflow chain ends before its payload")
        for raw in read(page, -(-length // per)):
            out.append(raw[4 : 4 + min(per, length)].tobytes())
            length -= per
            following = int.from_bytes(raw[:4].tobytes(), "big")
            page, went_on = following, following == page + 1
            if not went_on:
                break
    return b"".join(out)


def _column(c, flat: np.ndarray, at: np.ndarray, kind: np.ndarray, length: np.ndarray, numeric_as: str, timestamp_as: str) -> pa.Array:
    arrow, there = c.arrow_type(numeric_as, timestamp_as), kind > 0
    if c.is_text or c.kind == "binary":
        if (there & (kind < 12)).any():
            raise PageError(f"column {c.name} holds numbers, not {c.kind}")
        return codec.span_array(arrow, flat, at, length, there)
    if (kind >= 12).any():
        raise PageError(f"column {c.name} holds texts or blobs, not {c.kind}")
    real = c.kind in ("float4", "float8", "numeric")
    values = np.zeros(len(at), np.float64 if real else np.int64)
    for code in np.unique(kind[there]).tolist():
        rows = np.flatnonzero(kind == code)
        if code == 7:
            if not real:
                raise PageError(f"column {c.name} holds floating-point numbers, not {c.kind}")
            values[rows] = np.ascontiguousarray(codec.take(flat, at[rows], 8)).view(">f8").ravel()
        else:
            values[rows] = code - 8 if code in (8, 9) else big_endian(flat, at[rows], int(SIZES[code]))
    if c.kind == "numeric" and numeric_as == "decimal":
        return codec.decimal_array(np.rint(values * 10.0**c.scale).astype(np.int64), c.precision, c.scale, there)
    if c.kind == "bool":
        values = values != 0
    return codec.fixed_array(arrow, values if c.kind in ("bool", "numeric") else values.astype({"int2": np.int16, "int4": np.int32, "date": np.int32, "float4": np.float32}.get(c.kind, values.dtype)), there)


# -- writing, by the database's own library ------------------------------------------------------------------------

DECLARED = {"bool": "BOOLEAN", "int2": "INTEGER", "int4": "INTEGER", "int8": "INTEGER", "float4": "REAL", "float8": "REAL", "numeric": "REAL", "date": "DATE", "timestamp": "TIMESTAMP", "binary": "BLOB"}
EPOCH = datetime.datetime(1970, 1, 1)


def stored(v):
    """A value as the library takes it: days and microseconds for dates and timestamps."""
    if isinstance(v, datetime.datetime):
        return int((v - EPOCH) / datetime.timedelta(microseconds=1))
    return (v - EPOCH.date()).days if isinstance(v, datetime.date) else v


def database(batches, schema: StorageSchema, table: str, key: str | None = None, page_size: int = 4096, beside: int = 500) -> bytes | None:
    """A database file with the rows in a table, whose pages alternate with those of another; None without rows."""
    db, some = sqlite3.connect(":memory:"), False
    db.execute(f"PRAGMA page_size = {page_size}")
    db.execute("CREATE TABLE beside_it (a INTEGER, b TEXT)")
    db.executemany("INSERT INTO beside_it VALUES (?, ?)", [(i, "x" * 50) for i in range(beside)])
    columns = ", ".join(f"{c.name} {DECLARED.get(c.kind, 'TEXT')}{' PRIMARY KEY' if c.name == key else ''}" for c in schema.columns)
    db.execute(f"CREATE TABLE {table} ({columns})")
    for b in batches:
        rows = [tuple(map(stored, r.values())) for r in b.to_pylist()]
        db.executemany(f"INSERT INTO {table} VALUES ({', '.join('?' * len(schema.columns))})", rows)
        db.executemany("INSERT INTO beside_it VALUES (?, ?)", [(i, "between") for i in range(len(rows) // 10)])
        some = some or bool(rows)
    db.commit()
    return db.serialize() if some else None


def leaf_bytes(data: bytes, table: str) -> bytes:
    """The leaf pages of a table of a database file that is held in memory."""
    lay = layout(data[:FILE_HEADER])
    pages = np.frombuffer(data, np.uint8).reshape(-1, lay.page)
    read = lambda number, count: pages[number - 1 : number - 1 + count]
    master = [r for n in leaves(read, 1) for r in decode(read(int(n), 1), lay, MASTER, first=int(n) - 1).to_pylist()]
    root = next(r["rootpage"] for r in master if r["name"] == table)
    return pages[leaves(read, root) - 1].tobytes()
