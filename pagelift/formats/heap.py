"""Slotted heap pages (8 KB, little-endian): vectorised decoding and encoding.

A block of pages is one flat byte vector.  Decoding keeps a cursor for every visible tuple and moves all of them one
column at a time; columns that aren't wanted are walked over, and the walk ends at the last wanted one.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from pagelift.formats import codec
from pagelift.schema import FIXED, StorageSchema

PAGE = 8192
HEADER = 24
TUPLE_HEADER = 23
#: Tuple flags and line-pointer states.
HAS_NULL, LOCK_ONLY, INSERT_INVALID, DELETE_INVALID = 0x0001, 0x0080, 0x0200, 0x0800
UNUSED, NORMAL, REDIRECT, DEAD = 0, 1, 2, 3
#: What the special column __state of a writer's input means.
STATES = {"live": 0, "deleted": 1, "lock_only": 2, "rolled_back_delete": 3, "aborted_insert": 4}
POLICIES = ("delete_only", "insert_hint", "none")
EXTERNAL = 18  # bytes of a pointer to an overflow value


class PageError(ValueError):
    """Bytes that aren't what the format promises."""


@dataclass(frozen=True)
class Segment:
    path: str
    size: int
    changed: int = 0  # modification time in nanoseconds, where it is known

    @property
    def pages(self) -> int:
        return self.size // PAGE


def segment_order(path: str) -> tuple[str, int]:
    """A relation's base file and the number of its suffix; the base file itself is number 0."""
    m = re.fullmatch(r"(.*)\.(\d+)", path)
    return (m[1], int(m[2])) if m else (path, 0)


def page_headers(pages: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Lower, upper and special offsets of pages (n x PAGE bytes)."""
    words = np.ascontiguousarray(pages[:, 12:18]).view("<u2").astype(np.int64)
    return words[:, 0], words[:, 1], words[:, 2]


def line_pointers(pages: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Page, offset, state and length of every line pointer."""
    lower, upper, special = page_headers(pages)
    if ((lower != 0) & ((lower < HEADER) | (lower > upper) | (upper > special) | (special > PAGE))).any():
        raise PageError("a page header isn't a heap page's: lower, upper and special are out of order")
    count = np.where(lower == 0, 0, (lower - HEADER) >> 2)  # a zero page is empty
    page = np.repeat(np.arange(len(pages)), count)
    slot = np.arange(len(page)) - np.repeat(np.cumsum(count) - count, count)
    at = page * PAGE + HEADER + 4 * slot
    word = codec.take(pages.reshape(-1), at, 4)
    word = np.ascontiguousarray(word).view("<u4").ravel().astype(np.int64)
    return page, word & 0x7FFF, (word >> 15) & 3, word >> 17


def visible(xmax: np.ndarray, mask: np.ndarray, policy: str = "delete_only") -> np.ndarray:
    """Live tuples by their header alone: no deleter, or one that was rolled back or only locked."""
    if policy not in POLICIES:
        raise ValueError(f"visibility is one of {', '.join(POLICIES)}, not {policy!r}")
    if policy == "none":
        return np.ones(len(xmax), bool)
    live = (xmax == 0) | ((mask & DELETE_INVALID) != 0) | ((mask & LOCK_ONLY) != 0)
    return live & ((mask & INSERT_INVALID) == 0) if policy == "insert_hint" else live


@dataclass
class Tuples:
    flat: np.ndarray
    start: np.ndarray
    page: np.ndarray
    mask: np.ndarray
    attributes: np.ndarray
    data: np.ndarray  # where the attributes begin


def pointer_counts(pages: np.ndarray) -> np.ndarray:
    """Line pointers of each page."""
    lower = page_headers(pages)[0]
    return np.where(lower == 0, 0, (lower - HEADER) >> 2)


def tuples(pages: np.ndarray, policy: str = "delete_only", window: tuple[int, int] | None = None) -> Tuples:
    """window: the first slot of the first page that counts, and the end of the last page's (-1: all)."""
    page, offset, state, length = line_pointers(pages)
    kept = (state == NORMAL) & (length > 0)
    if window is not None:
        slot = np.arange(len(page)) - np.searchsorted(page, page)
        kept &= (page > 0) | (slot >= window[0])
        if window[1] >= 0:
            kept &= (page < len(pages) - 1) | (slot < window[1])
    page, start = page[kept], page[kept] * PAGE + offset[kept]
    if (offset[kept] + length[kept] > PAGE).any():
        raise PageError("a line pointer leads out of its page")
    flat = pages.reshape(-1)
    head = codec.take(flat, start, TUPLE_HEADER)
    word = lambda at, kind: np.ascontiguousarray(head[:, at : at + int(kind[-1])]).view(kind).ravel().astype(np.int64)
    mask = word(20, "<u2")
    seen = visible(word(4, "<u4"), mask, policy)
    return Tuples(flat, start[seen], page[seen], mask[seen], word(18, "<u2")[seen] & 0x7FF, (start + head[:, 22])[seen])


def validity(t: Tuples, column: int) -> np.ndarray:
    """Attributes that are there: not marked null, and not past the tuple's attribute count."""
    there = t.attributes > column
    marked = np.flatnonzero((t.mask & HAS_NULL) != 0)
    if len(marked):
        byte = t.flat[t.start[marked] + TUPLE_HEADER + (column >> 3)]
        there[marked] &= ((byte >> (column & 7)) & 1).astype(bool)
    return there


def varlena_span(flat: np.ndarray, at: np.ndarray):
    """Payload start and length, size of the datum from `at`, and whether it is an overflow pointer."""
    last = len(flat) - 1
    byte = lambda p: flat[np.minimum(p, last)].astype(np.int64)
    at = np.where(byte(at) == 0, (at + 3) & -4, at)  # a zero byte is padding before a long header
    first = byte(at)
    short, external = (first & 1) == 1, first == 1
    word = first | (byte(at + 1) << 8) | (byte(at + 2) << 16) | (byte(at + 3) << 24)
    if (~short & ((first & 3) == 2)).any():
        raise PageError("compressed values aren't supported")
    total = np.where(external, EXTERNAL, np.where(short, first >> 1, word >> 2))
    head = np.where(external, 2, np.where(short, 1, 4))
    return at + head, total - head, at + total, external


def decode(pages: np.ndarray, schema: StorageSchema, columns: list[str] | None = None, policy: str = "delete_only", numeric_as: str = "double", timestamp_as: str = "ntz", on_overflow: str = "error", page_base: int | None = None, window: tuple[int, int] | None = None) -> pa.RecordBatch:
    """The visible tuples of some pages as a record batch.  page_base: give each row its page number in `_page`, too."""
    t = tuples(pages, policy, window)
    wanted = set(columns if columns is not None else schema.names)
    last = max((i for i, c in enumerate(schema.columns) if c.name in wanted), default=-1)
    n, cursor, out = len(t.start), t.data, {}
    for i, c in enumerate(schema.columns[: last + 1]):
        there = validity(t, i)
        every = bool(there.all())
        rows = slice(None) if every else np.flatnonzero(there)
        kind = c.arrow_type(numeric_as, timestamp_as)
        spread = (lambda v: v) if every else (lambda v, rows=rows: _spread(v, rows, n))
        if c.kind in FIXED:
            width = FIXED[c.kind]
            at = (cursor[rows] + (width - 1)) & -width
            if c.name in wanted:
                out[c.name] = codec.fixed_array(kind, spread(codec.heap_fixed(c.kind, codec.take(t.flat, at, width))), there)
            end = at + width
        else:
            start, length, end, external = varlena_span(t.flat, cursor[rows])
            if external.any():
                if on_overflow == "error" and c.name in wanted:
                    raise PageError(f"column {c.name} has overflow values; read it with on_overflow null or resolve")
                if on_overflow == "resolve" and c.name in wanted:
                    ids = np.ascontiguousarray(codec.take(t.flat, start + 8, 8)).view("<i8").ravel()
                    there_id = np.zeros(n, bool)
                    there_id[rows] = external
                    out[f"__overflow_{c.name}"] = codec.fixed_array(pa.int64(), spread(np.where(external, ids, 0)), there_id)
                ok = np.zeros(n, bool)
                ok[rows] = ~external
                valid, length = ok, np.where(external, 0, length)
            else:
                valid = there
            if c.name in wanted:
                out[c.name] = _variable(c, kind, t.flat, spread(start), spread(length), valid, numeric_as)
        if every:
            cursor = end
        else:
            cursor = cursor.copy()
            cursor[rows] = end
    names = [c for c in (columns if columns is not None else schema.names)]
    arrays = [out[c] for c in names]
    if on_overflow == "resolve":
        for c in names[:]:
            if schema[c].kind not in FIXED:
                names.append(f"__overflow_{c}")
                arrays.append(out.get(f"__overflow_{c}", pa.nulls(n, pa.int64())))
    if page_base is not None:
        names.append("_page")
        arrays.append(pa.array(t.page + page_base, pa.int64()))
    if not arrays:  # a count needs rows, not columns
        return pa.RecordBatch.from_struct_array(pa.array([{}] * n, pa.struct([])))
    return pa.RecordBatch.from_arrays(arrays, names=names)


def _spread(values: np.ndarray, rows: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros((n, *values.shape[1:]), values.dtype)
    out[rows] = values
    return out


def _variable(c, kind, flat, start, length, valid, numeric_as):
    if c.kind == "numeric":
        if numeric_as == "decimal":
            return codec.numeric_decimal(flat, start, length, c.precision, c.scale, valid)
        return codec.fixed_array(kind, codec.numeric_double(flat, start, np.where(valid, length, 2)), valid)
    if c.kind == "bpchar":
        length = codec.rstrip_spans(flat, start, np.where(valid, length, 0))
    return codec.span_array(kind, flat, start, length, valid)


# -- encoding ------------------------------------------------------------------------------------------------------


@dataclass
class Encoded:
    """A column's datums: `size` bytes each; fixed rows of bytes, or spans with a header to be put before them."""

    there: np.ndarray
    fixed: np.ndarray | None = None
    flat: np.ndarray | None = None
    starts: np.ndarray | None = None
    lengths: np.ndarray | None = None
    align: int = 1


def _encode_column(c, column: pa.Array, long_numeric: bool) -> Encoded:
    there = np.asarray(column.is_valid())
    if c.kind in FIXED:
        return Encoded(there, fixed=codec.heap_fixed_bytes(c.kind, codec.column_values(column, c.kind)), align=FIXED[c.kind])
    if c.kind == "numeric":
        special = None
        if pa.types.is_floating(column.type):
            v = column.fill_null(0.0).to_numpy(zero_copy_only=False)
            special = np.where(np.isnan(v), 0xC000, np.where(v == np.inf, 0xD000, np.where(v == -np.inf, 0xF000, 0)))
        lengths, rows = codec.numeric_bytes(codec.in_precision(codec.scaled_ints(column, c.scale), c.precision, c.name), c.scale, long_numeric, special)
        return Encoded(there, flat=rows.ravel(), starts=np.arange(len(rows)) * rows.shape[1], lengths=lengths)
    if c.kind == "bpchar" and c.max_len:
        column = pc.utf8_rpad(column.cast(pa.string()), c.max_len, " ")
    flat, starts, lengths = codec.text_spans(column)
    return Encoded(there, flat=flat, starts=starts, lengths=lengths)


def encode(batch: pa.RecordBatch, schema: StorageSchema, fill_factor: int = 100, long_numeric: bool = False, dead_pointers: int = 0, overflow: dict[str, np.ndarray] | None = None) -> np.ndarray:
    """Pages (n x PAGE bytes) that hold the batch's rows in order.

    A column `__state` marks rows deleted, locked, and so on (STATES).  overflow: for a column, the value id of each
    row whose value is kept elsewhere, or 0.
    """
    n = batch.num_rows
    if not n:
        return np.zeros((0, PAGE), np.uint8)
    cols = [_encode_column(c, batch.column(c.name), long_numeric) for c in schema.columns]
    there = np.column_stack([c.there for c in cols])
    has_null = ~there.all(axis=1)
    bitmap = (len(cols) + 7) // 8
    hoff = np.where(has_null, (TUPLE_HEADER + bitmap + 7) & -8, (TUPLE_HEADER + 7) & -8)
    cursor, places = hoff.astype(np.int64), []
    for c, s in zip(cols, schema.columns):
        if c.fixed is not None:
            at = (cursor + (c.align - 1)) & -c.align
            end = at + c.fixed.shape[1]
        else:
            ids = overflow.get(s.name) if overflow else None
            out = (ids > 0) if ids is not None else np.zeros(n, bool)
            short = c.lengths + 1 <= 127
            at = np.where(short | out, cursor, (cursor + 3) & -4)
            end = at + np.where(out, EXTERNAL, np.where(short, c.lengths + 1, c.lengths + 4))
        places.append(at)
        cursor = np.where(c.there, end, cursor)
    size, room = (cursor + 7) & -8, PAGE - HEADER - 4 * dead_pointers
    if (size + 4 > room).any():
        raise PageError("a row is larger than a page; keep long values as overflow")
    total = np.cumsum(size + 4)
    limit, starts = max(int(room * fill_factor / 100), 1), [0]
    while starts[-1] < n:  # over pages
        done = total[starts[-1] - 1] if starts[-1] else 0
        starts.append(max(int(np.searchsorted(total, done + limit, side="right")), starts[-1] + 1))
    starts = np.array(starts)
    starts[-1] = n
    count = np.diff(starts)
    page = np.repeat(np.arange(len(count)), count)
    slot = np.arange(n) - starts[page]
    used = np.cumsum(size)
    offset = PAGE - (used - np.where(starts[page] > 0, used[starts[page] - 1], 0))
    out = np.zeros(len(count) * PAGE, np.uint8)
    base = page * PAGE + offset
    for c, s, at in zip(cols, schema.columns, places):
        rows = np.flatnonzero(c.there)
        if c.fixed is not None:
            codec.put(out, base[rows] + at[rows], c.fixed[rows])
            continue
        if overflow and s.name in overflow:
            away = rows[overflow[s.name][rows] > 0]
            rows = rows[overflow[s.name][rows] == 0]
            raw = np.zeros((len(away), EXTERNAL), np.uint8)
            raw[:, 0], raw[:, 1] = 1, 18
            ids = overflow[s.name][away]
            words = np.column_stack([c.lengths[away] + 4, c.lengths[away], ids & 0xFFFFFFFF, ids >> 32])
            raw[:, 2:] = words.astype("<u4").view(np.uint8).reshape(len(away), 16)
            codec.put(out, base[away] + at[away], raw)
        where, length = base[rows] + at[rows], c.lengths[rows]
        short = length + 1 <= 127
        out[where[short]] = ((length[short] + 1) << 1) | 1
        word = ((length[~short] + 4) << 2).astype("<u4").view(np.uint8).reshape(-1, 4)
        codec.put(out, where[~short], word)
        offsets, source = codec.span_index(c.starts[rows], length)
        target = np.repeat(where + np.where(short, 1, 4) - offsets[:-1], length) + np.arange(offsets[-1])
        out[target] = c.flat[source]
    state = np.asarray(batch.column("__state")).astype(np.int64) if "__state" in batch.schema.names else np.zeros(n, np.int64)
    mask = np.where(has_null, HAS_NULL, 0) | np.where(state == 2, LOCK_ONLY, 0) | np.where(state == 3, DELETE_INVALID, 0) | np.where(state == 4, INSERT_INVALID, 0)
    mask |= np.where(state == 0, DELETE_INVALID, 0)
    head = np.zeros((n, TUPLE_HEADER), np.uint8)
    word = lambda v, kind: np.ascontiguousarray(np.asarray(v).astype(kind)).view(np.uint8).reshape(n, -1)
    head[:, 0:4], head[:, 4:8] = word(np.full(n, 700), "<u4"), word(np.where((state > 0) & (state < 4), 701, 0), "<u4")
    head[:, 18:20], head[:, 20:22], head[:, 22] = word(np.full(n, len(cols)), "<u2"), word(mask, "<u2"), hoff
    codec.put(out, base, head)
    if has_null.any():
        rows = np.flatnonzero(has_null)
        codec.put(out, base[rows] + TUPLE_HEADER, np.packbits(there[rows], axis=1, bitorder="little"))
    pointer = (offset | (NORMAL << 15) | (cursor << 17)).astype("<u4").view(np.uint8).reshape(n, 4)
    codec.put(out, page * PAGE + HEADER + 4 * (slot + dead_pointers), pointer)
    pages = out.reshape(-1, PAGE)
    for k in range(dead_pointers):
        word = np.array([(0 | ([UNUSED, REDIRECT, DEAD][k % 3] << 15))], "<u4").view(np.uint8)
        pages[:, HEADER + 4 * k : HEADER + 4 * k + 4] = word
    lower = HEADER + 4 * (count + dead_pointers)
    upper = offset[starts[1:] - 1]
    pages[:, 12:18] = np.column_stack([lower, upper, np.full(len(count), PAGE)]).astype("<u2").view(np.uint8).reshape(-1, 6)
    pages[:, 18:20] = np.array([PAGE | 4], "<u2").view(np.uint8)
    return pages
