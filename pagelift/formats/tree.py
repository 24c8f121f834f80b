"""B-tree tablespace pages (16 KB, big-endian): vectorised decoding of leaf pages, and encoding.

Records of a page form a linked list, so all pages of a block are walked in lock step: one hop moves the cursor of every
page.  After that the records of all pages are decoded together, one column at a time.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from pagelift.formats import codec
from pagelift.formats.heap import PageError
from pagelift.schema import StorageSchema

PAGE = 16_384
#: Fixed values of the page format.
INDEX_PAGE, SPACE_HEADER, ALLOCATION, INODE, LONG_VALUE = 0x45BF, 8, 5, 3, 10
FIRST, LAST, DATA = 99, 112, 120
DELETED = 0x20
ROOT = 3  # page of the clustered index's root
TRAILER = 8
PAGE_HEADER = 38
POINTER = 20  # space, page, offset in it, and length of a value that is kept on pages of its own
PART = PAGE - PAGE_HEADER - 8 - TRAILER  # bytes of a value on a page
NO_PAGE = 0xFFFFFFFF
WIDTHS = {"bool": 1, "int2": 2, "int4": 4, "int8": 8, "float4": 4, "float8": 8, "date": 3, "timestamp": 8}


def _u16(pages: np.ndarray, at: int) -> np.ndarray:
    return (pages[:, at].astype(np.int64) << 8) | pages[:, at + 1]


def index_ids(pages: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(pages[:, 66:74]).view(">u8").ravel().astype(np.int64)


def index_pages(pages: np.ndarray) -> np.ndarray:
    return _u16(pages, 24) == INDEX_PAGE


def leaf_pages(pages: np.ndarray) -> np.ndarray:
    return _u16(pages, 64) == 0


def compact(pages: np.ndarray) -> np.ndarray:
    return (pages[:, 42] & 0x80) != 0


def clustered_leaves(pages: np.ndarray, index_id: int | None) -> np.ndarray:
    """Positions of the leaf pages of one index; a row format that isn't the compact one is refused."""
    mask = index_pages(pages) & leaf_pages(pages)
    if index_id is not None:
        mask &= index_ids(pages) == index_id
    if (mask & ~compact(pages)).any():
        raise PageError("a leaf page isn't in the compact row format")
    return np.flatnonzero(mask)


def discover_index(first_pages: np.ndarray) -> int | None:
    """Id of the clustered index: the root page's, else the lowest that is seen."""
    if len(first_pages) > ROOT and _u16(first_pages[ROOT : ROOT + 1], 24)[0] == INDEX_PAGE:
        return int(index_ids(first_pages[ROOT : ROOT + 1])[0])
    mask = index_pages(first_pages)
    return int(index_ids(first_pages[mask]).min()) if mask.any() else None


def record_origins(pages: np.ndarray, leaves: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Page and origin of all records, in key order within each page."""
    flat = pages.reshape(-1)
    page, at = leaves.astype(np.int64), np.full(len(leaves), FIRST, np.int64)
    limit = (_u16(pages, 42) & 0x7FFF)[leaves].max(initial=0) + 2
    found_page, found_at, hop, hops = [], [], [], 0
    while len(page):
        if hops > limit:
            raise PageError("a page's record list doesn't end")
        where = page * PAGE + at
        step = (flat[where - 2].astype(np.int64) << 8) | flat[where - 1]
        at = (at + step) & 0xFFFF  # a signed step of 16 bits
        on = (step != 0) & (at != LAST)
        page, at = page[on], at[on]
        if ((at < DATA) | (at >= PAGE - TRAILER)).any():
            raise PageError("a record lies outside its page")
        found_page.append(page)
        found_at.append(at)
        hop.append(np.full(len(page), hops))
        hops += 1
    if not found_page:
        return page, at
    page, at, hop = (np.concatenate(x) for x in (found_page, found_at, hop))
    by = np.lexsort((hop, page))
    return page[by], at[by]


def live(flat: np.ndarray, origin: np.ndarray) -> np.ndarray:
    """Ordinary records that aren't marked deleted."""
    return ((flat[origin - 5] & DELETED) == 0) & ((flat[origin - 3] & 7) == 0)


def key_bounds(pages: np.ndarray, leaves: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Smallest and largest key (a leading whole number of the given width) of each leaf page."""
    page, at = record_origins(pages, leaves)
    flat = pages.reshape(-1)
    key = codec.tree_int(codec.take(flat, page * PAGE + at, width)).astype(np.int64)
    first = np.searchsorted(page, leaves, side="left")
    last = np.searchsorted(page, leaves, side="right") - 1
    empty = last < first
    none = np.iinfo(np.int64)
    if not len(key):
        return np.full(len(leaves), none.max), np.full(len(leaves), none.min)
    return np.where(empty, none.max, key[np.minimum(first, len(key) - 1)]), np.where(empty, none.min, key[np.maximum(last, 0)])


def decode(pages: np.ndarray, schema: StorageSchema, columns: list[str] | None = None, index_id: int | None = None, numeric_as: str = "double", timestamp_as: str = "ntz", float_codec: str = "ordered", prefix: str = "declared", key_range: tuple[int | None, int | None] | None = None, on_overflow: str = "error", page_base: int | None = None, fetch: Callable[[int, int], bytes] | None = None) -> pa.RecordBatch:
    """Live records of the clustered index's leaf pages.  key_range skips pages by the bounds of their leading key; fetch
    gives the bytes of a value on pages of its own, by first page and length."""
    leaves = clustered_leaves(pages, index_id)
    order = schema.physical()
    if key_range is not None and order[0].kind in ("int2", "int4", "int8") and len(leaves):
        low, high = key_bounds(pages, leaves, WIDTHS[order[0].kind])
        on = np.ones(len(leaves), bool)
        if key_range[0] is not None:
            on &= high >= key_range[0]
        if key_range[1] is not None:
            on &= low <= key_range[1]
        leaves = leaves[on]
    page, at = record_origins(pages, leaves)
    flat = pages.reshape(-1)
    origin = page * PAGE + at
    kept = live(flat, origin)
    page, origin = page[kept], origin[kept]
    n = len(origin)
    wanted = list(columns if columns is not None else schema.names)
    last = max((i for i, c in enumerate(order) if c.name in wanted), default=-1)
    nullable = [c for c in order if c.nullable]
    lengths_at = origin - 6 - (len(nullable) + 7) // 8
    out, cursor, null_no = {}, origin.copy(), 0
    for c in order[: last + 1]:
        there = np.ones(n, bool)
        if c.nullable:
            there = ((flat[origin - 6 - (null_no >> 3)] >> (null_no & 7)) & 1) == 0
            null_no += 1
        if c.kind == "skip":
            cursor = cursor + c.width
            continue
        kind = c.arrow_type(numeric_as, timestamp_as)
        if c.kind in WIDTHS or c.kind == "numeric":
            width = WIDTHS.get(c.kind) or codec.decimal_width(c.precision, c.scale)
            if c.name in wanted:
                raw = codec.take(flat, np.minimum(cursor, len(flat) - width), width)
                out[c.name] = _fixed(c, kind, raw, there, numeric_as, float_codec)
            cursor = cursor + np.where(there, width, 0)
            continue
        first, second = flat[lengths_at].astype(np.int64), flat[lengths_at - 1].astype(np.int64)
        if 0 < c.max_len <= 255:
            length, used = first, 1
        elif prefix == "adaptive":
            wide = (first & 0x80) != 0
            length, used = np.where(wide, ((first & 0x3F) << 8) | second, first), np.where(wide, 2, 1)
        else:
            length, used = ((first & 0x3F) << 8) | second, 2
        length = np.where(there, length, 0)
        away = there & ((first & 0x40) != 0) if not 0 < c.max_len <= 255 else np.zeros(n, bool)
        if prefix == "adaptive":
            away &= (first & 0x80) != 0
        lengths_at = lengths_at - np.where(there, used, 0)
        if c.name in wanted:
            valid = there
            if away.any():
                if on_overflow == "error":
                    raise PageError(f"column {c.name} has overflow values; read it with on_overflow null or resolve")
                valid = there & ~away
            text = np.where(valid, length, 0)
            out[c.name] = codec.span_array(kind, flat, cursor, codec.rstrip_spans(flat, cursor, text) if c.kind == "bpchar" else text, valid)
            if away.any() and on_overflow == "resolve":
                at = (cursor + length - POINTER)[away]
                first, size = (np.ascontiguousarray(codec.take(flat, at + k, w)).view(f">u{w}").ravel().tolist() for k, w in ((4, 4), (12, 8)))
                out[c.name] = pc.replace_with_mask(out[c.name], pa.array(away), pa.array([fetch(p, n) for p, n in zip(first, size)], pa.binary()).cast(kind))
        cursor = cursor + length
    names, arrays = list(wanted), [out[c] for c in wanted]
    if page_base is not None:
        names.append("_page")
        arrays.append(pa.array(page + page_base, pa.int64()))
    if not arrays:
        return pa.RecordBatch.from_struct_array(pa.array([{}] * n, pa.struct([])))
    return pa.RecordBatch.from_arrays(arrays, names=names)


def _fixed(c, kind, raw, there, numeric_as, float_codec):
    if c.kind == "numeric":
        if numeric_as == "decimal":
            return codec.packed_decimal(raw, c.precision, c.scale, there)
        return codec.fixed_array(kind, codec.packed_double(raw, c.precision, c.scale), there)
    if c.kind in ("float4", "float8"):
        return codec.fixed_array(kind, codec.tree_float(raw, float_codec), there)
    if c.kind == "date":
        return codec.fixed_array(kind, codec.packed_date(raw), there)
    values = codec.tree_int(raw)
    return codec.fixed_array(kind, values != 0 if c.kind == "bool" else values, there)


# -- encoding ------------------------------------------------------------------------------------------------------


@dataclass
class _Column:
    there: np.ndarray
    fixed: np.ndarray | None = None
    flat: np.ndarray | None = None
    starts: np.ndarray | None = None
    lengths: np.ndarray | None = None
    away: np.ndarray | None = None  # kept on overflow pages: the row holds a pointer


def _column(c, batch: pa.RecordBatch, float_codec: str, hidden: int, overflow) -> _Column:
    n = batch.num_rows
    if c.kind == "skip":
        raw = np.zeros((n, c.width), np.uint8)
        raw[:, : min(6, c.width)] = np.ascontiguousarray((hidden + np.arange(n)).astype(">u8")).view(np.uint8).reshape(n, 8)[:, 2 : 2 + min(6, c.width)]
        return _Column(np.ones(n, bool), fixed=raw)
    column = batch.column(c.name)
    there = np.asarray(column.is_valid())
    if c.kind == "numeric":
        if pa.types.is_floating(column.type) and not pc.all(pc.is_finite(column.drop_null())).as_py() and len(column.drop_null()):
            raise PageError(f"{c.name} holds NaN or an infinity, which the tree's exact numbers don't have")
        return _Column(there, fixed=codec.packed_bytes(codec.in_precision(codec.scaled_ints(column, c.scale), c.precision, c.name), c.precision, c.scale))
    if c.kind in WIDTHS:
        v = codec.column_values(column, c.kind)
        if c.kind in ("float4", "float8"):
            return _Column(there, fixed=codec.tree_float_bytes(v, WIDTHS[c.kind], float_codec))
        if c.kind == "date":
            return _Column(there, fixed=codec.packed_date_bytes(v))
        return _Column(there, fixed=codec.tree_int_bytes(v.astype(np.int64), WIDTHS[c.kind]))
    if c.kind == "bpchar" and c.max_len:
        column = pc.utf8_rpad(column.cast(pa.string()), c.max_len, " ")
    flat, starts, lengths = codec.text_spans(column)
    if overflow and c.name in overflow:
        first = overflow[c.name]
        pointer = np.zeros((n, POINTER), np.uint8)
        for at, values, width in ((4, first, 4), (8, np.full(n, PAGE_HEADER), 4), (12, lengths, 8)):
            pointer[:, at : at + width] = np.ascontiguousarray(values.astype(f">u{width}")).view(np.uint8).reshape(n, width)
        away = first > 0
        return _Column(there, flat=np.concatenate([flat, pointer.ravel()]), starts=np.where(away, len(flat) + POINTER * np.arange(n), starts), lengths=np.where(away, POINTER, lengths), away=away)
    return _Column(there, flat=flat, starts=starts, lengths=lengths)


def page_frame(number: int, kind: int, level: int = 0, index_id: int = 0, heap: int = 2) -> np.ndarray:
    out = np.zeros(PAGE, np.uint8)
    put = lambda at, value, width: out.__setitem__(slice(at, at + width), np.frombuffer(int(value).to_bytes(width, "big"), np.uint8))
    put(4, number, 4)
    put(24, kind, 2)
    if kind == INDEX_PAGE:
        put(38, 2, 2)
        put(40, DATA, 2)
        put(42, 0x8000 | heap, 2)
        put(64, level, 2)
        put(66, index_id, 8)
        out[99:107] = np.frombuffer(b"infimum\0", np.uint8)
        out[112:120] = np.frombuffer(b"supremum", np.uint8)
        out[94], out[97:99] = 1, np.frombuffer((LAST - FIRST).to_bytes(2, "big"), np.uint8)
        out[96], out[109] = 2, 3  # record types of the two
    return out


def encode(batch: pa.RecordBatch, schema: StorageSchema, first_page: int = ROOT + 1, index_id: int = 40, float_codec: str = "ordered", prefix: str = "declared", fill_factor: int = 94, hidden: int = 1, overflow: dict[str, np.ndarray] | None = None) -> np.ndarray:
    """Leaf pages that hold the batch's rows, which must be in key order.  A column `__state` of 1 marks a row deleted."""
    n, order = batch.num_rows, schema.physical()
    if not n:
        return np.zeros((0, PAGE), np.uint8)
    cols = [_column(c, batch, float_codec, hidden, overflow) for c in order]
    nullable = [(c, k) for c, k in zip(order, cols) if c.nullable]
    null_bytes = (len(nullable) + 7) // 8
    data, prefix_size, places, entry = np.zeros(n, np.int64), np.full(n, null_bytes, np.int64), [], []
    for c, k in zip(order, cols):
        places.append(data)
        size = np.full(n, k.fixed.shape[1]) if k.fixed is not None else k.lengths
        if k.fixed is None:
            one = 0 < c.max_len <= 255
            if one and (k.lengths[k.there] > 255).any():
                raise PageError(f"a value of {c.name} is longer than declared")
            wide = np.zeros(n, bool) if one else np.ones(n, bool) if prefix == "declared" else (k.lengths > 127) | (k.away if k.away is not None else False)
            entry.append((prefix_size, wide))
            prefix_size = prefix_size + np.where(k.there, np.where(wide, 2, 1), 0)
        else:
            entry.append(None)
        data = data + np.where(k.there, size, 0)
    size, room = prefix_size + 5 + data, PAGE - DATA - TRAILER - 64
    if (size > room // 2).any():
        raise PageError("a row is larger than half a page; keep long values as overflow")
    total, limit, starts = np.cumsum(size), int(room * fill_factor / 100), [0]
    while starts[-1] < n:  # over pages
        done = total[starts[-1] - 1] if starts[-1] else 0
        starts.append(int(np.searchsorted(total, done + limit, side="right")))
    starts = np.array(starts)
    count = np.diff(starts)
    page = np.repeat(np.arange(len(count)), count)
    before = np.where(starts[page] > 0, total[starts[page] - 1], 0)
    end = DATA + total - before  # in the page
    origin_in = end - data
    origin = page * PAGE + origin_in
    out = np.zeros(len(count) * PAGE, np.uint8)
    for c, k, at, e in zip(order, cols, places, entry):
        rows = np.flatnonzero(k.there)
        if k.fixed is not None:
            codec.put(out, origin[rows] + at[rows], k.fixed[rows])
            continue
        where, wide = origin[rows] - 6 - e[0][rows], e[1][rows]
        length, away = k.lengths[rows], (k.away[rows] if k.away is not None else np.zeros(len(rows), bool))
        mark = np.where(away, 0x40, 0) | (0x80 if prefix == "adaptive" else 0)
        out[where] = np.where(wide, (length >> 8) | mark, length)
        out[where[wide] - 1] = length[wide] & 255
        offsets, source = codec.span_index(k.starts[rows], length)
        out[np.repeat(origin[rows] + at[rows] - offsets[:-1], length) + np.arange(offsets[-1])] = k.flat[source]
    for i, (_, k) in enumerate(nullable):
        rows = np.flatnonzero(~k.there)
        np.bitwise_or.at(out, origin[rows] - 6 - (i >> 3), np.uint8(1 << (i & 7)))
    state = np.asarray(batch.column("__state")).astype(np.int64) if "__state" in batch.schema.names else np.zeros(n, np.int64)
    out[origin - 5] = np.where(state == 1, DELETED, 0)
    heap_no = np.arange(n) - starts[page] + 2
    out[origin - 4], out[origin - 3] = (heap_no << 3) >> 8, (heap_no << 3) & 255
    is_last = np.r_[page[1:] != page[:-1], True]
    step = np.where(is_last, LAST - origin_in, np.r_[origin_in[1:], 0] - origin_in) & 0xFFFF
    out[origin - 2], out[origin - 1] = step >> 8, step & 255
    pages = out.reshape(-1, PAGE)
    first_origin = origin_in[starts[:-1]]
    for i in range(len(count)):  # over pages: frames
        frame = page_frame(first_page + i, INDEX_PAGE, 0, index_id, int(count[i]) + 2)
        pages[i, :DATA] = frame[:DATA]
        pages[i, 97:99] = np.frombuffer(int(first_origin[i] - FIRST).to_bytes(2, "big"), np.uint8)
        pages[i, 40:42] = np.frombuffer(int(end[starts[i + 1] - 1]).to_bytes(2, "big"), np.uint8)
    return pages


def value_pages(value: bytes, first: int) -> np.ndarray:
    """The chain of pages that holds a long value, from page number first on."""
    count = -(-len(value) // PART)
    out = np.vstack([page_frame(first + k, LONG_VALUE) for k in range(count)])
    for k in range(count):
        part = value[k * PART : (k + 1) * PART]
        head = len(part).to_bytes(4, "big") + (first + k + 1 if k + 1 < count else NO_PAGE).to_bytes(4, "big")
        out[k, PAGE_HEADER : PAGE_HEADER + 8 + len(part)] = np.frombuffer(head + part, np.uint8)
    return out


def chained(read: Callable[[int, int], bytes], first: int, length: int) -> bytes:
    """A long value; read gives the bytes of some pages in a row.  Chains that lie in a row are read at once."""
    out, have, page = [], 0, first
    while have < length:
        raw = read(page, -(-(length - have) // PART))
        for at in range(0, len(raw), PAGE):
            size, following = (int.from_bytes(raw[at + PAGE_HEADER + k : at + PAGE_HEADER + k + 4], "big") for k in (0, 4))
            if int.from_bytes(raw[at + 24 : at + 26], "big") != LONG_VALUE or not 0 < size <= PART:
                raise PageError(f"page {page} holds no part of a long value")
            out.append(raw[at + PAGE_HEADER + 8 : at + PAGE_HEADER + 8 + size])
            have += size
            if following != page + 1:
                page = following
                break
            page = following
        if have < length and page == NO_PAGE:
            raise PageError("a long value's pages end before its length")
    return b"".join(out)[:length]


def file_start(index_id: int) -> np.ndarray:
    """The first pages of a file: space header, allocation map, inodes, and the clustered root, which is an interior page."""
    return np.vstack([page_frame(0, SPACE_HEADER), page_frame(1, ALLOCATION), page_frame(2, INODE), page_frame(ROOT, INDEX_PAGE, 1, index_id)])


def decoy(number: int, index_id: int, rows: int = 20, level: int = 0) -> np.ndarray:
    """A page with records of a shape of their own, which a table scan must not read: a leaf of a secondary index, or, above
    level 0, an interior page."""
    page = page_frame(number, INDEX_PAGE, level, index_id, rows + 2)
    at, last = DATA, FIRST
    for k in range(rows):
        origin = at + 5
        step = (origin - last) & 0xFFFF
        page[last - 2], page[last - 1] = step >> 8, step & 255
        page[origin : origin + 12] = k + 1
        last, at = origin, origin + 12
    step = (LAST - last) & 0xFFFF
    page[last - 2], page[last - 1] = step >> 8, step & 255
    return page
