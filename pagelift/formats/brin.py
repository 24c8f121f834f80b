"""Block-range index files: min/max summaries of runs of heap pages, and the test that prunes runs by them."""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np

from pagelift.formats.heap import HEADER, NORMAL, PAGE, PageError
from pagelift.schema import StorageColumn

MAGIC = 0xA8109CFA
POINTER = 6
DATA_OFFSET_MASK, HAS_NULLS = 0x1F, 0x80
MAP_SPECIAL = PAGE - 8
CAPACITY = (MAP_SPECIAL - HEADER) // POINTER


@dataclass(frozen=True)
class RangePredicate:
    """low <= column <= high, where a bound may be missing; strict bounds are kept for what they are worth, but prune as
    closed ones.  values: the column equals one of them."""

    column: str
    low: object = None
    high: object = None
    values: tuple | None = None

    @classmethod
    def parse(cls, text: str) -> RangePredicate:
        """column:type:low:high, with either bound possibly empty; the bounds of timestamps may hold colons."""
        m = re.fullmatch(r"(\w+):(\w+)(?:\([\d,]+\))?:(.*)", text, re.S)
        if not m:
            raise ValueError(f"a range is column:type:low:high, not {text!r}")
        kind, rest = m[2], m[3]
        if kind in ("timestamp", "date"):
            one = r"((?:\d{4}-\d{2}-\d{2}(?:[ T]\d{2}:\d{2}(?::\d{2}(?:\.\d+)?)?)?)?)"
            b = re.fullmatch(one + ":" + one, rest)
            if not b:
                raise ValueError(f"bounds of {text!r} aren't dates")
            low, high = b[1], b[2]
        else:
            low, _, high = rest.partition(":")
        read = reader_of(kind)
        return cls(m[1], read(low) if low else None, read(high) if high else None)

    def to_closed(self, other: RangePredicate) -> RangePredicate:
        """Both at once, on one column."""
        top = lambda a, b, f: b if a is None else a if b is None else f(a, b)
        if self.values is not None and other.values is not None:
            values = tuple(v for v in self.values if v in other.values)
        else:
            values = self.values if self.values is not None else other.values
        return RangePredicate(self.column, top(self.low, other.low, max), top(self.high, other.high, min), values)


def reader_of(kind: str):
    """Text of a bound -> the index's comparable value."""
    if kind in ("int2", "int4", "int8", "int", "bigint"):
        return int
    if kind == "timestamp":
        return lambda x: int(np.datetime64(x.strip().replace(" ", "T"), "us").astype(np.int64))
    if kind == "date":
        return lambda x: int(np.datetime64(x.strip(), "D").astype(np.int64))
    if kind in ("float4", "float8", "numeric", "double", "float"):
        return float
    return lambda x: x.encode() if isinstance(x, str) else x


def comparable(value, kind: str):
    """A Python value of a pushed filter as the index compares it."""
    import datetime

    if value is None:
        return None
    if kind == "timestamp" and isinstance(value, datetime.datetime):
        return int(np.datetime64(value.replace(tzinfo=None), "us").astype(np.int64))
    if kind == "date" and isinstance(value, datetime.date):
        return int(np.datetime64(value, "D").astype(np.int64))
    if kind in ("float4", "float8", "numeric"):
        return float(value)
    if kind in ("bpchar", "varchar", "text"):
        return value.encode() if isinstance(value, str) else bytes(value)
    return value


@dataclass
class Ranges:
    """One entry a page range; usable is false where nothing may be concluded.  Bounds of fixed-width kinds are vectors, of
    others lists of bytes."""

    pages_per_range: int
    usable: np.ndarray
    low: np.ndarray | list
    high: np.ndarray | list
    all_null: np.ndarray
    some_null: np.ndarray

    def __len__(self):
        return len(self.usable)


#: Bytes of a stored bound, numpy type, and what to add to get the comparable value.
BOUNDS = {"int2": ("<i2", 0), "int4": ("<i4", 0), "int8": ("<i8", 0), "date": ("<i4", 10_957), "timestamp": ("<i8", 10_957 * 86_400 * 10**6), "float4": ("<f4", 0), "float8": ("<f8", 0), "numeric": ("<f8", 0)}


def _u(raw, at: int, width: int) -> int:
    return int.from_bytes(raw[at : at + width], "little")


def meta(data: bytes) -> tuple[int, int]:
    """Pages a range and the last map page."""
    if len(data) < PAGE or _u(data, HEADER, 4) != MAGIC:
        raise PageError("not a block-range index")
    return _u(data, HEADER + 8, 4), _u(data, HEADER + 12, 4)


def pointers(data: bytes) -> np.ndarray:
    """(block, slot) of each range's summary, slot 0 where there is none.  A map page's capacity follows from its special
    offset; its lower offset isn't kept up."""
    _, last = meta(data)
    out = []
    for p in range(1, last + 1):
        base = p * PAGE
        capacity = (_u(data, base + 16, 2) - HEADER) // POINTER
        words = np.frombuffer(data, "<u2", 3 * capacity, base + HEADER).reshape(-1, 3).astype(np.int64)
        out.append(np.column_stack([(words[:, 0] << 16) | words[:, 1], words[:, 2]]))
    return np.concatenate(out) if out else np.zeros((0, 2), np.int64)


def null_flags(info: int, attribute: int = 0, mode: str = "paired", bitmap: int = 0) -> tuple[bool, bool]:
    """(all null, some null) of a stored attribute: two neighbouring bits of the info byte, or of a separate bitmap."""
    word = info if mode == "paired" else bitmap
    return bool(word >> (2 * attribute) & 1), bool(word >> (2 * attribute + 1) & 1)


def _text(data: bytes, at: int):
    size = data[at] >> 1 if data[at] & 1 else _u(data, at, 4) >> 2
    head = 1 if data[at] & 1 else 4
    return bytes(data[at + head : at + size]), at + size


def _stored_text(value) -> bytes:
    raw = value.encode() if isinstance(value, str) else bytes(value)
    return bytes([((len(raw) + 1) << 1) | 1]) + raw if len(raw) < 127 else ((len(raw) + 4) << 2).to_bytes(4, "little") + raw


def covered(data: bytes) -> tuple[int, int]:
    """Pages that the index was built over and the number of its relation, or zeros where a file doesn't tell: then
    whoever wrote it keeps it up to date."""
    return _u(data, HEADER + 16, 8), _u(data, HEADER + 24, 8)


def load(data: bytes, column: StorageColumn, heap_pages: int, mode: str = "paired") -> Ranges:
    """Summaries of the ranges that cover heap_pages pages; a missing or all-null one is of no use, and neither is one of a
    range that has grown since the index was built."""
    per, _ = meta(data)
    where = pointers(data)
    n = -(-heap_pages // per)
    usable, some, every = np.zeros(n, bool), np.zeros(n, bool), np.zeros(n, bool)
    flat = np.frombuffer(data, np.uint8)
    rows = np.flatnonzero(where[:n, 1] > 0)
    base = where[rows, 0] * PAGE
    at = base + HEADER + 4 * (where[rows, 1] - 1)
    word = np.ascontiguousarray(flat[at[:, None] + np.arange(4)]).view("<u4").ravel().astype(np.int64)
    on = (word >> 15) & 3 == NORMAL
    rows, at = rows[on], (base + (word & 0x7FFF))[on]
    info = flat[at + 4].astype(np.int64)
    flags = info if mode == "paired" else flat[at + 5].astype(np.int64)
    every[rows], some[rows] = (flags & 1) != 0, (flags & 2) != 0
    start = at + ((info & DATA_OFFSET_MASK) if mode == "bitmap" else 8)
    rows, start = rows[~every[rows]], start[~every[rows]]
    usable[rows] = True
    if column.kind in BOUNDS:
        kind, shift = BOUNDS[column.kind]
        width = np.dtype(kind).itemsize
        wide = np.float64 if kind[1] == "f" else np.int64
        low, high = np.zeros(n, wide), np.zeros(n, wide)
        for k, out in enumerate((low, high)):
            raw = np.ascontiguousarray(flat[(start + k * width)[:, None] + np.arange(width)])
            out[rows] = raw.view(kind).ravel().astype(wide) + wide(shift)
    else:
        low, high = [None] * n, [None] * n
        for i, p in zip(rows.tolist(), start.tolist()):
            low[i], p = _text(data, p)
            high[i], _ = _text(data, p)
    pages, _ = covered(data)
    if pages and heap_pages > pages:
        usable[pages // per :] = False
    return Ranges(per, usable, low, high, every, some)


def keep(ranges: Ranges, predicate: RangePredicate | None) -> np.ndarray:
    """Ranges that must be read: those of no use, and those whose interval meets the predicate's."""
    if predicate is None:
        return np.ones(len(ranges), bool)
    low, high = predicate.low, predicate.high
    if isinstance(ranges.low, np.ndarray):
        meets = np.ones(len(ranges), bool)
        if low is not None:
            meets &= ~(ranges.high < low)  # a bound that is no number excludes nothing
        if high is not None:
            meets &= ~(ranges.low > high)
        if predicate.values is not None:
            among = np.zeros(len(ranges), bool)
            for v in predicate.values:
                among |= ~((ranges.low > v) | (ranges.high < v))
            meets &= among
        return meets | ~ranges.usable
    out = np.ones(len(ranges), bool)
    for i in np.flatnonzero(ranges.usable):
        a, b = ranges.low[i], ranges.high[i]
        if (low is not None and b < low) or (high is not None and a > high):
            out[i] = False
        elif predicate.values is not None:
            out[i] = any(a <= v <= b for v in predicate.values)
    return out


def _bodies(low, high, every: np.ndarray, column: StorageColumn) -> tuple[np.ndarray, np.ndarray]:
    """Rows of bytes of the bounds, padded to one width, and how many of them count."""
    if column.kind in BOUNDS:
        kind, shift = BOUNDS[column.kind]
        width = np.dtype(kind).itemsize
        out = np.zeros((len(every), 2 * width), np.uint8)
        for k, bound in enumerate((low, high)):
            v = np.array([0 if x is None else x for x in bound]) if not isinstance(bound, np.ndarray) else bound
            out[:, k * width : (k + 1) * width] = np.ascontiguousarray((np.where(every, shift, v) - shift).astype(kind)).view(np.uint8).reshape(len(every), width)
        return out, np.where(every, 0, 2 * width)
    raw = [b"" if n else _stored_text(a) + _stored_text(b) for a, b, n in zip(low, high, every)]
    sizes = np.array([len(x) for x in raw], np.int64)
    out = np.zeros((len(raw), int(sizes.max(initial=0))), np.uint8)
    for i, x in enumerate(raw):
        out[i, : len(x)] = np.frombuffer(x, np.uint8)
    return out, sizes


def write_ranges(present: np.ndarray, low, high, every: np.ndarray, some: np.ndarray, column: StorageColumn, pages_per_range: int, mode: str = "paired", pages: int = 0, relation: int = 0) -> bytes:
    """An index file.  present: ranges that have a summary; bounds, all null and some null are given for all ranges."""
    rows = np.flatnonzero(present)
    pick = lambda x: x[rows] if isinstance(x, np.ndarray) else [x[i] for i in rows.tolist()]
    body, used = _bodies(pick(low), pick(high), every[rows], column)
    flags = every[rows].astype(np.int64) | some[rows].astype(np.int64) << 1
    head = np.zeros((len(rows), 8), np.uint8)
    head[:, :4] = np.ascontiguousarray((rows * pages_per_range).astype("<u4")).view(np.uint8).reshape(-1, 4)
    head[:, 4] = flags if mode == "paired" else 8 | np.where(flags > 0, HAS_NULLS, 0)
    head[:, 5] = 0 if mode == "paired" else flags
    size = (8 + used + 7) & -8
    room = MAP_SPECIAL - HEADER
    # pages in order: a tuple and its pointer go to the next page when this one is full
    total, starts = np.cumsum(size + 4), [0]
    while starts[-1] < len(rows):  # over pages
        done = total[starts[-1] - 1] if starts[-1] else 0
        starts.append(max(int(np.searchsorted(total, done + room, side="right")), starts[-1] + 1))
    starts = np.array(starts)
    count = np.diff(starts)
    page = np.repeat(np.arange(len(count)), count)
    slot = np.arange(len(rows)) - starts[page]
    down = np.cumsum(size)
    upper = MAP_SPECIAL - (down - np.where(starts[page] > 0, down[starts[page] - 1], 0))
    tuples = np.zeros((max(1, len(count)), PAGE), np.uint8)
    flat = tuples.reshape(-1)
    at = page * PAGE + upper
    flat[at[:, None] + np.arange(8)] = head
    for w in np.unique(used):
        of = np.flatnonzero(used == w)
        flat[(at[of] + 8)[:, None] + np.arange(w)] = body[of, :w]
    pointer = (upper | NORMAL << 15 | size << 17).astype("<u4")
    flat[(page * PAGE + HEADER + 4 * slot)[:, None] + np.arange(4)] = pointer.view(np.uint8).reshape(-1, 4)
    lows = np.full(len(tuples), HEADER)
    highs = np.full(len(tuples), MAP_SPECIAL)
    lows[: len(count)] += 4 * count
    if len(count):
        highs[: len(count)] = upper[starts[1:] - 1]
    tuples[:, 12:18] = np.column_stack([lows, highs, np.full(len(tuples), MAP_SPECIAL)]).astype("<u2").view(np.uint8).reshape(-1, 6)
    maps = max(1, -(-len(present) // CAPACITY))
    words = np.zeros((maps * CAPACITY, 3), np.int64)
    block = 1 + maps + page
    words[rows] = np.column_stack([block >> 16, block & 0xFFFF, slot + 1])
    map_pages = np.zeros((maps, PAGE), np.uint8)
    # the lower offset stays at the header's end on purpose, as servers leave it
    map_pages[:, 12:18] = np.array([HEADER, MAP_SPECIAL, MAP_SPECIAL], "<u2").view(np.uint8)
    map_pages[:, HEADER : HEADER + CAPACITY * POINTER] = words.astype("<u2").view(np.uint8).reshape(maps, -1)
    first = bytearray(PAGE)
    first[HEADER : HEADER + 16] = b"".join(x.to_bytes(4, "little") for x in (MAGIC, 1, pages_per_range, maps))
    first[HEADER + 16 : HEADER + 32] = pages.to_bytes(8, "little") + relation.to_bytes(8, "little")
    first[12:14], first[14:16], first[16:18] = (x.to_bytes(2, "little") for x in (HEADER + 32, MAP_SPECIAL, MAP_SPECIAL))
    return bytes(first) + map_pages.tobytes() + tuples.tobytes()


def write(summaries: list[tuple[object, object, bool, bool] | None], column: StorageColumn, pages_per_range: int, mode: str = "paired") -> bytes:
    """An index file of (low, high, all null, some null) a range, or None for a range without summary."""
    low, high, every, some = (list(x) for x in zip(*[s or (None, None, True, False) for s in summaries])) if summaries else ([], [], [], [])
    return write_ranges(np.array([s is not None for s in summaries], bool), low, high, np.array(every, bool), np.array(some, bool), column, pages_per_range, mode)
