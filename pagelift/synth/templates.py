"""Parts of generated readers, as text: complete sources that import numpy and pyarrow only.

A source reads the column specification when it is called and has a branch for each storage type, whether the table at hand
has such a column or not.  Numbers in angle brackets come from the format specification.
"""

from __future__ import annotations

import re

COMMON = '''import re

import numpy as np
import pyarrow as pa

PAGE = <page_size>
ARROW = {
    "bool": pa.bool_(), "int2": pa.int16(), "int4": pa.int32(), "int8": pa.int64(), "float4": pa.float32(), "float8": pa.float64(),
    "numeric": pa.float64(), "date": pa.date32(), "timestamp": pa.timestamp("us"), "bpchar": pa.string(), "varchar": pa.string(),
    "text": pa.string(), "binary": pa.binary(),
}


def columns_of(text):
    """(name, type, arguments, nullable) of each "name:type(arguments)!"."""
    found = re.findall(r"(\\w+):(\\w+)(?:\\(([\\d,]+)\\))?(!?)", text)
    return [(name, kind, [int(a) for a in arguments.split(",") if a], not required) for name, kind, arguments, required in found]


def pick(flat, at, width):
    return flat[at[:, None] + np.arange(width)]


def validity(there):
    return None if there.all() else pa.py_buffer(np.packbits(there, bitorder="little").tobytes())


def plain(kind, values, there):
    full = np.zeros(len(there), values.dtype)
    full[there] = values
    data = np.packbits(full, bitorder="little") if pa.types.is_boolean(kind) else full
    return pa.Array.from_buffers(kind, len(there), [validity(there), pa.py_buffer(data.tobytes())])


def strings(kind, flat, start, size, there):
    first, length = np.zeros(len(there), np.int64), np.zeros(len(there), np.int64)
    first[there], length[there] = start, size
    offsets = np.concatenate([[0], np.cumsum(length)])
    place = np.repeat(first - offsets[:-1], length) + np.arange(offsets[-1])
    return pa.Array.from_buffers(kind, len(there), [validity(there), pa.py_buffer(offsets.astype(np.int32).tobytes()), pa.py_buffer(flat[place].tobytes())])


def without_padding(flat, start, size):
    size = size.copy()
    open_ = np.flatnonzero(size > 0)
    while len(open_):
        open_ = open_[flat[start[open_] + size[open_] - 1] == 32]
        size[open_] -= 1
        open_ = open_[size[open_] > 0]
    return size


def nearest(digits, tens, negative):
    """Doubles of whole numbers (Python's, where they are long) times powers of ten."""
    small = np.array([d < 1 << 53 for d in digits], bool) & (np.abs(tens) <= 22)
    out = np.zeros(len(digits))
    m, power = np.where(small, digits, 0).astype(np.float64), 10.0 ** np.minimum(np.abs(tens), 22)
    out = np.where(tens < 0, m / power, m * power)
    for i in np.flatnonzero(~small):
        out[i] = float(f"{int(digits[i])}e{int(tens[i])}")
    return np.where(negative, -out, out)

'''

#: Decoders of fixed-width values from rows of raw bytes, by type.
HEAP_FIXED = {
    "bool": ("1", "raw[:, 0] != 0"),
    "int2": ("2", 'raw.view("<i2").ravel()'),
    "int4": ("4", 'raw.view("<i4").ravel()'),
    "int8": ("8", 'raw.view("<i8").ravel()'),
    "float4": ("4", 'raw.view("<f4").ravel()'),
    "float8": ("8", 'raw.view("<f8").ravel()'),
    "date": ("4", 'raw.view("<i4").ravel() + np.int32(<epoch_days>)'),
    "timestamp": ("8", 'raw.view("<i8").ravel() + np.int64(<epoch_days>) * 86_400_000_000'),
}

HEAP_NUMERIC = '''

def numeric_values(flat, start, size):
    head = pick(flat, start, 2).view("<u2").ravel().astype(np.int64)
    following = pick(flat, start + 2, 2).view("<i2").ravel().astype(np.int64)
    short, special = head >> 14 == 2, head >> 14 == 3
    weight = np.where(short, (head & 63) - (head & 64), following)
    negative = np.where(short, head & 0x2000, head & 0x4000) > 0
    skip = np.where(short, 2, 4)
    count = np.where(special, 0, (size - skip) // 2)
    number = np.zeros(len(start), object)
    for k in range(int(count.max(initial=0))):
        on = np.flatnonzero(count > k)
        number[on] = number[on] * 10_000 + pick(flat, start[on] + skip[on] + 2 * k, 2).view("<u2").ravel().astype(object)
    out = nearest(number, np.where(count > 0, 4 * (weight - count + 1), 0), negative)
    sign = head >> 12 & 3
    return np.where(special, np.where(sign == 1, np.inf, np.where(sign == 3, -np.inf, np.nan)), out)

'''

HEAP_BODY = '''

def datum(flat, at):
    """Start and size of a variable-width value, and the place after it."""
    at = np.where(flat[at] == 0, (at + 3) // 4 * 4, at)
    first = flat[at].astype(np.int64)
    if ((first == 1) | (first & 3 == 2)).any():
        raise ValueError("a value is stored elsewhere or compressed")
    word = pick(flat, at, 4).view("<u4").ravel().astype(np.int64)
    total = np.where(first & 1, first >> 1, word >> 2)
    head = np.where(first & 1, 1, 4)
    return at + head, total - head, at + total


def read_pages(pages, column_spec, names=None, index_id=None):
    pages = np.asarray(pages, np.uint8).reshape(-1, PAGE)
    flat = np.concatenate([pages.ravel(), np.zeros(64, np.uint8)])
    lower = np.ascontiguousarray(pages[:, 12:14]).view("<u2").ravel().astype(np.int64)
    count = np.where(lower > 0, (lower - <header>) // <pointer>, 0)
    page = np.repeat(np.arange(len(pages)), count)
    slot = np.arange(len(page)) - np.repeat(np.cumsum(count) - count, count)
    pointer = pick(flat, page * PAGE + <header> + <pointer> * slot, 4).view("<u4").ravel().astype(np.int64)
    on = (pointer >> 15 & 3 == 1) & (pointer >> 17 > 0)
    start = (page * PAGE + (pointer & 0x7FFF))[on]
    flags = pick(flat, start + 20, 2).view("<u2").ravel().astype(np.int64)
    deleter = pick(flat, start + 4, 4).view("<u4").ravel()
    live = (deleter == 0) | (flags & 0x0800 > 0) | (flags & 0x0080 > 0)
    start, flags = start[live], flags[live]
    attributes = pick(flat, start + 18, 2).view("<u2").ravel().astype(np.int64) & 0x7FF
    cursor, out = start + flat[start + 22], {}
    for number, (name, kind, arguments, _) in enumerate(columns_of(column_spec)):
        bit = flat[start + <tuple_header> + number // 8] >> (number % 8) & 1
        there = (attributes > number) & ((flags & 1 == 0) | (bit == 1))
        at = cursor[there]
        if kind in FIXED:
            width, values = FIXED[kind]
            at = (at + width - 1) // width * width
            array, end = plain(ARROW[kind], values(pick(flat, at, width)), there), at + width
        else:
            first, size, end = datum(flat, at)
            if kind == "numeric":
                array = plain(ARROW[kind], numeric_values(flat, first, size), there)
            elif kind == "bpchar":
                array = strings(ARROW[kind], flat, first, without_padding(flat, first, size), there)
            else:
                array = strings(ARROW[kind], flat, first, size, there)
        cursor = cursor.copy()
        cursor[there] = end
        out[name] = array
    names = names or list(out)
    return pa.RecordBatch.from_arrays([out[n] for n in names], names=names)
'''

TREE_FIXED = {
    "bool": ("1", "signed(raw) != 0"),
    "int2": ("2", "signed(raw).astype(np.int16)"),
    "int4": ("4", "signed(raw).astype(np.int32)"),
    "int8": ("8", "signed(raw)"),
    "float4": ("4", 'ordered(raw).view(">f4").ravel().astype("<f4")'),
    "float8": ("8", 'ordered(raw).view(">f8").ravel().astype("<f8")'),
    "date": ("3", "calendar(raw)"),
    "timestamp": ("8", "signed(raw)"),
}

TREE_HELPERS = '''

def signed(raw):
    """Whole numbers, big-endian, the sign bit turned."""
    top = (raw[:, 0] ^ 128).astype(np.int8).astype(np.int64)
    for k in range(1, raw.shape[1]):
        top = (top << 8) | raw[:, k]
    return top


def ordered(raw):
    """Bytes of floating-point numbers whose order is the bytes' order."""
    turned = np.where(raw[:, :1] >= 128, raw ^ np.array([128] + [0] * (raw.shape[1] - 1), np.uint8), ~raw)
    return np.ascontiguousarray(turned)


def calendar(raw):
    """Days since 1970 of three bytes of year, month and day."""
    v = signed(raw)
    months = (v >> 9) * 12 + (v >> 5 & 15) - 1
    first = (months - 1970 * 12).astype("datetime64[M]").astype("datetime64[D]")
    return (first.astype(np.int64) + (v & 31) - 1).astype(np.int32)

'''

TREE_NUMERIC = '''

def groups_of(precision, scale):
    """(digits, bytes) of a packed decimal's groups."""
    used = (0, 1, 1, 2, 2, 3, 3, 4, 4, 4)
    whole = precision - scale
    sizes = [whole % 9] + [9] * (whole // 9) + [9] * (scale // 9) + [scale % 9]
    return [(n, used[n]) for n in sizes if n]


def packed_width(precision, scale):
    return sum(n for _, n in groups_of(precision, scale))


def numeric_values(raw, precision, scale):
    negative = raw[:, 0] < 128
    data = np.where(negative[:, None], ~raw, raw)
    data[:, 0] ^= 128
    number, at = np.zeros(len(raw), object), 0
    for digits, width in groups_of(precision, scale):
        group = np.zeros(len(raw), np.int64)
        for k in range(at, at + width):
            group = group * 256 + data[:, k]
        number, at = number * 10**digits + group.astype(object), at + width
    return nearest(number, np.full(len(raw), -scale), negative)

'''

TREE_BODY = '''

def read_pages(pages, column_spec, names=None, index_id=None):
    pages = np.asarray(pages, np.uint8).reshape(-1, PAGE)
    flat = np.concatenate([pages.ravel(), np.zeros(64, np.uint8)])
    number = lambda at, width: sum(pages[:, at + k].astype(np.int64) << 8 * (width - 1 - k) for k in range(width))
    leaf = (number(24, 2) == <page_type>) & (number(64, 2) == 0)
    index = number(66, 8)
    if index_id is None:
        index_id = index[number(24, 2) == <page_type>].min(initial=np.iinfo(np.int64).max)
    page = np.flatnonzero(leaf & (index == index_id))
    at, steps = page * PAGE + <first_record>, []
    while len(at):  # one step along all pages' lists at once
        step = flat[at - 2].astype(np.int64) << 8 | flat[at - 1]
        at = page * PAGE + (at - page * PAGE + step) % 65536
        on = (step != 0) & (at != page * PAGE + <last_record>)
        page, at = page[on], at[on]
        steps.append(at)
        if len(steps) > PAGE:
            raise ValueError("a page's list doesn't end")
    origin = np.sort(np.concatenate(steps)) if steps else np.zeros(0, np.int64)
    origin = origin[(flat[origin - 5] & 0x20 == 0) & (flat[origin - 3] & 7 == 0)]
    columns, out = columns_of(column_spec), {}
    nullable = [name for name, _, _, can in columns if can]
    lengths, cursor = origin - 6 - (len(nullable) + 7) // 8, origin.copy()
    for name, kind, arguments, can in columns:
        there = np.ones(len(origin), bool)
        if can:
            k = nullable.index(name)
            there = flat[origin - 6 - k // 8] >> (k % 8) & 1 == 0
        if kind == "raw":
            cursor = cursor + arguments[0]
            continue
        at, array = cursor[there], None
        if kind in FIXED:
            width, values = FIXED[kind]
            array, size = plain(ARROW[kind], values(pick(flat, at, width)), there), width
        elif kind == "numeric":
            size = packed_width(*arguments)
            array = plain(ARROW[kind], numeric_values(pick(flat, at, size), *arguments), there)
        else:
            where = lengths[there]
            short = bool(arguments) and arguments[0] <= 255
            if not short and (flat[where] & 0x40).any():
                raise ValueError("a value is stored elsewhere")
            size = flat[where].astype(np.int64) if short else (flat[where].astype(np.int64) & 63) << 8 | flat[where - 1]
            lengths = lengths - there * (1 if short else 2)
            array = strings(ARROW[kind], flat, at, without_padding(flat, at, size) if kind == "bpchar" else size, there)
        cursor = cursor.copy()
        cursor[there] = at + size
        out[name] = array
    names = names or list(out)
    return pa.RecordBatch.from_arrays([out[n] for n in names], names=names)
'''


CELL_BRANCHES = '''

SIZES = np.array([0, 1, 2, 3, 4, 6, 8, 8, 0, 0, 0, 0])


def numbers(flat, at, code, real):
    """Numbers of any serial type."""
    out = np.zeros(len(at), np.float64 if real else np.int64)
    for c in np.unique(code):
        on = np.flatnonzero(code == c)
        if c == 7:
            out[on] = pick(flat, at[on], 8).view(">f8").ravel()
        elif c in (8, 9):
            out[on] = c - 8
        else:
            raw = pick(flat, at[on], int(SIZES[c]))
            value = raw[:, 0].astype(np.int8).astype(np.int64)
            for k in range(1, raw.shape[1]):
                value = value << 8 | raw[:, k]
            out[on] = value
    return out


VALUES = {
    "bool": lambda *a: numbers(*a, False) != 0,
    "int2": lambda *a: numbers(*a, False).astype(np.int16),
    "int4": lambda *a: numbers(*a, False).astype(np.int32),
    "int8": lambda *a: numbers(*a, False),
    "float4": lambda *a: numbers(*a, True).astype(np.float32),
    "float8": lambda *a: numbers(*a, True),
    "numeric": lambda *a: numbers(*a, True),
    "date": lambda *a: numbers(*a, False).astype(np.int32),
    "timestamp": lambda *a: numbers(*a, False),
}

'''

CELL_BODY = '''

def varint(flat, at):
    value, size, live = np.zeros(len(at), np.int64), np.ones(len(at), np.int64), np.arange(len(at))
    for k in range(9):
        byte = flat[at[live] + k].astype(np.int64)
        value[live] = value[live] << 8 | byte if k == 8 else value[live] << 7 | byte & 127
        size[live] = k + 1
        live = live[byte >= 128]
    return value, at + size


def read_pages(pages, column_spec, names=None, index_id=None):
    pages = np.asarray(pages, np.uint8).reshape(-1, PAGE)
    if (pages[:, 0] != <leaf>).any():
        raise ValueError("not a leaf page")
    flat = np.concatenate([pages.ravel(), np.zeros(64, np.uint8)])
    count = pages[:, 3].astype(np.int64) << 8 | pages[:, 4]
    page = np.repeat(np.arange(len(pages)), count)
    slot = np.arange(len(page)) - np.repeat(np.cumsum(count) - count, count)
    at = page * PAGE + <cell_pointers> + 2 * slot
    payload, at = varint(flat, page * PAGE + (flat[at].astype(np.int64) << 8 | flat[at + 1]))
    if (payload > PAGE - <overflow_margin>).any():
        raise ValueError("a row goes on along overflow pages")
    _, at = varint(flat, at)
    head, cursor = varint(flat, at)
    body, end, out = at + head, at + head, {}
    for name, kind, arguments, _ in columns_of(column_spec):
        known = cursor < end
        code, after = varint(flat, np.where(known, cursor, 0))
        code, cursor = np.where(known, code, 0), np.where(known, after, cursor)
        size = np.where(code >= 12, (code - 12) // 2, SIZES[np.minimum(code, 11)])
        there = code > 0
        if kind in VALUES:
            out[name] = plain(ARROW[kind], VALUES[kind](flat, body[there], code[there]), there)
        else:
            out[name] = strings(ARROW[kind], flat, body[there], size[there], there)
        body = body + size
    names = names or list(out)
    return pa.RecordBatch.from_arrays([out[n] for n in names], names=names)
'''


def fixed_table(branches: dict[str, tuple[str, str]]) -> str:
    """The decoders of fixed-width types: a function each, and a table of widths and functions."""
    functions = "".join(f"\n\ndef value_{kind}(raw):\n    raw = np.ascontiguousarray(raw)\n    return {code}\n" for kind, (_, code) in branches.items())
    return functions + "\n\nFIXED = {" + ", ".join(f'"{kind}": ({width}, value_{kind})' for kind, (width, _) in branches.items()) + "}\n"


PARTS = {
    "pageheap": lambda: [COMMON, fixed_table(HEAP_FIXED), HEAP_NUMERIC, HEAP_BODY],
    "pagecell": lambda: [COMMON, CELL_BRANCHES, CELL_BODY],
    "pagetree": lambda: [COMMON, TREE_HELPERS, fixed_table(TREE_FIXED), TREE_NUMERIC, TREE_BODY],
}


def source(kind: str, constants: dict) -> str:
    """A whole reader for a format; KeyError for a constant that the specification doesn't give."""
    text = "".join(part.strip("\n") + "\n\n\n" for part in PARTS[kind]())
    return re.sub(r"<(\w+)>", lambda m: str(constants[m[1]]), text).rstrip("\n") + "\n"
