"""Vectorised value codecs of both page formats.  A vector holds one entry a row.

Spans (starts, lengths into a flat byte vector) stand for variable-width values.  Rows are looped over in two cases only:
long strings, which are copied as slices, and exact numerics beyond 18 digits, which become Python integers.
"""

from __future__ import annotations

from decimal import Context, Decimal

import numpy as np
import pyarrow as pa

EPOCH_DAYS = 10_957  # 1970-01-01 to 2000-01-01
EPOCH_MICROS = EPOCH_DAYS * 86_400 * 10**6
JULIAN_1970 = 2_440_588
EXACT = Context(prec=400)  # of decimals that must not be rounded on the way
EXACT_TENS = 22  # powers of ten up to this are exact doubles
#: Bytes of a group of 0..9 decimal digits in the packed tree format.
GROUP_BYTES = [0, 1, 1, 2, 2, 3, 3, 4, 4, 4]


def take(flat: np.ndarray, at: np.ndarray, width: int) -> np.ndarray:
    """width bytes from each position."""
    return flat[at[:, None] + np.arange(width)]


def put(flat: np.ndarray, at: np.ndarray, data: np.ndarray) -> None:
    flat[at[:, None] + np.arange(data.shape[1])] = data


def span_index(starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Offsets of the values when laid end to end, and the source position of each byte."""
    offsets = np.zeros(len(lengths) + 1, np.int64)
    np.cumsum(lengths, out=offsets[1:])
    return offsets, np.repeat(starts - offsets[:-1], lengths) + np.arange(offsets[-1])


def gather(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Offsets and bytes of the spans laid end to end."""
    n = len(lengths)
    if n and lengths[0] == lengths.max() == lengths.min():
        width = int(lengths[0])
        return np.arange(n + 1, dtype=np.int64) * width, take(flat, starts, width).ravel() if width else np.zeros(0, np.uint8)
    if n and lengths.mean() > 200:  # long values: copies of slices beat a position for each byte
        view = memoryview(flat)
        offsets = np.concatenate([[0], np.cumsum(lengths)]).astype(np.int64)
        return offsets, np.frombuffer(b"".join(view[s : s + k] for s, k in zip(starts.tolist(), lengths.tolist())), np.uint8)
    offsets, at = span_index(starts, lengths)
    return offsets, flat[at]


def bits(valid: np.ndarray) -> pa.Buffer | None:
    return None if valid.all() else pa.py_buffer(np.packbits(valid, bitorder="little").tobytes())


def fixed_array(kind: pa.DataType, values: np.ndarray, valid: np.ndarray) -> pa.Array:
    """Two buffers: validity and data."""
    if pa.types.is_boolean(kind):
        return pa.Array.from_buffers(kind, len(values), [bits(valid), pa.py_buffer(np.packbits(values.astype(bool), bitorder="little").tobytes())])
    return pa.Array.from_buffers(kind, len(values), [bits(valid), pa.py_buffer(np.ascontiguousarray(values))])


def span_array(kind: pa.DataType, flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray, valid: np.ndarray) -> pa.Array:
    """Three buffers: validity, 32-bit offsets and bytes."""
    offsets, data = gather(flat, starts, np.where(valid, lengths, 0))
    if offsets[-1] >= 1 << 31:
        raise ValueError("a batch's strings reach 2^31 bytes; read fewer pages at a time")
    return pa.Array.from_buffers(kind, len(starts), [bits(valid), pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data))])


def rstrip_spans(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Lengths without trailing blanks."""
    lengths = lengths.copy()
    live = np.flatnonzero(lengths > 0)
    while len(live):
        live = live[flat[starts[live] + lengths[live] - 1] == 0x20]
        lengths[live] -= 1
        live = live[lengths[live] > 0]
    return lengths


def scaled(mantissa: np.ndarray, tens: np.ndarray, exact: np.ndarray, slow) -> np.ndarray:
    """mantissa * 10^tens as the nearest doubles: one operation on exact operands, else slow(row)."""
    ok = exact & (np.abs(mantissa) < 1 << 53) & (np.abs(tens) <= EXACT_TENS)
    power = 10.0 ** np.clip(np.abs(tens), 0, EXACT_TENS)
    m = mantissa.astype(np.float64)
    out = np.where(tens < 0, m / power, m * power)
    for i in np.flatnonzero(~ok):
        out[i] = slow(i)
    return out


# -- heap values ---------------------------------------------------------------------------------------------------


def heap_fixed(kind: str, raw: np.ndarray) -> np.ndarray:
    """Values of raw little-endian bytes (rows x width)."""
    raw = np.ascontiguousarray(raw)
    if kind == "bool":
        return raw[:, 0] != 0
    v = raw.view({"int2": "<i2", "int4": "<i4", "int8": "<i8", "float4": "<f4", "float8": "<f8", "date": "<i4", "timestamp": "<i8"}[kind]).ravel()
    return v + np.int32(EPOCH_DAYS) if kind == "date" else v + EPOCH_MICROS if kind == "timestamp" else v


def heap_fixed_bytes(kind: str, values: np.ndarray) -> np.ndarray:
    if kind == "bool":
        return values.astype(np.uint8)[:, None]
    if kind == "date":
        values = values.astype(np.int32) - np.int32(EPOCH_DAYS)
    if kind == "timestamp":
        values = values.astype(np.int64) - EPOCH_MICROS
    v = np.ascontiguousarray(values.astype({"int2": "<i2", "int4": "<i4", "int8": "<i8", "float4": "<f4", "float8": "<f8", "date": "<i4", "timestamp": "<i8"}[kind]))
    return v.view(np.uint8).reshape(len(v), -1)


def numeric_parts(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray):
    """Sign, special, weight, digit count, first digit position of base-10000 values."""
    last = len(flat) - 1
    u16 = lambda at: flat[np.minimum(at, last)].astype(np.int64) | (flat[np.minimum(at + 1, last)].astype(np.int64) << 8)
    head = u16(starts)
    short, special = (head & 0xC000) == 0x8000, (head & 0xC000) == 0xC000
    weight_short = (head & 0x3F) - np.where(head & 0x40, 64, 0)
    weight_long = u16(starts + 2)
    weight_long = weight_long - np.where(weight_long & 0x8000, 1 << 16, 0)
    negative = np.where(short, head & 0x2000, head & 0x4000) != 0
    size = np.where(short, 2, 4)
    return head, special, negative, np.where(short, weight_short, weight_long), np.where(special, 0, (lengths - size) >> 1), starts + size, u16


def numeric_double(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    head, special, negative, weight, digits, at, u16 = numeric_parts(flat, starts, lengths)
    mantissa = np.zeros(len(starts), np.int64)
    top = int(digits.max(initial=0))
    for k in range(min(top, 4)):  # over digit places
        mantissa = np.where(digits > k, mantissa * 10_000 + u16(at + 2 * k), mantissa)

    def slow(i):
        m = 0
        for k in range(int(digits[i])):
            m = m * 10_000 + int(u16(at[i : i + 1] + 2 * k)[0])
        return float(Decimal(m).scaleb(4 * (int(weight[i]) - int(digits[i]) + 1)))

    out = scaled(mantissa, np.where(digits > 0, 4 * (weight - digits + 1), 0), digits <= 4, slow)
    out = np.where(negative, -out, out)
    if special.any():
        out = np.where(special, np.where((head & 0x3000) == 0x1000, np.inf, np.where((head & 0x3000) == 0x3000, -np.inf, np.nan)), out)
    return out


WORD = 1 << 64


def decimal_array(values: np.ndarray, precision: int, scale: int, valid: np.ndarray) -> pa.Array:
    """Decimals of scaled whole numbers, as two 64-bit words each."""
    words = np.zeros((len(values), 2), np.uint64)
    if values.dtype == object:
        words[:, 0] = [int(v) % WORD for v in values]
        words[:, 1] = [(int(v) >> 64) % WORD for v in values]
    else:
        words[:, 0], words[:, 1] = values.view(np.uint64), (values >> 63).view(np.uint64)
    return pa.Array.from_buffers(pa.decimal128(precision, scale), len(values), [bits(valid), pa.py_buffer(words)])


def numeric_decimal(flat, starts, lengths, precision: int, scale: int, valid) -> pa.Array:
    """The same as 128-bit decimals, exactly; digits beyond the scale are rounded half to even, and values that no decimal
    of the precision holds are null."""
    _, special, negative, weight, digits, at, u16 = numeric_parts(flat, starts, lengths)
    valid = valid & ~special
    digits = np.where(valid, digits, 0)
    tens = np.where(digits > 0, 4 * (weight - digits + 1) + scale, 0)
    mantissa = np.zeros(len(starts), np.int64)
    for k in range(min(int(digits.max(initial=0)), 4)):
        mantissa = np.where(digits > k, mantissa * 10_000 + u16(at + 2 * k), mantissa)
    powers = 10 ** np.arange(19, dtype=np.int64)
    # four digits fill at most 16 places; trailing zeros of the last make shifts to the right exact as well
    down = powers[np.clip(-tens, 0, 18)]
    plain = (digits <= 4) & (tens >= -18) & (tens <= 18) & np.where(tens < 0, mantissa % down == 0, mantissa < 10**18 // powers[np.clip(tens, 0, 18)])
    out = np.where(tens < 0, mantissa // down, mantissa * np.where(plain, powers[np.clip(tens, 0, 18)], 1))
    out = np.where(negative, -out, out)
    rest = np.flatnonzero(valid & ~plain)
    if len(rest):
        out = out.astype(object)
        for i in rest:
            m = 0
            for k in range(int(digits[i])):
                m = m * 10_000 + int(u16(at[i : i + 1] + 2 * k)[0])
            m = m * 10 ** int(tens[i]) if tens[i] >= 0 else int((Decimal(m).scaleb(int(tens[i]), EXACT)).to_integral_value())
            out[i] = -m if negative[i] else m
    if precision < 19 or out.dtype == object:
        valid = valid & (np.abs(out) < 10**precision)
        out = np.where(valid, out, 0)
    return decimal_array(out, precision, scale, valid)


def scaled_ints(column: pa.Array, scale: int) -> np.ndarray:
    """The column's values times 10^scale as whole numbers, Python's where 64 bits are too few; nulls give 0."""
    valid = np.asarray(column.is_valid())
    if pa.types.is_decimal(column.type):
        words = np.frombuffer(column.cast(pa.decimal128(38, scale)).buffers()[1], np.int64).reshape(-1, 2)[column.offset : column.offset + len(column)]
        low, high = np.where(valid, words[:, 0], 0), np.where(valid, words[:, 1], 0)
        if (high == low >> 63).all():
            return low
        return high.astype(object) * WORD + low.view(np.uint64).astype(object)
    v = column.cast(pa.float64()).fill_null(0.0).to_numpy(zero_copy_only=False)
    v = np.where(np.isfinite(v), v, 0.0)
    near = np.rint(v * 10.0**scale)
    large = np.abs(near) >= 2.0**62
    out = np.where(large, 0, near).astype(np.int64)
    if large.any():  # so large doubles are whole numbers over a power of two: exact as decimals
        out = out.astype(object)
        for i in np.flatnonzero(large):
            out[i] = int(Decimal(float(v[i])).scaleb(scale, EXACT).to_integral_value())
    return out


def in_precision(values: np.ndarray, precision: int, name: str) -> np.ndarray:
    """The values; ValueError if one has more digits than its column."""
    if precision < 19 or values.dtype == object:
        if len(values) and (np.abs(values) >= 10**precision).any():
            raise ValueError(f"a value of {name} has more than {precision} digits")
    return values


def numeric_bytes(values: np.ndarray, scale: int, long_form: bool = False, special: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Lengths and padded rows of bytes of scaled whole numbers; special: 0 or the whole first word of NaN and infinities."""
    groups_after = -(-scale // 4)
    lift = 10 ** (4 * groups_after - scale)
    negative, m = (values < 0).astype(bool), np.abs(values)
    places = 6 if values.dtype != object else max(6, -(-(len(str(max(m, default=0))) + 3) // 4) + 1)
    digits = np.zeros((len(m), places), np.int64)
    if lift > 1:
        low = m % (10_000 // lift)
        rest = m // (10_000 // lift)
        digits[:, places - 1] = low * lift
        start = places - 2
    else:
        rest, start = m, places - 1
    for k in range(start, -1, -1):
        digits[:, k] = rest % 10_000
        rest = rest // 10_000
    used = digits != 0
    any_ = used.any(axis=1)
    first = np.where(any_, used.argmax(axis=1), places)
    last = np.where(any_, places - 1 - used[:, ::-1].argmax(axis=1), places - 1)
    count = np.where(any_, last - first + 1, 0)
    weight = np.where(any_, places - groups_after - 1 - first, 0)
    head = 4 if long_form else 2
    out = np.zeros((len(m), head + 2 * places), np.uint8)
    if long_form:
        word = (negative & any_) * 0x4000 | scale
        out[:, 2:4] = weight.astype("<i2").view(np.uint8).reshape(-1, 2)
    else:
        word = 0x8000 | np.where(negative & any_, 0x2000, 0) | (scale << 7) | (weight & 0x7F)
    out[:, :2] = np.asarray(word, "<u2").view(np.uint8).reshape(-1, 2)
    at = np.minimum(first[:, None] + np.arange(places), places - 1)
    packed = np.where(np.arange(places) < count[:, None], np.take_along_axis(digits, at, axis=1), 0)
    out[:, head:] = packed.astype("<u2").view(np.uint8).reshape(len(m), -1)
    lengths = head + 2 * count
    if special is not None and special.any():
        rows = special > 0
        out[rows, :2] = special[rows].astype("<u2").view(np.uint8).reshape(-1, 2)
        lengths = np.where(rows, 2, lengths)
    return lengths, out


# -- tree values ---------------------------------------------------------------------------------------------------


def tree_int(raw: np.ndarray) -> np.ndarray:
    """Big-endian with the sign bit flipped."""
    raw = raw.copy()
    raw[:, 0] ^= 0x80
    return np.ascontiguousarray(raw).view(f">i{raw.shape[1]}").ravel().astype(f"<i{raw.shape[1]}")


def tree_int_bytes(values: np.ndarray, width: int) -> np.ndarray:
    out = np.ascontiguousarray(values.astype(f">i{width}")).view(np.uint8).reshape(-1, width).copy()
    out[:, 0] ^= 0x80
    return out


def tree_float(raw: np.ndarray, codec: str = "ordered") -> np.ndarray:
    width = raw.shape[1]
    if codec == "raw_le":
        return np.ascontiguousarray(raw).view(f"<f{width}").ravel()
    positive = (raw[:, :1] & 0x80) != 0
    flipped = raw.copy()
    flipped[:, 0] ^= 0x80
    return np.ascontiguousarray(np.where(positive, flipped, ~raw)).view(f">f{width}").ravel().astype(f"<f{width}")


def tree_float_bytes(values: np.ndarray, width: int, codec: str = "ordered") -> np.ndarray:
    if codec == "raw_le":
        return np.ascontiguousarray(values.astype(f"<f{width}")).view(np.uint8).reshape(-1, width)
    raw = np.ascontiguousarray(values.astype(f">f{width}")).view(np.uint8).reshape(-1, width)
    flipped = raw.copy()
    flipped[:, 0] ^= 0x80
    return np.where((raw[:, :1] & 0x80) != 0, ~raw, flipped)


def decimal_groups(precision: int, scale: int) -> list[tuple[int, int]]:
    """(digits, bytes) of the groups of DECIMAL(precision, scale): whole part, then fraction."""
    whole, frac = precision - scale, scale
    out = [(whole % 9, GROUP_BYTES[whole % 9])] if whole % 9 else []
    out += [(9, 4)] * (whole // 9) + [(9, 4)] * (frac // 9)
    return out + ([(frac % 9, GROUP_BYTES[frac % 9])] if frac % 9 else [])


def decimal_width(precision: int, scale: int) -> int:
    return sum(b for _, b in decimal_groups(precision, scale))


def packed_mantissa(raw: np.ndarray, precision: int, scale: int) -> tuple[np.ndarray, np.ndarray]:
    """Magnitude as whole number (object dtype above 18 digits) and sign."""
    positive = (raw[:, 0] & 0x80) != 0
    data = np.where(positive[:, None], raw, ~raw)
    data[:, 0] = np.where(positive, raw[:, 0] & 0x7F, (~raw[:, 0]) & 0x7F)
    m = np.zeros(len(raw), np.int64 if precision <= 18 else object)
    at = 0
    for digits, width in decimal_groups(precision, scale):
        group = np.zeros(len(raw), np.int64)
        for k in range(width):
            group = group * 256 + data[:, at + k]
        m = m * 10**digits + group
        at += width
    return m, ~positive


def packed_double(raw: np.ndarray, precision: int, scale: int) -> np.ndarray:
    m, negative = packed_mantissa(raw, precision, scale)
    small = m if m.dtype != object else np.array([x if x < 1 << 53 else 0 for x in m], np.int64)
    exact = np.array([x < 1 << 53 for x in m], bool) if m.dtype == object else np.ones(len(m), bool)
    out = scaled(small, np.full(len(m), -scale), exact, lambda i: float(Decimal(int(m[i])).scaleb(-scale)))
    return np.where(negative, -out, out)


def packed_decimal(raw: np.ndarray, precision: int, scale: int, valid: np.ndarray) -> pa.Array:
    m, negative = packed_mantissa(raw, precision, scale)
    return decimal_array(np.where(valid, np.where(negative, -m, m), 0), precision, scale, valid)


def packed_bytes(values: np.ndarray, precision: int, scale: int) -> np.ndarray:
    """Rows of bytes of scaled whole numbers."""
    negative, rest = (values < 0).astype(bool), np.abs(values)
    groups = decimal_groups(precision, scale)
    out = np.zeros((len(values), sum(b for _, b in groups)), np.uint8)
    at = out.shape[1]
    for digits, width in reversed(groups):
        group, rest = rest % 10**digits, rest // 10**digits
        at -= width
        for k in range(width - 1, -1, -1):
            out[:, at + k] = group % 256
            group = group // 256
    out[:, 0] |= 0x80
    return np.where(negative[:, None], ~out, out)


def days_of(year: np.ndarray, month: np.ndarray, day: np.ndarray) -> np.ndarray:
    """Day number of a date (proleptic Gregorian), counted from 1970-01-01 through Julian day numbers."""
    a = (14 - month) // 12
    y, m = year + 4800 - a, month + 12 * a - 3
    return day + (153 * m + 2) // 5 + 365 * y + y // 4 - y // 100 + y // 400 - 32_045 - JULIAN_1970


def packed_date(raw: np.ndarray) -> np.ndarray:
    v = ((raw[:, 0].astype(np.int64) ^ 0x80) << 16) | (raw[:, 1].astype(np.int64) << 8) | raw[:, 2]
    return days_of(v >> 9, (v >> 5) & 15, v & 31).astype(np.int32)


def packed_date_bytes(days: np.ndarray) -> np.ndarray:
    d = days.astype("datetime64[D]")
    month = d.astype("datetime64[M]").astype(np.int64)
    year, mon = 1970 + month // 12, month % 12 + 1
    day = (d - d.astype("datetime64[M]")).astype(np.int64) + 1
    v = (year << 9) | (mon << 5) | day
    out = np.column_stack([(v >> 16) & 255, (v >> 8) & 255, v & 255]).astype(np.uint8)
    out[:, 0] ^= 0x80
    return out


def column_values(column: pa.Array, kind: str) -> np.ndarray:
    """Numpy values of a fixed-width column for encoding; nulls give 0."""
    if kind == "bool":
        return column.cast(pa.bool_()).fill_null(False).to_numpy(zero_copy_only=False)
    if kind == "date":
        return column.cast(pa.date32()).cast(pa.int32()).fill_null(0).to_numpy(zero_copy_only=False)
    if kind == "timestamp":
        return column.cast(pa.timestamp("us", column.type.tz if pa.types.is_timestamp(column.type) else None)).cast(pa.int64()).fill_null(0).to_numpy(zero_copy_only=False)
    to = {"int2": pa.int16(), "int4": pa.int32(), "int8": pa.int64(), "float4": pa.float32(), "float8": pa.float64()}[kind]
    return column.cast(to).fill_null(0).to_numpy(zero_copy_only=False)


def text_spans(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Flat bytes, starts and lengths of a string or binary column; nulls have length 0."""
    column = column.cast(pa.large_binary() if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else pa.large_string())
    buffers = column.buffers()
    offsets = np.frombuffer(buffers[1], np.int64)[column.offset : column.offset + len(column) + 1]
    flat = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None and buffers[2].size else np.zeros(1, np.uint8)
    return flat, offsets[:-1].copy(), np.where(np.asarray(column.is_valid()), np.diff(offsets), 0)
