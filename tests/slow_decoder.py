"""Independent decoders of both page formats, one row at a time with struct: the brute force that the engine is held against."""

import struct
from datetime import date, datetime, timedelta
from decimal import Decimal

SIZES = {"bool": 1, "int2": 2, "int4": 4, "int8": 8, "float4": 4, "float8": 8, "date": 4, "timestamp": 8}
CODES = {"bool": "?", "int2": "h", "int4": "i", "int8": "q", "float4": "f", "float8": "d", "date": "i", "timestamp": "q"}


def numeric(raw):
    (head,) = struct.unpack_from("<H", raw)
    if head & 0xC000 == 0xC000:
        return float("nan") if head & 0x3000 == 0 else float("inf") if head & 0x3000 == 0x1000 else float("-inf")
    if head & 0x8000:
        negative, weight, at = bool(head & 0x2000), (head & 0x3F) - (64 if head & 0x40 else 0), 2
    else:
        negative, (weight,), at = bool(head & 0x4000), struct.unpack_from("<h", raw, 2), 4
    total = Decimal(0)
    for k in range((len(raw) - at) // 2):
        total += Decimal(struct.unpack_from("<H", raw, at + 2 * k)[0]) * Decimal(10) ** (4 * (weight - k))
    return float(-total if negative else total)


def heap_rows(data, columns, policy="delete_only"):
    """columns: (name, kind, nullable) in order; rows as tuples."""
    out = []
    for base in range(0, len(data), 8192):
        page = data[base : base + 8192]
        (lower,) = struct.unpack_from("<H", page, 12)
        for p in range(24, lower, 4):
            (word,) = struct.unpack_from("<I", page, p)
            at, state, size = word & 0x7FFF, (word >> 15) & 3, word >> 17
            if state != 1 or not size:
                continue
            (xmax,), (natts,), (mask,), hoff = struct.unpack_from("<I", page, at + 4), struct.unpack_from("<H", page, at + 18), struct.unpack_from("<H", page, at + 20), page[at + 22]
            if policy != "none" and xmax and not mask & 0x0800 and not mask & 0x0080:
                continue
            if policy == "insert_hint" and mask & 0x0200:
                continue
            cur, row = at + hoff, []
            for i, (_, kind, *_) in enumerate(columns):
                if i >= (natts & 0x7FF) or (mask & 1 and not page[at + 23 + i // 8] >> (i % 8) & 1):
                    row.append(None)
                    continue
                if kind in SIZES:
                    cur += -cur % SIZES[kind]
                    (v,) = struct.unpack_from("<" + CODES[kind], page, cur)
                    cur += SIZES[kind]
                    row.append(date(2000, 1, 1) + timedelta(v) if kind == "date" else datetime(2000, 1, 1) + timedelta(microseconds=v) if kind == "timestamp" else v)
                    continue
                if page[cur] == 0:
                    cur += -cur % 4
                if page[cur] & 1:
                    size, head = page[cur] >> 1, 1
                else:
                    size, head = struct.unpack_from("<I", page, cur)[0] >> 2, 4
                raw = bytes(page[cur + head : cur + size])
                cur += size
                row.append(numeric(raw) if kind == "numeric" else raw if kind == "binary" else raw.decode().rstrip(" ") if kind == "bpchar" else raw.decode())
            out.append(tuple(row))
    return out


def packed(raw, precision, scale):
    negative = not raw[0] & 0x80
    raw = bytes([raw[0] ^ 0x80]) + raw[1:]
    if negative:
        raw = bytes(255 - b for b in raw)
    sizes, whole, digits, at = [0, 1, 1, 2, 2, 3, 3, 4, 4, 4], precision - scale, "", 0
    groups = ([whole % 9] if whole % 9 else []) + [9] * (whole // 9) + [9] * (scale // 9) + ([scale % 9] if scale % 9 else [])
    for g in groups:
        digits += str(int.from_bytes(raw[at : at + sizes[g]], "big")).rjust(g, "0")
        at += sizes[g]
    v = float(Decimal(int(digits)).scaleb(-scale))
    return -v if negative else v


def tree_rows(data, columns, index_id=40, prefix="declared"):
    """columns in physical order: (name, kind, nullable, max_len, precision, scale, width)."""
    out = []
    for base in range(0, len(data), 16384):
        page = data[base : base + 16384]
        if page[24:26] != b"\x45\xbf" or page[64:66] != b"\0\0" or int.from_bytes(page[66:74], "big") != index_id:
            continue
        at = 99
        while True:
            (step,) = struct.unpack_from(">h", page, at - 2)
            at += step
            if not step or at == 112:
                break
            if page[at - 5] & 0x20 or page[at - 3] & 7:
                continue
            nullable = [c for c in columns if c[2]]
            lens, cur, row, k = at - 6 - (len(nullable) + 7) // 8, at, [], 0
            for _, kind, null_ok, max_len, precision, scale, width in columns:
                if null_ok:
                    gone = page[at - 6 - k // 8] >> (k % 8) & 1
                    k += 1
                    if gone:
                        row.append(None)
                        continue
                if kind == "skip":
                    cur += width
                    continue
                if kind in ("bpchar", "varchar", "text", "binary"):
                    size = page[lens]
                    lens -= 1
                    if not 0 < max_len <= 255 and (prefix == "declared" or size & 0x80):
                        size = (size & 0x3F) << 8 | page[lens]
                        lens -= 1
                    raw = bytes(page[cur : cur + size])
                    cur += size
                    row.append(raw if kind == "binary" else raw.decode().rstrip(" ") if kind == "bpchar" else raw.decode())
                    continue
                if kind == "numeric":
                    size = sum([0, 1, 1, 2, 2, 3, 3, 4, 4, 4][g] for g in ((precision - scale) % 9, scale % 9)) + 4 * ((precision - scale) // 9 + scale // 9)
                    row.append(packed(page[cur : cur + size], precision, scale))
                    cur += size
                    continue
                size = 3 if kind == "date" else SIZES[kind]
                raw = page[cur : cur + size]
                cur += size
                if kind in ("float4", "float8"):
                    raw = bytes([raw[0] ^ 0x80]) + raw[1:] if raw[0] & 0x80 else bytes(255 - b for b in raw)
                    row.append(struct.unpack(">" + CODES[kind], raw)[0])
                    continue
                v = int.from_bytes(bytes([raw[0] ^ 0x80]) + raw[1:], "big", signed=kind != "date")
                row.append(date(v >> 9, v >> 5 & 15, v & 31) if kind == "date" else datetime(1970, 1, 1) + timedelta(microseconds=v) if kind == "timestamp" else bool(v) if kind == "bool" else v)
            out.append(tuple(row))
    return out
