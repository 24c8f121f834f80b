"""Golden bytes, random tables against the slow decoders, visibility, pruning, and broken files."""

import math
from datetime import date, datetime, timedelta
from decimal import Context, Decimal

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from slow_decoder import heap_rows, tree_rows

from pagelift.formats import brin, codec, heap, tree
from pagelift.formats.heap import PageError
from pagelift.schema import StorageColumn, StorageSchema

VALUES = {
    "bool": st.booleans(),
    "int2": st.integers(-(2**15), 2**15 - 1),
    "int4": st.integers(-(2**31), 2**31 - 1),
    "int8": st.integers(-(2**63), 2**63 - 1),
    "float4": st.floats(width=32, allow_nan=False),
    "float8": st.floats(allow_nan=False),
    "date": st.dates(date(1, 1, 1), date(9999, 12, 31)),
    "timestamp": st.datetimes(datetime(1600, 1, 1), datetime(2400, 1, 1)),
    "numeric": st.integers(-(10**12), 10**12).map(lambda x: x / 100),
    "bpchar": st.text(st.characters(codec="utf-8", exclude_characters="\x00"), max_size=10).map(lambda s: s.rstrip(" ")),
    "varchar": st.text(st.characters(codec="utf-8"), max_size=60),
    "text": st.one_of(st.text(st.characters(codec="utf-8"), max_size=40), st.integers(120, 400).map(lambda n: "x" * n)),
    "binary": st.binary(max_size=140),
}
SUFFIX = {"numeric": "(15,2)", "bpchar": "(10)", "varchar": "(250)"}


@st.composite
def tables(draw):
    kinds = draw(st.lists(st.sampled_from(sorted(VALUES)), min_size=1, max_size=9))
    nulls = [draw(st.booleans()) for _ in kinds]
    n = draw(st.integers(1, 60))
    spec = ",".join(f"c{i}:{k}{SUFFIX.get(k, '')}{'' if ok else '!'}" for i, (k, ok) in enumerate(zip(kinds, nulls)))
    schema = StorageSchema.parse(spec)
    cols = [draw(st.lists(st.one_of(st.none(), VALUES[k]) if ok else VALUES[k], min_size=n, max_size=n)) for k, ok in zip(kinds, nulls)]
    return schema, pa.RecordBatch.from_arrays([pa.array(v, c.arrow_type()) for v, c in zip(cols, schema.columns)], names=schema.names), list(zip(*cols))


def same(a, b):
    return len(a) == len(b) and all(x == y or (isinstance(x, float) and isinstance(y, float) and (x == pytest.approx(y, rel=1e-15) or math.isnan(x) and math.isnan(y))) for r, s in zip(a, b) for x, y in zip(r, s))


def rows_of(batch, names):
    return list(zip(*(batch.column(n).to_pylist() for n in names))) if names else []


@settings(max_examples=60, deadline=None)
@given(tables(), st.booleans())
def test_heap_round_trip_and_slow_decoder(made, long_numeric):
    schema, batch, rows = made
    pages = heap.encode(batch, schema, long_numeric=long_numeric)
    slow = heap_rows(pages.tobytes(), [(c.name, c.kind) for c in schema.columns])
    assert same(slow, rows) and same(rows_of(heap.decode(pages, schema), schema.names), rows)
    some = schema.names[::-2]
    assert same(rows_of(heap.decode(pages, schema, some), some), [tuple(r[schema.names.index(n)] for n in some) for r in rows])


@settings(max_examples=60, deadline=None)
@given(tables(), st.sampled_from(["declared", "adaptive"]))
def test_tree_round_trip_and_slow_decoder(made, prefix):
    schema, batch, rows = made
    pages = np.vstack([tree.file_start(40), tree.encode(batch, schema, prefix=prefix), tree.decoy(9, 41)])
    order = [(c.name, c.kind, c.nullable, c.max_len, c.precision, c.scale, c.width) for c in schema.physical()]
    assert same(tree_rows(pages.tobytes(), order, prefix=prefix), rows)
    assert same(rows_of(tree.decode(pages, schema, index_id=40, prefix=prefix), schema.names), rows)


def test_golden_values():
    assert codec.EPOCH_MICROS == 10_957 * 86_400 * 10**6
    assert tree.INDEX_PAGE == 0x45BF and (tree.FIRST, tree.LAST) == (99, 112) and brin.MAGIC == 0xA8109CFA
    assert brin.CAPACITY == (8184 - 24) // 6 == 1360
    ints = codec.tree_int_bytes(np.array([-(2**31), 2**31 - 1]), 4)
    assert ints.tobytes().hex() == "00000000ffffffff"
    assert codec.days_of(np.array([1970, 2000]), np.array([1, 1]), np.array([1, 1])).tolist() == [0, 10_957]
    assert codec.GROUP_BYTES == [0, 1, 1, 2, 2, 3, 3, 4, 4, 4] and codec.decimal_width(15, 2) == 7
    s = StorageSchema.parse("a:text")
    for size, short in ((0, True), (126, True), (127, False), (128, False)):
        pages = heap.encode(pa.RecordBatch.from_arrays([pa.array(["x" * size])], names=["a"]), s)
        t = heap.tuples(pages)
        first = int(t.flat[t.data[0]])
        assert (first & 1 == 1) == short and heap.decode(pages, s).column("a").to_pylist() == ["x" * size]
        assert first >> 1 == size + 1 if short else int.from_bytes(t.flat[t.data[0] : t.data[0] + 4].tobytes(), "little") >> 2 == size + 4


@settings(max_examples=80, deadline=None)
@given(st.integers(1, 38).flatmap(lambda p: st.tuples(st.just(p), st.integers(0, p))), st.data())
def test_decimals_of_any_precision(size, data):
    """Both formats give exact decimals back, also beyond 64 bits, and between them nulls."""
    precision, scale = size
    whole = st.integers(-(10**precision) + 1, 10**precision - 1)
    values = data.draw(st.lists(st.one_of(st.none(), whole), min_size=1, max_size=20))
    rows = [None if v is None else Decimal(v).scaleb(-scale, Context(prec=50)) for v in values]
    schema = StorageSchema.parse(f"n:numeric({precision},{scale})")
    batch = pa.RecordBatch.from_arrays([pa.array(rows, pa.decimal128(precision, scale))], names=["n"])
    for long_numeric in (False, True) if scale < 64 else (True,):
        assert heap.decode(heap.encode(batch, schema, long_numeric=long_numeric), schema, numeric_as="decimal").column("n").to_pylist() == rows
    tree_schema = StorageSchema.parse(f"k:int8!,n:numeric({precision},{scale})", ("k",))
    keyed = pa.RecordBatch.from_arrays([pa.array(range(len(rows)), pa.int64()), batch.column(0)], names=["k", "n"])
    pages = np.vstack([tree.file_start(40), tree.encode(keyed, tree_schema)])
    assert tree.decode(pages, tree_schema, index_id=40, numeric_as="decimal").column("n").to_pylist() == rows


def test_large_doubles_as_numerics():
    schema = StorageSchema.parse("n:numeric(30,2)")
    batch = pa.RecordBatch.from_arrays([pa.array([1e20, -3.5e27, 0.25, 92233720368547758.0, None])], names=["n"])
    got = heap.decode(heap.encode(batch, schema), schema, numeric_as="decimal").column("n").to_pylist()
    assert got == [Decimal(10) ** 20, -Decimal(int(3.5e27)), Decimal("0.25"), Decimal(92233720368547758.0), None]
    assert heap.decode(heap.encode(batch, schema), schema).column("n").to_pylist() == [1e20, -3.5e27, 0.25, 92233720368547758.0, None]


def test_scaling_is_exact():
    rng = np.random.default_rng(0)
    cents = rng.integers(-(10**11), 10**11, 50_000)
    v = cents / 100
    s = StorageSchema.parse("a:numeric(15,2)")
    b = pa.RecordBatch.from_arrays([pa.array(v)], names=["a"])
    assert np.array_equal(heap.decode(heap.encode(b, s), s).column("a").to_numpy(), v)
    assert np.array_equal(tree.decode(tree.encode(b, s), s).column("a").to_numpy(), v)
    d = heap.decode(heap.encode(b, s), s, numeric_as="decimal").column("a")
    assert [int(x * 100) for x in d[:50].to_pylist()] == cents[:50].tolist()
    odd = pa.RecordBatch.from_arrays([pa.array([float("nan"), float("inf"), float("-inf"), 0.0])], names=["a"])
    got = heap.decode(heap.encode(odd, s), s).column("a").to_pylist()
    assert math.isnan(got[0]) and got[1:] == [float("inf"), float("-inf"), 0.0]


@pytest.mark.parametrize("xmax", [0, 5])
@pytest.mark.parametrize("invalid", [0, heap.DELETE_INVALID])
@pytest.mark.parametrize("lock", [0, heap.LOCK_ONLY])
def test_visibility_table(xmax, invalid, lock):
    mask = np.array([invalid | lock])
    assert heap.visible(np.array([xmax]), mask)[0] == (xmax == 0 or bool(invalid) or bool(lock))
    assert heap.visible(np.array([xmax]), mask, "none")[0]
    assert not heap.visible(np.array([xmax]), mask | heap.INSERT_INVALID, "insert_hint")[0]


def test_missing_attributes_are_null():
    old, new = StorageSchema.parse("a:int4,b:text"), StorageSchema.parse("a:int4,b:text,c:int8,d:text")
    pages = heap.encode(pa.RecordBatch.from_arrays([pa.array([1, 2], pa.int32()), pa.array(["x", None])], names=["a", "b"]), old)
    assert rows_of(heap.decode(pages, new), new.names) == [(1, "x", None, None), (2, None, None, None)]


def test_broken_pages():
    s = StorageSchema.parse("a:int4,t:text")
    b = pa.RecordBatch.from_arrays([pa.array(range(100), pa.int32()), pa.array(["t"] * 100)], names=["a", "t"])
    pages = heap.encode(b, s)
    assert heap.decode(np.zeros((2, heap.PAGE), np.uint8), s).num_rows == 0
    bad = pages.copy()
    bad[0, 12:14] = 255
    with pytest.raises(PageError):
        heap.decode(bad, s)
    leaf = tree.encode(b, s)
    loose = leaf.copy()
    loose[0, 42] = 0
    with pytest.raises(PageError):
        tree.decode(loose, s)
    ring = leaf.copy()
    page, at = tree.record_origins(leaf, np.array([0]))
    back = (int(at[0]) - int(at[5])) & 0xFFFF
    ring[0, at[5] - 2], ring[0, at[5] - 1] = back >> 8, back & 255
    with pytest.raises(PageError):
        tree.decode(ring, s)
    with pytest.raises(PageError):
        brin.meta(bytes(8192))
    with pytest.raises(PageError):
        heap.encode(pa.RecordBatch.from_arrays([pa.array([1], pa.int32()), pa.array(["x" * 9000])], names=["a", "t"]), s)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.one_of(st.none(), st.tuples(st.integers(-50, 50), st.integers(0, 30), st.booleans(), st.booleans())), min_size=1, max_size=40), st.one_of(st.none(), st.integers(-60, 60)), st.one_of(st.none(), st.integers(-60, 60)), st.sampled_from(["paired", "bitmap"]))
def test_index_round_trip_and_safe_pruning(made, low, high, mode):
    column = StorageColumn("k", "int8")
    summaries = [None if m is None else (m[0], m[0] + m[1], m[2], m[3]) for m in made]
    ranges = brin.load(brin.write(summaries, column, 4, mode), column, 4 * len(made), mode)
    kept = brin.keep(ranges, brin.RangePredicate("k", low, high))
    for s, k, usable in zip(summaries, kept, ranges.usable):
        assert usable == (s is not None and not s[2])
        may = s is None or s[2] or ((low is None or s[1] >= low) and (high is None or s[0] <= high))
        assert k == may


def test_large_index_uses_several_map_pages():
    column = StorageColumn("k", "timestamp")
    base = datetime(2024, 1, 1)
    at = lambda i: brin.comparable(base + timedelta(hours=i), "timestamp")
    ranges = brin.load(brin.write([(at(i), at(i + 1), False, False) for i in range(4000)], column, 1), column, 4000)
    assert len(ranges) == 4000 and ranges.usable.all() and ranges.low[3999] == at(3999)
    p = brin.RangePredicate.parse("k:timestamp:2024-01-02 00:00:00:2024-01-02 05:30:00")
    assert brin.keep(ranges, p).sum() == 7


def test_schema_texts():
    s = StorageSchema.parse("a:int8!, b:numeric(15,2), c:bpchar(10), raw:raw(13)")
    assert StorageSchema.from_json(s.to_json()) == s and s.names == ["a", "b", "c"]
    with pytest.raises(ValueError):
        StorageSchema.parse("a:box")
    tree_order = [c.name for c in StorageSchema.parse("x:int4,k:int8", ("k",)).physical()]
    assert tree_order == ["k", "_hidden", "x"]
