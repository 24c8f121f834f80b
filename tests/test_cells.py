"""Database files of SQLite 3, written by its own library: what the reader gives is what a SELECT gives."""

import random
import sqlite3

import pytest

from pagelift import scan
from pagelift.formats import cell
from pagelift.plans import pages as plan
from pagelift.sources.paged import declared_schema, file_layout, tables_of, tree_pages

SPEC = "k:int8!,a:int8,b:float8,c:text,d:binary,e:bool"


def filled(path, page_size=1024, rows=3000, seed=1):
    """A table with rows of all sizes, some updated, some deleted, and a column that came later; beside other tables."""
    rng = random.Random(seed)
    db = sqlite3.connect(path)
    db.execute(f"PRAGMA page_size = {page_size}")
    db.execute("CREATE TABLE other (x TEXT)")
    db.execute("CREATE TABLE t (k INTEGER PRIMARY KEY, a INTEGER, b REAL, c TEXT, d BLOB)")
    db.execute("CREATE INDEX by_a ON t (a)")
    for i in range(rows):
        whole = rng.choice([None, 0, 1, -1, 127, -128, 32767, -8388608, 2**31 - 1, -(2**47), 2**63 - 1, -(2**63)])
        size = rng.choice([0, 1, 5, 40, 200]) if i % 50 else rng.choice([900, 1100, 5000, 40000])
        db.execute("INSERT INTO t VALUES (?, ?, ?, ?, ?)", (i * 3, whole, rng.choice([None, 1.5, -2.0, 1e300, 7.0]), rng.choice([None, "é" * size, "x" * size]), bytes(size % 300) if i % 7 else None))
        if i % 3 == 0:
            db.execute("INSERT INTO other VALUES (?)", ("y" * 60,))
    db.execute("ALTER TABLE t ADD COLUMN e BOOLEAN")
    db.execute("UPDATE t SET e = k % 2, c = 'changed' WHERE k % 13 = 0")
    db.execute("DELETE FROM t WHERE k % 11 = 0")
    db.commit()
    want = db.execute("SELECT k, a, b, c, d, e FROM t").fetchall()
    db.close()
    return [(*r[:5], None if r[5] is None else bool(r[5])) for r in want]


@pytest.mark.parametrize("page_size", [512, 1024, 4096, 65536])
def test_rows_are_those_of_a_select(spark, tmp_path, page_size):
    path = str(tmp_path / "a.db")
    want = sorted(filled(path, page_size, 1500), key=lambda r: r[0])
    for how in ({}, {"pages_per_read": 1, "split_bytes": page_size * 3, "max_rows": 7}):
        df = scan.scan(spark, "pagecell", path, table="t", columns_spec=SPEC, pk="k", on_overflow="resolve", **how)
        got = sorted((tuple(bytes(v) if isinstance(v, bytearray) else v for v in r) for r in df.collect()), key=lambda r: r[0])
        assert got == want
    some = scan.scan(spark, "pagecell", path, columns=["c", "k"], table="t", columns_spec=SPEC, pk="k", on_overflow="resolve")
    assert sorted(map(tuple, some.collect()), key=lambda r: r[1]) == [(r[3], r[0]) for r in want]
    with pytest.raises(Exception, match="overflow"):
        scan.scan(spark, "pagecell", path, table="t", columns_spec=SPEC, pk="k").collect()


def test_only_the_tables_leaves_are_read(spark, tmp_path):
    path = str(tmp_path / "a.db")
    filled(path)
    lay = file_layout(path)
    t, other = (set(tree_pages(path, x, lay).tolist()) for x in ("t", "other"))
    assert t and other and not t & other and 1 not in t
    with sqlite3.connect(path) as db:
        assert {name: root for name, root in db.execute("SELECT name, rootpage FROM sqlite_master WHERE type = 'table'")} == {k: v[0] for k, v in tables_of(path, lay).items()}
    segment = plan.list_segments(path)[0]
    with open(path, "r+b") as f:  # pages of the other table become garbage
        for number in other:
            f.seek((number - 1) * lay.page)
            f.write(b"\xff" * lay.page)
    assert segment.pages and scan.scan(spark, "pagecell", path, table="t", columns_spec=SPEC, pk="k", on_overflow="resolve").count() == len(filled(str(tmp_path / "b.db")))


def test_row_numbers_prune_leaves(spark, tmp_path):
    """Interior pages tell which leaves hold a range; others become garbage and are not read."""
    path = str(tmp_path / "a.db")
    want = filled(path, 512, 4000)
    lay = file_layout(path)
    every = tree_pages(path, "t", lay)
    for low, high in ((100, 400), (None, 50), (11_900, None), (5, 5), (50_000, None), (None, -1)):
        some = tree_pages(path, "t", lay, low, high)
        assert set(some.tolist()) <= set(every.tolist()) and len(some) < len(every) / 4
        where = " AND ".join([f"k >= {low}"] * (low is not None) + [f"k <= {high}"] * (high is not None))
        df = scan.scan(spark, "pagecell", path, table="t", columns_spec=SPEC, pk="k", on_overflow="resolve", range=f"k:int8:{'' if low is None else low}:{'' if high is None else high}", where=where)
        assert sorted(r.k for r in df.collect()) == sorted(r[0] for r in want if (low is None or r[0] >= low) and (high is None or r[0] <= high))
    pushed = scan.scan(spark, "pagecell", path, columns=["k"], table="t", columns_spec=SPEC, pk="k", pushdown=True, on_overflow="resolve")
    kept = set(tree_pages(path, "t", lay, 300, 310).tolist())
    with open(path, "r+b") as f:
        for number in set(every.tolist()) - kept:
            f.seek((number - 1) * lay.page)
            f.write(b"\xff" * lay.page)
    assert sorted(r.k for r in pushed.where("k >= 300 AND k <= 310").collect()) == sorted(r[0] for r in want if 300 <= r[0] <= 310)


def test_schemas_come_from_definitions(spark, tmp_path):
    got = declared_schema('CREATE TABLE "t" (id INTEGER PRIMARY KEY, name VARCHAR(20) NOT NULL, price DOUBLE PRECISION, ok BOOLEAN, at DATE, raw BLOB)')
    assert [(c.name, c.kind) for c in got.columns] == [("id", "int8"), ("name", "text"), ("price", "float8"), ("ok", "bool"), ("at", "date"), ("raw", "binary")]
    assert got.key == ("id",) and not got["name"].nullable and got["price"].nullable
    path = str(tmp_path / "a.db")
    filled(path, rows=50)
    with pytest.raises(Exception, match="no table"):
        scan.scan(spark, "pagecell", path, table="nothing", columns_spec=SPEC).count()


def test_what_is_no_such_file_is_refused(tmp_path):
    with pytest.raises(cell.PageError):
        cell.layout(b"x" * 200)
    path = str(tmp_path / "w.db")
    db = sqlite3.connect(path)
    db.execute("PRAGMA journal_mode = WAL")
    db.execute("CREATE TABLE t (a INTEGER)")
    db.commit()
    with pytest.raises(cell.PageError, match="write-ahead"):
        file_layout(path)
    db.close()
