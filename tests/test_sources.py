"""The data sources in a session: metamorphic scans, plans, overflow, snapshots, streams and synthesis."""

import json
import os
import shutil

import pytest
from pyspark.sql import functions as F

from pagelift import extract, measure, scan, wire, workloads
from pagelift.operators import ranges
from pagelift.plans import pages as plan
from pagelift.schema import StorageSchema
from pagelift.sources.paged import HeapReader
from pagelift.synth import coder, deploy, loop
from pagelift.workloads import fixtures as fx
from pagelift.workloads.synthesis import job


@pytest.fixture(scope="module")
def orders(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/orders.parquet").cache()


@pytest.fixture
def at(tmp_path):
    return str(tmp_path / "relation")


def rows(df):
    return sorted(map(str, df.collect()))


@pytest.mark.parametrize("kind", ["pageheap", "pagetree"])
def test_layout_and_reading_do_not_change_rows(spark, orders, at, kind):
    pk = ("o_orderkey",) if kind == "pagetree" else ()
    want = rows(orders)
    for k, (write, read) in enumerate([({}, {}), ({"fill_factor": 60}, {"split_bytes": 1 << 16}), ({"segment_pages": 2}, {"pages_per_read": 1, "max_rows": 7}), ({}, {"columns": orders.columns[::-1]})]):
        scan.write(orders, kind, f"{at}{k}", fx.SPECS["orders"], pk=pk, **write)
        got = scan.scan(spark, kind, f"{at}{k}", **read)
        assert rows(got.select(*orders.columns)) == want


def test_scan_needs_no_shuffle_and_keeps_the_filter(spark, orders, at):
    scan.write(orders, "pageheap", at, fx.SPECS["orders"], cluster_by=("o_orderkey",), partitions=1)
    index = scan.build_index(spark, at, "o_orderkey", 2)
    df = scan.scan(spark, "pageheap", at, index_path=index, index_column="o_orderkey", pushdown=True).where("o_orderkey < 300")
    text = df._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in text and "Filter" in text and "BatchEvalPython" not in text
    assert df.count() == orders.where("o_orderkey < 300").count()
    whole = scan.metrics(at, index_path=index, range="o_orderkey:int8::")
    part = scan.metrics(at, index_path=index, range="o_orderkey:int8:100:300")
    none = scan.metrics(at, index_path=index, range="o_orderkey:int8:-9:-3")
    assert whole["pages_read"] == whole["pages_total"] > part["pages_read"] > none["pages_read"] == 0


def test_pruned_pages_are_not_opened(spark, orders, at):
    """Pages outside the kept runs are overwritten with garbage: the pruned scan never sees it."""
    scan.write(orders, "pageheap", at, fx.SPECS["orders"], cluster_by=("o_orderkey",), partitions=1)
    index = scan.build_index(spark, at, "o_orderkey", 1)
    (segment,) = plan.list_segments(at)
    with open(segment.path, "r+b") as f:
        f.seek(8192 * (segment.pages - 1))
        f.write(b"\xff" * 8192)
    options = {"index_path": index, "range": "o_orderkey:int8::50"}
    assert scan.scan(spark, "pageheap", at, **options).where("o_orderkey <= 50").count() == orders.where("o_orderkey <= 50").count()
    with pytest.raises(Exception):
        scan.scan(spark, "pageheap", at).count()


def test_tree_files_outside_the_keys_are_not_read(spark, orders, at):
    scan.write(orders, "pagetree", at, fx.SPECS["orders"], pk=("o_orderkey",), partitions=6)
    top = orders.count()
    m = scan.metrics(at, "pagetree", range=f"o_orderkey:int8::{top // 10}")
    assert 0 < m["pages_read"] < m["pages_total"] / 2
    for s in plan.list_segments(at)[3:]:
        with open(s.path, "r+b") as f:
            f.write(b"\xff" * s.size)
    got = scan.scan(spark, "pagetree", at, pushdown=True).where(f"o_orderkey <= {top // 10}")
    assert rows(got) == rows(orders.where(f"o_orderkey <= {top // 10}"))
    for k, (low, high) in enumerate((f["keys"] for f in plan.manifest(at)["files"])):
        assert low <= high and (k == 0 or low > before)
        before = high


def test_direct_scan_reads_page_files_only(spark, sf_dir, tmp_path):
    copy = tmp_path / "tables"
    copy.mkdir()
    shutil.copy(f"{sf_dir}/nation.parquet", copy)
    scan.write(spark.read.parquet(f"{copy}/nation.parquet"), "pageheap", str(tmp_path / "n"), fx.SPECS["nation"])
    shutil.rmtree(copy)
    assert scan.scan(spark, "pageheap", str(tmp_path / "n")).count() == 25


@pytest.mark.parametrize("kind", ["pageheap", "pagetree"])
def test_overflow_values(spark, at, kind):
    df = spark.range(30).select(F.col("id").alias("k"), F.expr("repeat('é', int(id) * 300)").alias("t"), F.expr("CASE WHEN id % 5 = 0 THEN NULL ELSE cast(repeat('b', int(id) * 200) AS binary) END").alias("b"))
    scan.write(df, kind, at, "k:int8!,t:text,b:binary", pk=("k",) if kind == "pagetree" else (), overflow=True)
    assert rows(scan.scan(spark, kind, at, on_overflow="resolve")) == rows(df)
    assert scan.scan(spark, kind, at, on_overflow="null").where("t IS NULL").count() > 0
    with pytest.raises(Exception, match="overflow"):
        scan.scan(spark, kind, at).count()
    assert scan.scan(spark, kind, at, columns=["k"]).count() == 30


def test_snapshot_guard_and_truncation(spark, orders, at):
    scan.write(orders, "pageheap", at, fx.SPECS["orders"], partitions=1)
    (segment,) = plan.list_segments(at)
    df = scan.scan(spark, "pageheap", at)
    with open(segment.path, "ab") as f:
        f.write(bytes(8192))
    with pytest.raises(Exception, match="changed"):
        df.count()
    with open(segment.path, "ab") as f:
        f.write(b"x")
    with pytest.raises(Exception, match="whole page"):
        scan.scan(spark, "pageheap", at, snapshot="off").count()


def test_a_file_of_the_same_size_is_noticed(spark, orders, at):
    scan.write(orders, "pageheap", at, fx.SPECS["orders"], partitions=1)
    (segment,) = plan.list_segments(at)
    df = scan.scan(spark, "pageheap", at)
    df.count()
    with open(segment.path, "r+b") as f:
        raw = f.read()
        f.seek(0)
        f.write(raw)
    os.utime(segment.path, ns=(segment.changed + 10**9, segment.changed + 10**9))
    with pytest.raises(Exception, match="changed"):  # its pages were planned before
        df.count()
    assert scan.scan(spark, "pageheap", at).count() == orders.count()


@pytest.mark.parametrize("name", ["heap_numeric_wide", "tree_numeric_wide"])
def test_wide_numbers_of_larger_tables(spark, tmp_path, name):
    import duckdb

    keys = [1, 2, 8_999, 9_001, 15_000, 900_000, 9_000_001, 89_999_999, 90_000_000]
    spark.createDataFrame([(k,) for k in keys], "c_custkey long").coalesce(1).write.parquet(f"{tmp_path}/customer.parquet")
    got = workloads.queries()[name](spark, str(tmp_path)).collect()
    want = duckdb.sql(f"WITH customer AS (SELECT * FROM '{tmp_path}/customer.parquet/*.parquet') {workloads.oracle_sql()[name]}").fetchall()
    assert sorted(map(tuple, got)) == sorted(want) and len(got) == len(keys)


@pytest.mark.parametrize("kind", ["pageheap", "pagetree"])
def test_overflow_values_of_several_writes_and_relations(spark, tmp_path, kind):
    """Two appends and two relations whose values have the same partition and place in their writes."""
    pk, paths = ("k",) if kind == "pagetree" else (), []
    want = []
    for n in range(2):
        paths.append(str(tmp_path / f"r{n}"))
        for k in range(2):
            df = spark.createDataFrame([(10 * n + k, chr(97 + 2 * n + k) * 5000)], "k long, t string").coalesce(1)
            scan.write(df, kind, paths[-1], "k:int8!,t:text", mode="append", pk=pk, overflow=True)
            want.append((10 * n + k, chr(97 + 2 * n + k) * 5000))
    assert sorted(map(tuple, scan.scan(spark, kind, paths, on_overflow="resolve").collect())) == want
    assert sorted(map(tuple, scan.scan(spark, kind, paths[0], on_overflow="resolve").collect())) == want[:2]


def test_an_append_notices_another_one(spark, at):
    from pagelift.sources.paged import HeapWriter

    spec = {"path": at, "columns_spec": "k:int8!"}
    scan.write(spark.range(10).toDF("k"), "pageheap", at, "k:int8!")
    schema = StorageSchema.parse("k:int8!").spark()
    late = HeapWriter(schema, spec, False)
    scan.write(spark.range(10).toDF("k"), "pageheap", at, "k:int8!", mode="append")
    with pytest.raises(ValueError, match="another job"):
        late.commit([])
    assert scan.scan(spark, "pageheap", at).count() == 20


def test_an_index_knows_what_it_covers(spark, at):
    spec = "k:int8!"
    scan.write(spark.range(100).toDF("k").coalesce(1), "pageheap", at, spec)
    for form, name in (("file", "i"), ("table", "t")):
        scan.build_index(spark, at, "k", index_path=f"{at}/{name}", form=form)
    scan.write(spark.range(1000, 1100).toDF("k").coalesce(1), "pageheap", at, spec, mode="append")
    for name in ("i", "t"):
        assert scan.scan(spark, "pageheap", at, index_path=f"{at}/{name}", range="k:int8:1000:").where("k >= 1000").count() == 100
        assert scan.scan(spark, "pageheap", at, index_path=f"{at}/{name}", index_column="k", pushdown=True).where("k >= 1000").count() == 100
    scan.write(spark.range(5000, 5100).toDF("k").coalesce(1), "pageheap", at, spec)
    for name in ("i", "t"):
        assert scan.scan(spark, "pageheap", at, index_path=f"{at}/{name}", range="k:int8:5000:").where("k >= 5000").count() == 100


def test_a_job_and_the_driver_prune_alike(spark, at):
    """A table of summaries leaves the pages that an index file leaves, by range and by pushed filter."""
    spec = "k:int8!,t:timestamp,d:date,s:text,f:float8"
    df = spark.range(60_000).selectExpr("id AS k", "IF(id % 9 = 0 OR id DIV 3000 = 4, NULL, timestampadd(SECOND, id, TIMESTAMP_NTZ '2001-01-01 00:00:00')) AS t", "date_add(DATE'1999-12-01', int(id DIV 100)) AS d", "lpad(id, 6, '0') AS s", "id / 7 AS f").coalesce(1)
    scan.write(df, "pageheap", at, spec)
    pages = lambda **o: sum(r.count for r in HeapReader(StorageSchema.parse(spec).spark(), {k: str(v) for k, v in o.items()} | {"path": at}, StorageSchema.parse(spec), plan.manifest(at)).plan()[0])
    for column, text, kind in (("k", "1000:2000", "int8"), ("t", "2001-01-01 05:00:00:2001-01-01 06:00:00", "timestamp"), ("d", "2000-01-05:2000-02-01", "date"), ("s", "001000:002000", "text"), ("f", "100:", "float8")):
        one = scan.build_index(spark, at, column, 4, f"{at}/{column}-file", form="file")
        two = scan.build_index(spark, at, column, 4, f"{at}/{column}-table", form="table")
        bounds = f"{column}:{kind}:{text}"
        by_file = pages(index_path=one, range=bounds)
        predicate = scan.RangePredicate.parse(bounds)
        assert by_file == pages(index_path=two, range=bounds) == pages(runs=scan.runs_by_job(spark, at, two, predicate), range=bounds)
        assert 0 < by_file < pages()


def test_the_pruning_job_joins_nothing(spark, sf_dir):
    from pagelift.workloads import scans

    text = scans.prune_distributed(spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in text and "Exchange" not in text


def test_what_a_tree_cannot_hold_is_refused(spark, at):
    for value in ("double('NaN')", "double('Infinity')"):
        with pytest.raises(Exception, match="NaN or an infinity"):
            scan.write(spark.range(1).selectExpr("id AS k", f"{value} AS n"), "pagetree", at, "k:int8!,n:numeric(15,2)", pk=("k",))
    for kind in ("pageheap", "pagetree"):
        with pytest.raises(Exception, match="more than 5 digits"):
            scan.write(spark.range(1).selectExpr("id AS k", "1000.00BD AS n"), kind, at, "k:int8!,n:numeric(5,2)", pk=("k",) if kind == "pagetree" else ())


def test_a_stream_reads_rows_added_to_the_last_page(spark, tmp_path):
    from pagelift.streaming import tails

    path, at = str(tmp_path / "grows"), str(tmp_path / "at")
    for n in (10, 30, 30, 900, 901):
        whole = f"{path}-{n}"
        scan.write(spark.range(n).toDF("k").coalesce(1), "pageheap", whole, "k:int8!")
        if n == 10:
            scan.write(spark.range(n).toDF("k").coalesce(1), "pageheap", path, "k:int8!")
        else:
            tails.replace_files(whole, path)
        got = [r.k for r in tails.finish(tails.tail(spark, path), at=at).collect()]
        assert sorted(got) == list(range(n))


def test_segments_without_a_manifest_are_ordered_by_number(tmp_path, spark, orders):
    scan.write(orders, "pageheap", str(tmp_path / "w"), fx.SPECS["orders"], partitions=1, segment_pages=1)
    files = [s.path for s in plan.list_segments(str(tmp_path / "w"))]
    assert len(files) > 3
    for k, f in enumerate(files):
        shutil.copy(f, tmp_path / ("16384" + (f".{k}" if k else "")))
    df = scan.scan(spark, "pageheap", str(tmp_path / "16384"), columns_spec=fx.SPECS["orders"])
    assert rows(df) == rows(orders)
    assert [os.path.basename(s.path) for s in plan.list_segments(str(tmp_path / "16384"))][:3] == ["16384", "16384.1", "16384.2"]


def test_large_range_tables_are_pruned_by_a_job(spark):
    """Ten million ranges: only runs come back."""
    table = spark.range(10_000_000).select(F.col("id").alias("range_no"), F.lit(True).alias("usable"), (F.col("id") * 10).alias("vmin"), (F.col("id") * 10 + 9).alias("vmax"))
    runs = plan.prune_distributed(table, (F.col("vmax") >= 5000) & (F.col("vmin") <= 9000), 128).collect()
    assert [(r.first_page, r.n_pages) for r in runs] == [(500 * 128, 401 * 128)]


def test_range_and_asof_joins(spark):
    spans = spark.sql("SELECT id AS a, timestamp_seconds(id * 100) AS low, timestamp_seconds(id * 100 + 250) AS high FROM range(20)")
    points = spark.sql("SELECT id AS b, timestamp_seconds(id * 37) AS at FROM range(60)")
    got = {(r.a, r.b) for r in ranges.range_join(spans, points, "low", "high", "at", 90).collect()}
    assert got == {(a, b) for a in range(20) for b in range(60) if a * 100 <= b * 37 <= a * 100 + 250}
    left = spark.sql("SELECT id % 3 AS k, timestamp_seconds(id * 40000) AS at, id AS l FROM range(50)")
    right = spark.sql("SELECT id % 3 AS k, timestamp_seconds(id * 90000) AS at, id AS r FROM range(12)")
    got = {x.l: x.r for x in ranges.asof_join(left, right, "k", "at", ["r"]).collect()}
    assert got == {i: max((j for j in range(12) if j % 3 == i % 3 and j * 90000 <= i * 40000), default=None) for i in range(50)}


def test_protocol_rows_equal_direct_rows(spark, orders, tmp_path):
    scan.register(spark)
    wire.register(spark)
    schema = StorageSchema.parse(fx.SPECS["orders"])
    scan.write(orders, "pageheap", str(tmp_path / "h"), fx.SPECS["orders"])
    direct = scan.scan(spark, "pageheap", str(tmp_path / "h"))
    for text in (False, True):
        path = wire.encode_copy(orders, str(tmp_path / f"w{text}"), schema, text)
        got = spark.read.format("wiretext" if text else "wirebinary").option("path", path).option("columns_spec", fx.SPECS["orders"]).load()
        assert measure.exact_diff(direct, got).first() == (0, 0)
    one = list(extract.batches(str(tmp_path / "h"), "pageheap"))
    assert sum(b.num_rows for b in one) == orders.count()
    for consumer in ("pyarrow", "duckdb"):
        extract.etl(extract.batches(str(tmp_path / "h"), "pageheap"), consumer, str(tmp_path / f"{consumer}.parquet"))
        assert measure.exact_diff(direct, spark.read.parquet(str(tmp_path / f"{consumer}.parquet"))).first() == (0, 0)


@pytest.mark.parametrize("text", [False, True])
def test_a_client_holds_a_block_and_a_batch(spark, orders, tmp_path, monkeypatch, text):
    import tracemalloc

    spec, path = fx.SPECS["orders"], str(tmp_path / "w")
    wire.encode_copy(orders.crossJoin(spark.range(8)).drop("id").coalesce(1), path, StorageSchema.parse(spec), text)
    (name,) = [x for x in os.listdir(path) if x.endswith((".txt", ".bin"))]
    size, want = os.path.getsize(f"{path}/{name}"), [tuple(r.values()) for b in extract.row_batches(path, spec, text) for r in b.to_pylist()]
    assert len(want) == 8 * orders.count()
    for block in (5, 1 << 12):  # rows that span blocks, and blocks of many rows
        monkeypatch.setattr(wire, "BLOCK", block)
        got, times = [], {}
        for b in extract.row_batches(path, spec, text, rows=64, times=times):
            got += [tuple(r.values()) for r in b.to_pylist()]
        assert got == want and set(times) == {"receive", "convert"}
    tracemalloc.start()
    assert sum(b.num_rows for b in extract.row_batches(path, spec, text, rows=64)) == len(want)
    assert tracemalloc.get_traced_memory()[1] < size / 4
    tracemalloc.stop()
    with open(f"{path}/{name}", "r+b") as f:
        f.truncate(size - 1)
    with pytest.raises(ValueError, match="within a row"):
        list(extract.row_batches(path, spec, text))


def test_synthesis_loop(spark, sf_dir, tmp_path):
    scan.register(spark)
    j = job(spark, sf_dir, "orders", "pageheap")
    good = loop.run(spark, j)
    assert good.passed and good.attempts == 1 and good.diagnosis_calls == 0
    bad = loop.run(spark, j, loop.SynthConfig(coder=coder.FaultyCoder(("crash",) * 3)), n_max=2, checkpoint=str(tmp_path / "c.json"))
    assert not bad.passed and bad.attempts == 2 and bad.diagnosis_calls == 2 and os.path.exists(bad.checkpoint)
    state = json.loads((tmp_path / "c.json").read_text())
    assert len(state["feedback"]["diagnoses"]) == 2 and state["kinds"] == ["run", "run"]
    with pytest.raises(ValueError):
        deploy.deploy(bad)

    class Refusing:
        def __call__(self, *a):
            raise AssertionError("a resumed run writes no new specification")

    again = loop.run(spark, j, loop.SynthConfig(architect=Refusing(), coder=coder.TemplateCoder()), resume=str(tmp_path / "c.json"))
    assert again.passed and again.attempts == 1
    assert loop.escalate(["run", "run"]) and not loop.escalate(["run", "check"]) and loop.is_stuck(["a", "b", "a"]) and not loop.is_stuck(["a", "b"])


def test_checker_finds_each_kind_of_error(spark, sf_dir):
    scan.register(spark)
    from pagelift.synth.spec import architect

    j = job(spark, sf_dir, "events", "pageheap")
    spec = architect(j.struct, j.kind, j.kinds, j.key)
    tables = loop.tables_of(spark, j, spec, loop.SynthConfig())
    assert loop.verdict_on(spark, coder.TemplateCoder().generate(spec, coder.Feedback()), tables, "pageheap")[0].passed
    for fault, f in coder.FAULTS.items():
        if fault == "prose":
            continue
        source = coder.FaultyCoder((fault,)).generate(spec, coder.Feedback())
        verdict, _ = loop.verdict_on(spark, source, tables, "pageheap")
        assert not verdict.passed and verdict.kind in (f.kind, *(coder.SHOWN if f.kind in ("value", "null_count") else ())), fault


@pytest.mark.parametrize("kind", ["pageheap", "pagetree", "pagecell"])
def test_generated_readers_stand_alone(spark, sf_dir, kind):
    """No import of the package, no column of the table in the source; branches of types the table lacks are checked."""
    import ast

    scan.register(spark)
    j = job(spark, sf_dir, "nation", kind)
    r = loop.run(spark, j)
    assert r.passed and r.attempts == 1
    tree_ = ast.parse(r.source)
    imported = {a.name for n in ast.walk(tree_) if isinstance(n, ast.Import) for a in n.names} | {n.module for n in ast.walk(tree_) if isinstance(n, ast.ImportFrom)}
    assert imported == {"re", "numpy", "pyarrow"}
    assert "n_name" not in r.source and all(t in r.source for t in ("bool", "int2", "int4", "int8", "float4", "float8", "numeric", "date", "timestamp", "bpchar", "varchar", "text"))
    if kind == "pagecell":  # it has no epoch of its own; its scan is a query
        return
    # nation has no dates: only the table of all types shows a wrong epoch
    faulty = lambda: coder.FaultyCoder(("wrong_epoch",))
    assert loop.run(spark, j, loop.SynthConfig(coder=faulty(), all_types=False)).attempts == 1
    caught = loop.run(spark, j, loop.SynthConfig(coder=faulty()))
    assert caught.passed and caught.attempts == 2 and caught.errors == ["value"]
    path = fx.base(spark, sf_dir, "nation", kind)
    with pytest.raises(Exception, match="allow_generated"):
        scan.scan(spark, kind, path, reader=deploy.deploy(r)).collect()
    assert scan.scan(spark, kind, path, **deploy.options(r)).count() == 25


def test_roles_as_commands(spark, tmp_path):
    """Each role by a command of its own, from the command line; the diagnoser is asked when something is wrong."""
    import sys

    from pagelift.synth import __main__ as cli
    from pagelift.synth import templates
    from pagelift.synth.spec import CONSTANTS

    good, log = tmp_path / "good.txt", tmp_path / "log"
    good.write_text(templates.source("pageheap", CONSTANTS["pageheap"]))
    role = lambda name, body: f"{sys.executable} -c \"import sys, json; x = json.load(sys.stdin); open(r'{log}', 'a').write('{name} '); {body}\""
    code = role("coder", f"t = open(r'{good}').read(); print('Here you are.' if not x['feedback']['diagnoses'] else t)")
    arguments = ["--columns", "k:int8!,t:text,n:numeric(12,2)", "--kind", "pageheap", "--out", str(tmp_path / "reader.py"), "--rows", "20"]
    roles = ["--architect", role("architect", "print(json.dumps(x))"), "--coder", code, "--diagnoser", role("diagnoser", "print(json.dumps({'kind': 'prose', 'text': 'write code'}))")]
    assert cli.main([*arguments, *roles], spark) == 0
    assert log.read_text().split() == ["architect", "coder", "diagnoser", "coder"] and (tmp_path / "reader.py").read_text() == good.read_text()
    checkpoint = str(tmp_path / "c.json")
    assert cli.main([*arguments, "--coder", role("coder", "print('no')"), "--budget", "2", "--checkpoint", checkpoint], spark) == 1
    assert cli.main([*arguments, "--resume", checkpoint], spark) == 0


def test_long_values_in_a_row_are_read_at_once(spark, at):
    """Chains that follow each other take few reads; chains in any order give the same values."""
    from pagelift.formats import tree
    from pagelift.sources.paged import _Ahead

    df = spark.range(200).selectExpr("id AS k", "repeat(cast(id AS string), 9000) AS t").coalesce(1)
    scan.write(df, "pagetree", at, "k:int8!,t:text", pk=("k",), partitions=1, overflow=True)
    assert rows(scan.scan(spark, "pagetree", at, on_overflow="resolve")) == rows(df)
    (segment,) = plan.list_segments(at)
    calls = []

    class Counted:
        def __init__(self, f):
            self.f = f

        def seek(self, at):
            calls.append(at)
            self.f.seek(at)

        def read(self, n):
            return self.f.read(n)

    with open(segment.path, "rb") as f:
        pages = f.read()
        kinds = [int.from_bytes(pages[p * tree.PAGE + 24 : p * tree.PAGE + 26], "big") for p in range(len(pages) // tree.PAGE)]
        first = kinds.index(tree.LONG_VALUE)
        ahead, page = _Ahead(Counted(f), tree.PAGE), first
        for k in range(200):
            value = str(k).encode() * 9000
            assert tree.chained(ahead.read, page, len(value)) == value
            page += -(-len(value) // tree.PART)
        assert len(calls) <= 2 + (page - first) / _Ahead.MANY + 1
        back = _Ahead(f, tree.PAGE)
        for k in range(199, -1, -1):
            value = str(k).encode() * 9000
            page -= -(-len(value) // tree.PART)
            assert tree.chained(back.read, page, len(value)) == value


def test_extraction_reads_every_byte_once(spark, orders, tmp_path):
    for kind in ("pageheap", "pagetree"):
        at, spent = str(tmp_path / kind), {}
        scan.write(orders, kind, at, fx.SPECS["orders"], pk=("o_orderkey",) if kind == "pagetree" else ())
        assert sum(b.num_rows for b in extract.batches(at, kind, times=spent)) == orders.count()
        assert spent["bytes"] == sum(s.size for s in plan.list_segments(at))


def test_large_indexes_become_tables_by_themselves(spark, at, monkeypatch):
    scan.write(spark.range(20_000).toDF("k").coalesce(1), "pageheap", at, "k:int8!")
    assert os.path.isfile(scan.build_index(spark, at, "k", 1, f"{at}/small"))
    monkeypatch.setattr(plan, "DRIVER_RANGES", 5)
    assert os.path.isdir(scan.build_index(spark, at, "k", 1, f"{at}/large"))
    df = scan.scan(spark, "pageheap", at, index_path=f"{at}/large", range="k:int8:50:60", with_page=True)
    assert df.select("_page").distinct().count() == 1 and df.where("k BETWEEN 50 AND 60").count() == 11


def test_a_further_format(spark, sf_dir):
    """Comma-separated lines as a format: registered with its encoder and the text of a reader."""
    import pyarrow as pa
    import pyarrow.csv
    from pagelift.synth import spec

    def encode(batch, storage):
        out = pa.BufferOutputStream()
        pyarrow.csv.write_csv(pa.Table.from_batches([batch]), out)
        return out.getvalue().to_pybytes()

    template = '''import io

import pyarrow as pa
import pyarrow.csv

KINDS = {"int4": pa.int32(), "int8": pa.int64(), "varchar": pa.string(), "text": pa.string()}


def read_pages(pages, column_spec, names=None, index_id=None):
    kinds = {c.split(":")[0]: KINDS[c.split(":")[1].split("(")[0].rstrip("!")] for c in column_spec.split(",")}
    options = pyarrow.csv.ConvertOptions(column_types=kinds, strings_can_be_null=True, quoted_strings_can_be_null=False)
    table = pyarrow.csv.read_csv(io.BytesIO(pages.tobytes()), convert_options=options).combine_chunks()
    return table.select(names or table.column_names).to_batches()[0]
'''
    spec.register_format("lines", {"separator": ","}, "all rows", ["text may hold separators"], encode, template)
    j = loop.Job("nation/lines", "lines", StorageSchema.parse("a:int8!,b:int4,c:varchar(600)").spark(), {"c": "varchar(600)"})
    good = loop.run(spark, j, loop.SynthConfig(all_types=False))
    assert good.passed and good.attempts == 1
    prose = loop.run(spark, j, loop.SynthConfig(coder=coder.FaultyCoder(("prose",)), all_types=False))
    assert prose.passed and prose.attempts == 2


def test_prose_is_stripped():
    assert coder.strip_prose("Here it is:\n\n```python\nimport os\n```\nDone.") == "import os\n"
    assert coder.strip_prose("Sure!\ndef f():\n    pass") == "def f():\n    pass\n"
    with pytest.raises(ValueError):
        coder.strip_prose("no code here")


def test_all_queries_are_named_once_and_have_matching_sql():
    import __spark_entry__ as e

    q, s = e.queries(), e.oracle_sql()
    assert set(s) <= set(q) and len(q) > 250
