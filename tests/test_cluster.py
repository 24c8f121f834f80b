"""Queries on a cluster of two executors that share nothing with the driver but one folder, held against their SQL."""

import datetime
import os
import subprocess
import sys

import duckdb
import pyspark
import pytest

from conftest import DATA, ROOT

QUERIES = ["access_compare", "etl_jdbc_lineitem", "jdbc_partitioned", "jdbc_row_at_a_time", "jdbc_server_filter", "sink_jdbc", "src_jdbc", "src_jdbc_partitioned"]

RUN = """
import sys
from pyspark.sql import SparkSession
import __spark_entry__ as entry
data, out, *names = sys.argv[1:]
spark = (
    SparkSession.builder.master("local-cluster[2,1,1024]").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.host", "127.0.0.1")
    .config("spark.sql.shuffle.partitions", "4").config("spark.checkpoint.dir", f"file://{out}/shared").getOrCreate()
)
for name in names:
    try:
        entry.queries()[name](spark, data).write.parquet(f"{out}/{name}")
    except Exception as e:
        open(f"{out}/{name}.error", "w").write(str(e)[:2000])
spark.stop()
"""


@pytest.fixture(scope="module")
def results(tmp_path_factory):
    out = tmp_path_factory.mktemp("cluster")
    left_out = ("PYSPARK_GATEWAY_PORT", "PYSPARK_GATEWAY_SECRET", "PYSPARK_SUBMIT_ARGS")
    env = {k: v for k, v in os.environ.items() if k not in left_out} | {"PYTHONPATH": ROOT, "PYSPARK_PYTHON": sys.executable, "SPARK_HOME": os.path.dirname(pyspark.__file__), "SPARK_SCALA_VERSION": "2.13"}
    subprocess.run([sys.executable, "-c", RUN, DATA, str(out), *QUERIES], env=env, cwd=out, timeout=600, check=True, capture_output=True)
    return out


@pytest.mark.parametrize("name", QUERIES)
def test_executors_share_nothing_with_the_driver(results, name):
    import __spark_entry__ as entry

    error = results / f"{name}.error"
    assert not error.exists(), error.read_text()
    db = duckdb.connect()
    for file in os.listdir(DATA):
        db.execute(f"CREATE VIEW {file.removesuffix('.parquet')} AS SELECT * FROM '{DATA}/{file}'")
    got, want = f"(SELECT * FROM '{results}/{name}/*.parquet')", f"({entry.oracle_sql()[name]})"
    assert db.execute(f"SELECT count(*) FROM {got}").fetchone() == db.execute(f"SELECT count(*) FROM {want}").fetchone() != (0,)
    for a, b in ((got, want), (want, got)):
        assert db.execute(f"SELECT * FROM {a} EXCEPT ALL SELECT * FROM {b}").fetchall() == []


def test_values_survive_the_import(spark, tmp_path):
    from pagelift import wire

    at = datetime.datetime(1999, 12, 31, 23, 59, 59, 123456)
    rows = [
        (1, "", 1e-300, at, True, at.date()), (2, None, -0.1, None, None, None), (3, 'a "quoted", cell\nand a line\r\n', 1.7e308, datetime.datetime(1, 1, 1), False, datetime.date(1, 1, 1)),
        (2**63 - 1, "é\U0001f600 ", 5e-324, datetime.datetime(1500, 3, 1), True, datetime.date(1500, 3, 1)), (-(2**63), "NULL", 0.1 + 0.2, at, None, None),
        (6, "x" * 100_000, 1.0, datetime.datetime(9999, 12, 31, 23, 59, 59, 999999), False, datetime.date(9999, 12, 31)),
    ]
    df = spark.createDataFrame(rows, "k long, t string, v double, at timestamp_ntz, b boolean, d date").repartition(3)
    url = wire.load_jdbc(df, f"{tmp_path}/it's/odd.jar", "odd")
    assert sorted(map(tuple, wire.jdbc(spark, url, "odd", 10).collect())) == sorted(rows)
    assert os.listdir(f"{tmp_path}/it's") == ["odd.jar"]
    assert wire.jdbc(spark, wire.load_jdbc(df.where("k = 0"), f"{tmp_path}/none.jar", "odd"), "odd", 10).count() == 0


def test_a_database_is_filled_by_parts(spark, tmp_path):
    import zipfile

    from pagelift import wire

    df = spark.range(0, 300_000, 1, 40).selectExpr("id AS k", "cast(id AS double) AS v", "id % 7 AS r").where("r <> 0 OR k > 100000")
    url = wire.load_jdbc(df, f"{tmp_path}/parts.jar", "parts")
    for found in (wire.jdbc(spark, url, "parts", 1000), wire.jdbc(spark, url, "parts", 1000, "K", (0, 299_999))):
        assert found.exceptAll(df).count() == df.exceptAll(found).count() == 0
    with zipfile.ZipFile(tmp_path / "parts.jar") as z:
        large = [x.file_size for x in z.infolist() if x.filename.startswith("db/seg0/") and x.file_size >= 100_000]
    assert wire.TABLES - 2 <= len(large) <= wire.TABLES + 10  # a file each, none of which waits for another's log
    assert sum(large) < 50 * df.count()  # pages are full


@pytest.mark.parametrize("key", ["id AS k", "cast(null AS long) AS k"])
def test_partitions_without_keys(spark, tmp_path, key):
    from pagelift import wire

    df = spark.range(3).selectExpr(key).where("k IS NULL")
    url = wire.load_jdbc(df, f"{tmp_path}/keys.jar", "keys_of")
    assert wire.jdbc(spark, url, "keys_of", 10, "K", wire.bounds(df, "k")).count() == df.count()


@pytest.mark.parametrize("name", ["src_jdbc", "src_jdbc_partitioned"])
def test_rows_without_line_number_are_returned(spark, tmp_path, name):
    from pagelift import workloads

    rows = [(1, 1, 5.0), (1, 2, None), (2, None, 7.0), (None, None, 9.0), (3, 3, 1.0), (3, -4, 2.0), (4, 5, 3.0)]
    spark.createDataFrame(rows, "l_orderkey long, l_linenumber int, l_quantity double").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    got = workloads.queries()[name](spark, str(tmp_path)).collect()
    want = duckdb.sql(f"WITH lineitem AS (SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet') {workloads.oracle_sql()[name]}").fetchall()
    assert sorted(map(tuple, got), key=repr) == sorted(want, key=repr)
