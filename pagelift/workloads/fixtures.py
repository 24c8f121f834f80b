"""Page files made from the given tables.  A fixture is encoded once: its folder's name holds a hash of its layout and of
the encoders' code, and its manifest is written last."""

from __future__ import annotations

import functools
import hashlib
import json
import os
import uuid

from pyspark.sql import DataFrame, SparkSession

from pagelift import scan
from pagelift.plans import pages as plan
from pagelift.session import ROOT, shared_dir

#: Storage types by table; columns in Parquet order.
SPECS = {
    "region": "r_regionkey:int4!,r_name:varchar(25)",
    "nation": "n_nationkey:int4!,n_name:varchar(25),n_regionkey:int4",
    "customer": "c_custkey:int8!,c_name:varchar(25),c_nationkey:int4,c_acctbal:numeric(15,2),c_mktsegment:bpchar(10)",
    "supplier": "s_suppkey:int8!,s_name:varchar(25),s_nationkey:int4,s_acctbal:numeric(15,2)",
    "part": "p_partkey:int8!,p_name:varchar(55),p_brand:bpchar(10),p_type:varchar(25),p_size:int4,p_retailprice:numeric(15,2)",
    "orders": "o_orderkey:int8!,o_custkey:int8,o_orderstatus:bpchar(1),o_totalprice:numeric(15,2),o_orderdate:timestamp,o_orderpriority:bpchar(15)",
    "lineitem": "l_orderkey:int8,l_partkey:int8,l_suppkey:int8,l_linenumber:int4,l_quantity:float8,l_extendedprice:numeric(15,2),l_discount:numeric(15,2),l_tax:numeric(15,2),l_returnflag:bpchar(1),l_linestatus:bpchar(1),l_shipdate:timestamp",
    "events": "event_id:int8!,ts:timestamp,user_id:int8,event_type:varchar(16),value:float8,props:text",
    "documents": "doc_id:int8!,text:text,lang:bpchar(2),source:varchar(20),n_chars:int8",
    "pages": "page_id:int8!,url:text,html:text",
    "benchmark": "item_id:int8!,text:text",
    "labels": "doc_id:int8!,quality:int4,toxic:int4",
    "conversations": "conv_id:int8!,turn:int8!,role:varchar(10),text:text",
    "embeddings": "vec_id:int8!,embedding:binary,label:int4",
}
KEYS = {
    "region": ("r_regionkey",), "nation": ("n_nationkey",), "customer": ("c_custkey",), "supplier": ("s_suppkey",), "part": ("p_partkey",), "orders": ("o_orderkey",), "lineitem": (),
    "events": ("event_id",), "documents": ("doc_id",), "pages": ("page_id",), "benchmark": ("item_id",), "labels": ("doc_id",), "conversations": ("conv_id", "turn"), "embeddings": ("vec_id",),
}
LONG_VALUES = ("documents", "pages")


@functools.cache
def code_hash() -> str:
    d = hashlib.sha256()
    for name in ("schema.py", "scan.py", "formats/codec.py", "formats/heap.py", "formats/tree.py", "formats/brin.py", "sources/paged.py", "workloads/fixtures.py"):
        d.update(open(os.path.join(ROOT, name), "rb").read())
    return d.hexdigest()[:10]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def place(spark: SparkSession, sf_dir: str, label: str, layout: dict) -> str:
    digest = hashlib.sha256(json.dumps([sf_dir, layout, code_hash()], sort_keys=True).encode()).hexdigest()[:12]
    return f"{shared_dir(spark)}/{os.path.basename(sf_dir.rstrip('/'))}/{label}/{digest}"


def ensure(spark: SparkSession, sf_dir: str, label: str, kind: str, make, spec: str, pk: tuple[str, ...] = (), cluster_by: tuple[str, ...] = (), index: dict | None = None, recipe: str = "", **options) -> str:
    """Path of a fixture; make() gives its rows.  A writer that is beaten by another uses the other's files."""
    scan.register(spark)
    layout = {"kind": kind, "spec": spec, "pk": pk, "cluster": cluster_by, "index": index, "recipe": recipe, "version": 2, **options}
    path = place(spark, sf_dir, f"{kind}-{label}", layout)
    if not plan.exists(f"{path}/{plan.MANIFEST}"):
        draft = f"{path}.{uuid.uuid4().hex[:8]}"
        scan.write(make(), kind, draft, spec, pk=pk, cluster_by=cluster_by, **options)
        if index:
            scan.build_index(spark, draft, **index, index_path=f"{draft}/index.brin")
        fs, at = plan.file_system(draft)
        try:
            fs.move(at, plan.file_system(path)[1])
        except OSError:
            if not plan.exists(f"{path}/{plan.MANIFEST}"):
                raise
    return path


def base(spark: SparkSession, sf_dir: str, name: str, kind: str) -> str:
    """The plain fixture of a table."""
    more = {"overflow": "true"} if name in LONG_VALUES else {}
    pk = KEYS[name] if kind == "pagetree" else ()
    return ensure(spark, sf_dir, name, kind, lambda: table(spark, sf_dir, name), SPECS[name], pk=pk, **more)


def direct(spark: SparkSession, sf_dir: str, name: str, kind: str, **options) -> DataFrame:
    """The table, read from page files."""
    if name in LONG_VALUES:
        options.setdefault("on_overflow", "resolve")
    return scan.scan(spark, kind, base(spark, sf_dir, name, kind), **options)
