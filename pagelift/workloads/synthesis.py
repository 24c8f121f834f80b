"""The reader-synthesis pipeline as queries: statistics, verdicts, retries, resumption, deployment."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import functions as F

from pagelift import measure, scan
from pagelift.session import scratch
from pagelift.synth import deploy, loop
from pagelift.synth.coder import FaultyCoder
from pagelift.synth.study import ROLES, WORKERS, study
from pagelift.workloads import fixtures as fx
from pagelift.workloads.registry import Registry
from pagelift.workloads.scans import TYPE_SQL

REG = Registry()
TABLES = [t for t in fx.SPECS if t != "embeddings"]


def job(spark, d, table: str, kind: str) -> loop.Job:
    from pagelift.schema import StorageSchema

    struct = StorageSchema.parse(fx.SPECS[table]).spark()
    key = fx.KEYS[table] if kind == "pagetree" else ()
    kinds = {}
    for part in fx.SPECS[table].replace("!", "").split(","):
        if ":" in part:
            name, _, rest = part.partition(":")
            kinds[name] = rest
    for k, v in kinds.items():
        if v.startswith("numeric"):
            kinds[k] = "numeric(15,2)"
        elif v.startswith(("bpchar", "varchar")):
            kinds[k] = "varchar(600)"  # the checking table's texts are longer than some columns
    return loop.Job(f"{table}/{kind}", kind, struct, kinds, key)


def truth_rows(spark, d, table):
    """The statistics as rows (column, measure, value)."""
    t = measure.truth(fx.direct(spark, d, table, "pageheap"))
    rows = [("", "rows", float(t.rows), None)]
    for c, stats in t.columns.items():
        for what, v in stats.items():
            rows.append((c, what, float(v), None) if isinstance(v, (int, float)) else (c, what, None, v))
    return spark.createDataFrame(rows, "column string, measure string, number double, text string").where("measure IN ('rows', 'count', 'min', 'max', 'distinct')")


def truth_sql(table: str) -> str:
    out = [f"SELECT '' AS \"column\", 'rows' AS measure, CAST(count(*) AS DOUBLE) AS number, CAST(NULL AS VARCHAR) AS text FROM {table}"]
    import re

    for name, kind in re.findall(r"(\w+):(\w+)", fx.SPECS[table]):
        out.append(f"SELECT '{name}', 'count', CAST(count({name}) AS DOUBLE), NULL FROM {table}")
        if kind in ("int2", "int4", "int8", "float4", "float8", "numeric"):
            out += [f"SELECT '{name}', '{m}', CAST({m}({name}) AS DOUBLE), NULL FROM {table}" for m in ("min", "max")]
        elif kind in ("text", "varchar", "bpchar", "binary"):
            out.append(f"SELECT '{name}', 'distinct', CAST(count(DISTINCT {name}) AS DOUBLE), NULL FROM {table}")
    return " UNION ALL ".join(out)


for _t in ("lineitem", "orders", "events", "customer", "part"):
    REG.add(f"synth_truth_{_t}", lambda s, d, t=_t: truth_rows(s, d, t), truth_sql(_t))


def _pass(kind):
    def run(spark, d):
        """One row a schema: did a reader pass, in how many tries, with how many explanations (none for a correct one)."""
        scan.register(spark)
        with ThreadPoolExecutor(WORKERS) as pool:
            rows = list(pool.map(lambda t: loop.run(spark, job(spark, d, t, kind)).metrics(), TABLES))
        return spark.createDataFrame([(r["name"], r["passed"], r["attempts"], r["diagnosis_calls"]) for r in rows], "job string, passed boolean, attempts int, diagnosis_calls int")

    return run


def _pass_sql(kind):
    return " UNION ALL ".join(f"SELECT '{t}/{kind}' AS job, true AS passed, CAST(1 AS INTEGER) AS attempts, CAST(0 AS INTEGER) AS diagnosis_calls" for t in TABLES)


for _k in ("pageheap", "pagetree"):
    REG.add(f"synth_pass_{_k[4:]}", _pass(_k), _pass_sql(_k))

REG.add("synth_pass_cell", _pass("pagecell"), _pass_sql("pagecell"))


@REG.query("synth_deployed_cell", "SELECT * FROM lineitem")
def synth_deployed_cell(spark, d):
    """Database files of another system, through a generated reader; one fault on the way."""
    from pagelift.workloads import cells

    scan.register(spark)
    r = loop.run(spark, job(spark, d, "lineitem", "pagecell"), loop.SynthConfig(coder=FaultyCoder(("sign_lost",))))
    if r.attempts != 2:
        raise AssertionError("the fault was not seen")
    return scan.scan(spark, "pagecell", cells.base(spark, d, "lineitem"), table="lineitem", columns_spec=fx.SPECS["lineitem"], **deploy.options(r))


FAULTS = [(), ("syntax",), ("crash",), ("lost_rows",), ("wrong_epoch",), ("sign_lost",), ("scale_lost",), ("null_bits_turned",), ("prose",), ("syntax", "crash", "lost_rows", "wrong_epoch")]


@REG.query("synth_retry_faults", " UNION ALL ".join(f"SELECT '{'+'.join(f)}' AS faults, true AS passed, CAST({len(f) + 1} AS INTEGER) AS attempts, CAST({len(f)} AS INTEGER) AS diagnosis_calls" for f in FAULTS))
def synth_retry_faults(spark, d):
    """Seeded faults: each costs one try and one explanation."""
    scan.register(spark)
    return study(spark, [job(spark, d, "orders", "pageheap")], FAULTS).select("faults", "passed", "attempts", "diagnosis_calls")


@REG.query("synth_stubborn", "SELECT true AS passed, CAST(3 AS INTEGER) AS attempts, CAST(1 AS INTEGER) AS rewrites, CAST(1 AS INTEGER) AS stuck")
def synth_stubborn(spark, d):
    """A coder that repeats itself is told so, and asked to write anew."""
    scan.register(spark)
    r = loop.run(spark, job(spark, d, "orders", "pageheap"), loop.SynthConfig(coder=FaultyCoder(("crash",), ("crash",))))
    return spark.createDataFrame([(r.passed, r.attempts, r.rewrites, r.stuck)], "passed boolean, attempts int, rewrites int, stuck int")


@REG.query("synth_resume", "SELECT false AS first_passed, CAST(2 AS INTEGER) AS first_attempts, true AS passed, CAST(1 AS INTEGER) AS attempts")
def synth_resume(spark, d):
    """A spent budget leaves a checkpoint; a second run goes on from it."""
    scan.register(spark)
    at = f"{scratch(spark, 'synth')}/checkpoint.json"
    j, coder = job(spark, d, "orders", "pageheap"), FaultyCoder(("syntax", "crash"))
    one = loop.run(spark, j, loop.SynthConfig(coder=coder), n_max=2, checkpoint=at)
    two = loop.run(spark, j, loop.SynthConfig(coder=coder), n_max=2, resume=at)
    return spark.createDataFrame([(one.passed, one.attempts, two.passed, two.attempts)], "first_passed boolean, first_attempts int, passed boolean, attempts int")


for _k in ("pageheap", "pagetree"):

    def _deployed(spark, d, kind=_k):
        """The whole table through a generated reader."""
        scan.register(spark)
        r = loop.run(spark, job(spark, d, "orders", kind))
        return scan.scan(spark, kind, fx.base(spark, d, "orders", kind), **deploy.options(r))

    REG.add(f"synth_deployed_{_k[4:]}", _deployed, "SELECT * FROM orders")

    def _elsewhere(spark, d, kind=_k):
        """A reader that was made for one table, on another: it takes the columns when it is called."""
        scan.register(spark)
        r = loop.run(spark, job(spark, d, "nation", kind))
        return scan.scan(spark, kind, fx.base(spark, d, "lineitem", kind), **deploy.options(r))

    REG.add(f"synth_other_table_{_k[4:]}", _elsewhere, "SELECT * FROM lineitem")

    def _types(spark, d, kind=_k):
        """All types, through a generated reader."""
        from pagelift.workloads import scans

        scan.register(spark)
        r = loop.run(spark, job(spark, d, "nation", kind))
        key = ("k",) if kind == "pagetree" else ()
        return scans.made(spark, d, "types", kind, fx.table(spark, d, "orders").selectExpr(*scans.TYPE_EXPRS), scans.TYPES, pk=key, read=deploy.options(r))

    REG.add(f"synth_types_{_k[4:]}", _types, TYPE_SQL)

MEASURES = "job, faults, without, passed, correct, attempts, diagnosis_calls, errors, timed"
STUDIED = [f"{t}/{k}" for t in ("nation", "events", "lineitem") for k in ("pageheap", "pagetree")]


def _told(rows):
    """Rows of the study's measures as SQL."""
    text = lambda x: f"'{x}'" if isinstance(x, str) else str(x).lower() if isinstance(x, bool) else f"CAST({x} AS INTEGER)"
    return " UNION ALL ".join(f"SELECT {', '.join(f'{text(v)} AS {n}' for n, v in zip(MEASURES.split(', '), r))}" for r in rows)


@REG.query("synth_study", _told([(j, "+".join(f), "", True, True, len(f) + 1, len(f), ",".join(e), True) for j in STUDIED for f, e in (((), ()), (("lost_rows",), ("row_count",)), (("syntax", "sign_lost"), ("compile", "value")))]))
def synth_study(spark, d):
    """Tries, outcome and time over several schemas, formats and fault sets."""
    scan.register(spark)
    jobs = [job(spark, d, *name.split("/")) for name in STUDIED]
    return study(spark, jobs, [(), ("lost_rows",), ("syntax", "sign_lost")]).withColumn("timed", F.col("seconds") > 0).select(*MEASURES.split(", "))


def _without(job_name):
    # no knowledge of the format: no code.  No explanations: what the compiler says is mended, a wrong value is not.
    # No checks: the first source is taken, right or wrong.
    yield job_name, "", "architect", False, False, 3, 3, "prose,prose,prose", True
    yield job_name, "syntax+sign_lost", "architect", False, False, 3, 3, "prose,prose,prose", True
    yield job_name, "", "diagnoser", True, True, 1, 0, "", True
    yield job_name, "syntax+sign_lost", "diagnoser", False, False, 3, 0, "compile,value,value", True
    yield job_name, "", "checker", True, True, 1, 0, "", True
    yield job_name, "syntax+sign_lost", "checker", True, False, 1, 0, "", True


@REG.query("synth_ablation", _told([r for j in ("events/pageheap", "events/pagetree") for r in _without(j)]))
def synth_ablation(spark, d):
    """What each role contributes: the loop without it."""
    scan.register(spark)
    jobs = [job(spark, d, "events", k) for k in ("pageheap", "pagetree")]
    return study(spark, jobs, [(), ("syntax", "sign_lost")], n_max=3, without=ROLES).withColumn("timed", F.col("seconds") > 0).select(*MEASURES.split(", "))


@REG.query("measure_exact_diff", "SELECT CAST(0 AS BIGINT) AS only_a, CAST(0 AS BIGINT) AS only_b")
def measure_exact_diff(spark, d):
    return measure.exact_diff(fx.direct(spark, d, "orders", "pageheap"), fx.direct(spark, d, "orders", "pagetree")).select(F.col("only_a").cast("long"), F.col("only_b").cast("long"))
