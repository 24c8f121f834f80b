"""The deterministic checker, and explanations of what it found."""

from __future__ import annotations

import json
import traceback
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.formats import cell, heap, tree
from pagelift.measure import GroundTruth, Mismatch, compare, truth
from pagelift.schema import StorageSchema
from pagelift.synth.coder import ENTRY, ask
from pagelift.synth.spec import column_spec, registered


@dataclass
class Verdict:
    passed: bool
    stage: str  # compile, run or check
    output: str = ""
    errors: list[Mismatch] = field(default_factory=list)

    @property
    def kind(self) -> str:
        return "" if self.passed else self.stage if self.stage != "check" else self.errors[0].kind


def page_bytes(df: DataFrame, kind: str, storage: StorageSchema) -> bytes:
    """The rows as page files would hold them; a checking table is small by design."""
    batch = _batch(df)
    if registered(kind):
        return registered(kind)["encode"](batch, storage)
    if kind == "pageheap":
        return heap.encode(batch, storage).tobytes()
    if kind == "pagecell":
        return cell.leaf_bytes(cell.database([batch], storage, "made"), "made")
    return np.vstack([tree.file_start(40), tree.encode(batch, storage)]).tobytes()


def _batch(df: DataFrame) -> pa.RecordBatch:
    table = df.toArrow()
    return pa.RecordBatch.from_arrays([c.combine_chunks() if c.num_chunks != 1 else c.chunk(0) for c in table.columns], names=table.column_names)


def compiled(source: str):
    """The entry function of a source, or an exception."""
    space: dict = {"__name__": "generated_reader"}
    exec(compile(source, "<reader>", "exec"), space)  # noqa: S102 - running generated readers is the point
    return space[ENTRY]


def check(spark: SparkSession, source: str, data: bytes, storage: StorageSchema, expected: GroundTruth, kind: str, rtol: float = 1e-3) -> Verdict:
    """Compile the source, run it over the pages in a task, and compare the statistics of what it returns."""
    try:
        compile(source, "<reader>", "exec")
    except SyntaxError as e:
        return Verdict(False, "compile", f"{e.__class__.__name__}: {e}")
    schema = storage.spark()
    spec, names = column_spec(storage, kind), storage.names

    def run(batches):
        for _ in batches:
            reader = compiled(source)
            out = reader(np.frombuffer(data, np.uint8), spec, names)
            yield pa.RecordBatch.from_arrays([out.column(n) for n in names], names=names)

    try:
        found = truth(spark.range(1).coalesce(1).select(F.col("id")).mapInArrow(run, schema))
    except Exception as e:  # the reader's fault, whatever it is: the loop reports it
        return Verdict(False, "run", "\n".join(traceback.format_exception_only(e))[-2000:])
    errors = compare(found, expected, rtol)
    return Verdict(not errors, "check", errors=errors)


@dataclass
class Diagnosis:
    kind: str
    text: str
    columns: list
    fixed: list


class RuleDiagnoser:
    """Explains a failed verdict by rules, and tells which earlier errors are gone.  It is asked about failures only."""

    def __init__(self):
        self.calls = 0

    def explain(self, verdict: Verdict, history: list[Diagnosis], storage: StorageSchema) -> Diagnosis:
        self.calls += 1
        columns = sorted({e.column for e in verdict.errors if e.column})
        fixed = sorted({c for d in history for c in d.columns} - set(columns))
        if verdict.stage != "check":
            return Diagnosis(verdict.stage, verdict.output[-500:], columns, fixed)
        first = verdict.errors[0]
        if first.kind == "row_count":
            text = f"{first.got} rows of {first.expected}: look at page and tuple selection, and at visibility"
        else:
            kinds = sorted({storage[c].kind for c in columns})
            text = f"{first.what} of {first.column} is {first.got}, not {first.expected}; storage types concerned: {', '.join(kinds)}"
        return Diagnosis(first.kind, text, columns, fixed)


class ExternalDiagnoser:
    """Runs a command that gets verdict and history as JSON on its input and answers with a diagnosis as JSON.  Like the
    rules, it is asked about failures only."""

    def __init__(self, command: list[str], timeout: int = 600):
        self.command, self.timeout, self.calls = command, timeout, 0

    def explain(self, verdict: Verdict, history: list[Diagnosis], storage: StorageSchema) -> Diagnosis:
        self.calls += 1
        request = {"stage": verdict.stage, "output": verdict.output, "errors": [asdict(e) for e in verdict.errors], "history": [asdict(d) for d in history], "columns": storage.text()}
        told = json.loads(ask(self.command, json.loads(json.dumps(request, default=str)), self.timeout))
        return Diagnosis(told.get("kind") or verdict.kind, told.get("text", ""), told.get("columns", []), told.get("fixed", []))
