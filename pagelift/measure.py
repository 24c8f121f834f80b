"""Measures of correctness: column statistics against expected ones, and exact differences of two tables."""

from __future__ import annotations

import math
from dataclasses import asdict, dataclass, field
from decimal import Decimal

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WHOLE, REAL = ("byte", "short", "integer", "long"), ("float", "double", "decimal")


@dataclass
class GroundTruth:
    """Row count, and for each column what its type allows: bounds and sum, distinct values, or first and last date."""

    rows: int
    columns: dict[str, dict] = field(default_factory=dict)

    def to_json(self) -> dict:
        return asdict(self)


def truth(df: DataFrame) -> GroundTruth:
    """All statistics in one aggregate."""
    wanted = [F.count(F.lit(1)).alias("__rows")]
    for f in df.schema.fields:
        c, kind = F.col(f"`{f.name}`"), f.dataType.typeName()
        wanted.append(F.count(c).alias(f"{f.name}|count"))
        if kind in WHOLE:
            wanted += [F.min(c).cast("long").alias(f"{f.name}|min"), F.max(c).cast("long").alias(f"{f.name}|max"), F.sum(c.cast("decimal(38,0)")).alias(f"{f.name}|sum")]
        elif kind in REAL:
            d = c.cast("double")
            wanted += [F.min(d).alias(f"{f.name}|min"), F.max(d).alias(f"{f.name}|max"), F.sum(d).alias(f"{f.name}|sum")]
        elif kind in ("date", "timestamp", "timestamp_ntz"):
            wanted += [F.min(c).cast("string").alias(f"{f.name}|first"), F.max(c).cast("string").alias(f"{f.name}|last")]
        elif kind == "boolean":
            wanted.append(F.count_if(c).alias(f"{f.name}|true"))
        else:
            wanted.append(F.count_distinct(c).alias(f"{f.name}|distinct"))
    row = df.agg(*wanted).first().asDict()
    out = GroundTruth(row.pop("__rows"))
    for key, value in row.items():
        name, _, what = key.rpartition("|")
        out.columns.setdefault(name, {})[what] = int(value) if isinstance(value, Decimal) else value
    return out


@dataclass(frozen=True)
class Mismatch:
    kind: str
    column: str
    what: str
    expected: object
    got: object


def compare(found: GroundTruth, expected: GroundTruth, rtol: float = 1e-3) -> list[Mismatch]:
    """Numbers within a relative tolerance, everything else exactly."""
    out = []
    if found.rows != expected.rows:
        out.append(Mismatch("row_count", "", "rows", expected.rows, found.rows))
    for name, stats in expected.columns.items():
        for what, want in stats.items():
            got = found.columns.get(name, {}).get(what)
            if isinstance(want, float) and isinstance(got, (int, float)):
                same = (math.isnan(want) and math.isnan(got)) or want == got or abs(got - want) <= rtol * max(abs(want), 1e-12)
            else:
                same = want == got
            if not same:
                out.append(Mismatch("null_count" if what == "count" else "value", name, what, want, got))
    return out


def exact_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """only_a and only_b: rows, with multiplicity, that one table has and the other lacks.  Rows are pre-aggregated."""
    cols = a.columns
    one, two = (x.select(*cols).groupBy(*cols).agg(F.count(F.lit(1)).alias(n)) for x, n in ((a, "n1"), (b, "n2")))
    right = two.select(*[F.col(c).alias(f"__{c}") for c in cols], "n2")
    cond = [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in cols]
    both = one.join(right, cond, "full")
    n1, n2 = F.coalesce("n1", F.lit(0)), F.coalesce("n2", F.lit(0))
    return both.agg(F.coalesce(F.sum(F.greatest(n1 - n2, F.lit(0))), F.lit(0)).alias("only_a"), F.coalesce(F.sum(F.greatest(n2 - n1, F.lit(0))), F.lit(0)).alias("only_b"))
