"""Data for checking a reader: a small deterministic table of any schema, as rows, page files and known statistics."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DataType, StructType

from pagelift.measure import GroundTruth, truth


def value(kind: DataType, i: Column, position: int, nullable: bool) -> Column:
    """A value of row i; every seventh is null where that is allowed, at another place in each column."""
    name = kind.typeName()
    n = i * (position + 3) - 40
    made = {
        "boolean": lambda: (n % 3 == 0),
        "byte": lambda: n % 100,
        "short": lambda: n * 97 % 30000,
        "integer": lambda: n * 1_000_003 % 2_000_000_000,
        "long": lambda: n * 10_000_000_019,
        "float": lambda: n / 8,
        "double": lambda: F.round(n * 1.37, 2),
        "decimal": lambda: F.round(n * 12.34, getattr(kind, "scale", 2)),
        "date": lambda: F.date_add(F.lit("1999-12-01").cast("date"), (n * 17).cast("int")),
        "timestamp_ntz": lambda: F.expr(f"timestampadd(MICROSECOND, (id * {position + 3} - 40) * 86400000037, TIMESTAMP_NTZ '2000-01-01 00:00:00')"),
        "timestamp": lambda: F.timestamp_micros(F.lit(946_684_800_000_000) + n * 86_400_000_037),
        "binary": lambda: F.encode(F.repeat(F.lit("z"), (i % 5).cast("int")), "UTF-8"),
    }.get(name, lambda: F.concat(F.lit("v"), F.repeat(F.lit("é"), (i % 4).cast("int")), (i * position).cast("string"), F.repeat(F.lit("x"), F.when(i % 10 == 3, 130).otherwise(0))))()
    made = made.cast(kind)
    return F.when((i + position) % 7 == 0, F.lit(None).cast(kind)).otherwise(made) if nullable else made


def make(spark: SparkSession, struct: StructType, rows: int = 50, key: tuple[str, ...] = ()) -> tuple[DataFrame, GroundTruth]:
    """The table and its statistics.  Keys are made of the row's number and never null."""
    base = spark.range(rows).coalesce(1)
    cols = []
    for p, f in enumerate(struct.fields):
        if f.name in key:
            cols.append((F.col("id") * 2 + 1).cast(f.dataType).alias(f.name))
        else:
            short = f.metadata.get("storage", "") if f.metadata else ""
            v = value(f.dataType, F.col("id"), p, f.nullable)
            if f.dataType.typeName() == "string" and "(" in short:
                v = F.substring(v, 1, int(short.split("(")[1].rstrip(")")))
            cols.append(v.alias(f.name))
    df = base.select(*cols)
    return df, truth(df)
