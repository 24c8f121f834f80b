"""Storage schemas: which bytes a column has on disk, and which Spark and Arrow type it becomes."""

from __future__ import annotations

import json
import re
from dataclasses import asdict, dataclass, field, replace

import pyarrow as pa
from pyspark.sql import types as T

FIXED = {"bool": 1, "int2": 2, "int4": 4, "int8": 8, "float4": 4, "float8": 8, "date": 4, "timestamp": 8}
VARIABLE = ("numeric", "bpchar", "varchar", "text", "binary")
KINDS = (*FIXED, *VARIABLE, "skip")


@dataclass(frozen=True)
class StorageColumn:
    name: str
    kind: str
    precision: int = 15
    scale: int = 2
    max_len: int = 0  # characters of bpchar, bytes of varchar; 0: no limit
    nullable: bool = True
    width: int = 0  # of skip

    def __post_init__(self):
        if self.kind not in KINDS:
            raise ValueError(f"unknown storage type {self.kind} of column {self.name}")

    @property
    def is_text(self) -> bool:
        return self.kind in ("bpchar", "varchar", "text")

    def spark_type(self, numeric_as: str = "double", timestamp_as: str = "ntz") -> T.DataType:
        if self.kind == "numeric":
            return T.DecimalType(self.precision, self.scale) if numeric_as == "decimal" else T.DoubleType()
        if self.kind == "timestamp":
            return T.TimestampType() if timestamp_as == "ltz" else T.TimestampNTZType()
        return {
            "bool": T.BooleanType(), "int2": T.ShortType(), "int4": T.IntegerType(), "int8": T.LongType(), "float4": T.FloatType(),
            "float8": T.DoubleType(), "date": T.DateType(), "binary": T.BinaryType(),
        }.get(self.kind, T.StringType())

    def arrow_type(self, numeric_as: str = "double", timestamp_as: str = "ntz") -> pa.DataType:
        if self.kind == "numeric":
            return pa.decimal128(self.precision, self.scale) if numeric_as == "decimal" else pa.float64()
        if self.kind == "timestamp":
            return pa.timestamp("us", "UTC" if timestamp_as == "ltz" else None)
        return {"bool": pa.bool_(), "int2": pa.int16(), "int4": pa.int32(), "int8": pa.int64(), "float4": pa.float32(), "float8": pa.float64(), "date": pa.date32(), "binary": pa.binary()}.get(self.kind, pa.string())


@dataclass(frozen=True)
class StorageSchema:
    """Columns in logical order; for a tree, key names the columns that come first on disk."""

    columns: tuple[StorageColumn, ...]
    key: tuple[str, ...] = field(default=())

    @classmethod
    def parse(cls, text: str, key: tuple[str, ...] = ()) -> StorageSchema:
        """"name:type" pairs with commas between; type may have (arguments), and ! for NOT NULL.  Also JSON."""
        if text.lstrip().startswith("{"):
            return cls.from_json(text)
        out = []
        for m in re.finditer(r"\s*(\w+)\s*:\s*(\w+)(?:\(([\d\s,]+)\))?(!?)\s*(?:,|$)", text):
            args = [int(x) for x in (m[3] or "").split(",") if x.strip()]
            kind = {"string": "text", "int": "int4", "bigint": "int8", "double": "float8", "decimal": "numeric", "raw": "skip"}.get(m[2], m[2])
            more = {}
            if kind == "numeric" and args:
                more = {"precision": args[0], "scale": args[1] if len(args) > 1 else 0}
            elif kind == "skip":
                more = {"width": args[0] if args else 13}
            elif args:
                more = {"max_len": args[0]}
            out.append(StorageColumn(m[1], kind, nullable=not m[4], **more))
        if not out:
            raise ValueError(f"no columns in {text!r}")
        return cls(tuple(out), tuple(key))

    @classmethod
    def from_struct(cls, struct: T.StructType, kinds: dict[str, str] | None = None, key: tuple[str, ...] = ()) -> StorageSchema:
        """From a Spark schema; a storage type may be given by column, or as the field's metadata "storage"."""
        base = {"boolean": "bool", "smallint": "int2", "tinyint": "int2", "int": "int4", "bigint": "int8", "float": "float4", "double": "float8", "date": "date", "timestamp_ntz": "timestamp", "timestamp": "timestamp", "string": "text", "binary": "binary"}
        parts = []
        for f in struct.fields:
            if f.name.startswith("__"):
                continue
            name = f.dataType.simpleString()
            kind = (kinds or {}).get(f.name) or f.metadata.get("storage") or (name.replace("decimal", "numeric") if name.startswith("decimal") else base.get(name))
            if kind is None:
                raise ValueError(f"column {f.name} of type {name} has no storage type")
            parts.append(f"{f.name}:{kind}{'' if f.nullable and f.name not in key else '!'}")
        return cls.parse(",".join(parts), key)

    @classmethod
    def from_json(cls, text: str) -> StorageSchema:
        j = json.loads(text)
        return cls(tuple(StorageColumn(**c) for c in j["columns"]), tuple(j.get("key", ())))

    def to_json(self) -> str:
        return json.dumps({"columns": [asdict(c) for c in self.columns], "key": list(self.key)})

    def text(self, columns: tuple[StorageColumn, ...] | list[StorageColumn] | None = None) -> str:
        """The columns (or those given) as parse reads them; bytes to skip are raw."""
        out = []
        for c in self.columns if columns is None else columns:
            args = f"({c.precision},{c.scale})" if c.kind == "numeric" else f"({c.width})" if c.kind == "skip" else f"({c.max_len})" if c.max_len else ""
            out.append(f"{c.name}:{'raw' if c.kind == 'skip' else c.kind}{args}{'' if c.nullable else '!'}")
        return ",".join(out)

    @property
    def names(self) -> list[str]:
        return [c.name for c in self.columns if c.kind != "skip"]

    def __getitem__(self, name: str) -> StorageColumn:
        return next(c for c in self.columns if c.name == name)

    def spark(self, columns: list[str] | None = None, **how) -> T.StructType:
        return T.StructType([T.StructField(n, self[n].spark_type(**how), True) for n in columns or self.names])

    def physical(self) -> list[StorageColumn]:
        """Order on disk in a tree: key, hidden columns, the rest; without a key the hidden row number comes first too."""
        if any(c.kind == "skip" for c in self.columns):
            return list(self.columns)
        key = [replace(self[k], nullable=False) for k in self.key]
        rest = [c for c in self.columns if c.name not in self.key]
        return [*key, StorageColumn("_hidden", "skip", width=13 if key else 19, nullable=False), *rest]
