"""Format specifications: what a reader's writer has to know about a format, as data.

The specification of a schema is derived from its Spark schema, a kind of page file, and a knowledge file that holds the
format's constants and pitfalls in words.
"""

from __future__ import annotations

import json
import os
import re
import subprocess
from collections.abc import Callable
from dataclasses import asdict, dataclass, field

import pyarrow as pa
from pyspark.sql.types import StructType

from pagelift.schema import FIXED, StorageSchema
from pagelift.session import ROOT

ARROW = {"bool": "b", "int2": "s", "int4": "i", "int8": "l", "float4": "f", "float8": "g", "date": "tdD", "timestamp": "tsu:", "numeric": "g", "bpchar": "u", "varchar": "u", "text": "u", "binary": "z"}
CONSTANTS = {
    "pageheap": {"page_size": 8192, "header": 24, "pointer": 4, "tuple_header": 23, "epoch_days": 10957, "byte_order": "little"},
    "pagecell": {"page_size": 4096, "leaf": 13, "cell_pointers": 8, "overflow_margin": 35, "byte_order": "big"},
    "pagetree": {"page_size": 16384, "header": 38, "index_header": 36, "first_record": 99, "last_record": 112, "page_type": 0x45BF, "byte_order": "big"},
}
VISIBILITY = {"pagecell": "keep all cells that a leaf page points to", "pageheap": "keep unless a deleter is set that was neither rolled back nor only a lock", "pagetree": "keep ordinary records that aren't marked deleted"}


@dataclass(frozen=True)
class FormatSpec:
    kind: str
    constants: dict
    columns: list
    visibility: str
    pitfalls: list
    key: list = field(default_factory=list)
    template: str = ""  # of formats that are registered: the source of a reader

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @classmethod
    def from_json(cls, text: str) -> FormatSpec:
        return cls(**json.loads(text))

    def storage(self) -> StorageSchema:
        return StorageSchema.parse(",".join(c["storage"] for c in self.columns), tuple(self.key))


_FORMATS: dict[str, dict] = {}


def register_format(kind: str, constants: dict, visibility: str, pitfalls: list[str], encode: Callable[[pa.RecordBatch, StorageSchema], bytes], template: str) -> None:
    """Make a further format known: to the specification writer, to the checker (encode: rows as the format's bytes) and to
    the template coder (template: the source of a reader with the usual entry function)."""
    _FORMATS[kind] = {"constants": constants, "visibility": visibility, "pitfalls": pitfalls, "encode": encode, "template": template}


def registered(kind: str) -> dict | None:
    return _FORMATS.get(kind)


def column_spec(storage: StorageSchema, kind: str) -> str:
    """What a generated reader is told of a table when it is called: columns in their order on disk."""
    return storage.text(storage.physical() if kind == "pagetree" else storage.columns)


#: Every storage type, as nullable columns and once as a required one, behind a key.
ALL_TYPES = "k:int8!,a:bool,b:int2,c:int4,d:int8,e:float4,f:float8,g:numeric(15,2),h:date,i:timestamp,j:bpchar(40),l:varchar(600),m:text,n:numeric(18,2)!,o:int2!,p:bool!,q:int4!"


def knowledge(kind: str) -> list[str]:
    """Pitfalls listed in the format's knowledge file."""
    with open(os.path.join(ROOT, "knowledge", f"{kind}.md"), encoding="utf-8") as f:
        return [m[1].strip() for m in re.finditer(r"^- (.+)$", f.read(), re.M)]


def architect(struct: StructType, kind: str, kinds: dict[str, str] | None = None, key: tuple[str, ...] = ()) -> FormatSpec:
    """Schema and kind of page file -> specification."""
    storage = StorageSchema.from_struct(struct, kinds, key)
    columns = []
    for c in storage.columns:
        args = f"({c.precision},{c.scale})" if c.kind == "numeric" else f"({c.max_len})" if c.max_len else ""
        columns.append({"name": c.name, "storage": f"{c.name}:{c.kind}{args}{'' if c.nullable else '!'}", "arrow": ARROW[c.kind], "fixed": c.kind in FIXED})
    known = _FORMATS.get(kind) or {"constants": CONSTANTS[kind], "visibility": VISIBILITY[kind], "pitfalls": knowledge(kind)}
    return FormatSpec(kind, known["constants"], columns, known["visibility"], known["pitfalls"], list(key), known.get("template", ""))


class ExternalArchitect:
    """Runs a command that gets the built-in specification of a schema as JSON on its input and answers with the one to be
    used."""

    def __init__(self, command: list[str], timeout: int = 600):
        self.command, self.timeout = command, timeout

    def __call__(self, struct: StructType, kind: str, kinds: dict[str, str] | None = None, key: tuple[str, ...] = ()) -> FormatSpec:
        request = architect(struct, kind, kinds, key).to_json()
        done = subprocess.run(self.command, input=request, capture_output=True, text=True, timeout=self.timeout, check=True)
        return FormatSpec.from_json(done.stdout)
