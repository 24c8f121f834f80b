"""Make a reader from the command line: python -m pagelift.synth --columns "k:int8!,t:text" --kind pageheap --out reader.py

Each role can have a backend of its own, as a command that reads JSON and answers: --architect, --coder, --diagnoser.  A
spent budget leaves --checkpoint, and --resume goes on from one.
"""

from __future__ import annotations

import argparse
import json
import shlex
import sys

from pyspark.sql import SparkSession
from pyspark.sql.types import StructField, StructType

from pagelift import scan
from pagelift.schema import StorageSchema
from pagelift.synth import coder, loop, qa, spec


def main(arguments: list[str] | None = None, spark: SparkSession | None = None) -> int:
    p = argparse.ArgumentParser(prog="python -m pagelift.synth", description=__doc__.split("\n")[0])
    p.add_argument("--columns", required=True, help="name:type pairs, as for the sources")
    p.add_argument("--kind", required=True, help="pageheap, pagetree or a registered format")
    p.add_argument("--key", default="", help="key columns of a tree")
    p.add_argument("--out", required=True, help="where the source goes")
    p.add_argument("--budget", type=int, default=loop.BUDGET)
    p.add_argument("--rows", type=int, default=50, help="rows of the checking table")
    p.add_argument("--checkpoint")
    p.add_argument("--resume")
    for role in ("architect", "coder", "diagnoser"):
        p.add_argument(f"--{role}", help=f"command in place of the built-in {role}")
    a = p.parse_args(arguments)
    storage = StorageSchema.parse(a.columns, tuple(k for k in a.key.split(",") if k))
    struct = StructType([StructField(f.name, f.dataType, storage[f.name].nullable) for f in storage.spark().fields])
    kinds = {c.name: storage.text([c]).split(":", 1)[1].rstrip("!") for c in storage.columns}
    config = loop.SynthConfig()
    if a.architect:
        config.architect = spec.ExternalArchitect(shlex.split(a.architect))
    if a.coder:
        config.coder = coder.ExternalCoder(shlex.split(a.coder))
    if a.diagnoser:
        config.diagnoser = qa.ExternalDiagnoser(shlex.split(a.diagnoser))
    own = spark is None
    spark = scan.register(spark or SparkSession.builder.getOrCreate())
    result = loop.run(spark, loop.Job(a.out, a.kind, struct, kinds, storage.key, a.rows), config, a.budget, a.checkpoint, a.resume)
    if own:
        spark.stop()
    print(json.dumps(result.metrics()))
    if result.passed:
        with open(a.out, "w", encoding="utf-8") as f:
            f.write(result.source)
    return 0 if result.passed else 1


if __name__ == "__main__":
    sys.exit(main())
