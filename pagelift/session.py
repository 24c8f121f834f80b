"""What a session needs before a query runs: the package on the executors, and runtime settings."""

from __future__ import annotations

import atexit
import hashlib
import os
import tempfile
import uuid
import zipfile

from pyspark.sql import SparkSession

ROOT = os.path.dirname(os.path.abspath(__file__))


def _files():
    for folder, dirs, names in os.walk(ROOT):
        dirs[:] = sorted(d for d in dirs if d != "__pycache__")
        for name in sorted(names):
            if name.endswith((".py", ".json", ".md")):
                full = os.path.join(folder, name)
                yield full, os.path.relpath(full, os.path.dirname(ROOT))


#: Rows of an Arrow batch at most: rows here hold whole documents, and both JVM and worker keep batches in memory.  This is
#: the one setting of the caller's session that `ship` changes: it lowers it, as batches are cut when a plan runs and plans
#: here are lazy.
BATCH_ROWS = 2000


def ship(spark: SparkSession) -> SparkSession:
    """Send the package to the executors once a Spark context, as they may not see this file system."""
    sc, rows = spark.sparkContext, "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(rows, "10000")) <= BATCH_ROWS:
        spark.conf.set(rows, str(BATCH_ROWS))
    if getattr(sc, "_pagelift_shipped", False):
        return spark
    digest = hashlib.sha256()
    files = list(_files())
    for full, name in files:
        digest.update(name.encode() + open(full, "rb").read())
    path = os.path.join(tempfile.mkdtemp(prefix="pagelift-code-"), f"pagelift-{digest.hexdigest()[:12]}.zip")
    with zipfile.ZipFile(path, "w") as z:
        for full, name in files:
            z.write(full, name)
    sc.addPyFile(path)
    # processes that plan sources on this machine get no added files, but this path
    known = sc.environment.get("PYTHONPATH")
    sc.environment["PYTHONPATH"] = os.pathsep.join([os.path.dirname(ROOT), *([known] if known else [])])
    sc._pagelift_shipped = True
    return spark


def scratch(spark: SparkSession, label: str) -> str:
    """A new folder in the shared one, for output that lasts as long as this process."""
    path = f"{shared_dir(spark)}/{label}/{uuid.uuid4().hex}"
    atexit.register(_remove, path)
    return path


def _remove(path: str) -> None:
    from pyarrow import fs

    try:
        system, at = fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)
        system.delete_dir(at)
    except (OSError, ValueError):
        return  # never written, or in a store that only Spark reaches


def shared_dir(spark: SparkSession) -> str:
    """A folder that all executors see: the session's checkpoint folder.  Without one, a local session takes this machine's
    own, and a cluster is refused: its executors would write where nobody else reads."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found and not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return (found or os.path.join(tempfile.gettempdir(), "pagelift")).rstrip("/")
