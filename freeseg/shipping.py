"""Sends the package to the executors, which need not see the driver's folders."""

from __future__ import annotations

import os
import re
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_shipped: set[str] = set()
#: Bytes of rows that go to a Python worker at once, where the session has Spark's default.
ARROW, DEFAULT, BATCH = "spark.sql.execution.arrow.maxBytesPerBatch", ("67108864b", "64MB", "64m"), "8m"


def ship(spark: SparkSession) -> None:
    """Adds this package to the application's Python files, once for each application, and keeps batches for Python workers small."""
    sc = spark.sparkContext
    if spark.conf.get(ARROW, DEFAULT[0]) in DEFAULT:
        spark.conf.set(ARROW, BATCH)
    if sc.applicationId in _shipped:
        return
    root = Path(__file__).resolve().parent
    fd, name = tempfile.mkstemp(prefix="freeseg", suffix=".zip")
    with os.fdopen(fd, "wb") as out, zipfile.ZipFile(out, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    sc.addPyFile(os.path.abspath(name))
    _shipped.add(sc.applicationId)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset a temporary one is made if the master is local, as in tests; a cluster has to name one."""
    sc = spark.sparkContext
    at = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not at:
        if not re.match(r"local(\[[^\]]*\])?$", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        at = tempfile.mkdtemp(prefix="freeseg-shared")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(at)
    return at


def work_dir(spark: SparkSession) -> str:
    """Where this application's intermediate tables are, in the shared folder."""
    return f"{shared_dir(spark).rstrip('/')}/freeseg-{spark.sparkContext.applicationId}"


def release(spark: SparkSession) -> None:
    """Deletes the intermediate tables of this application, once the results that were made from them are written."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(work_dir(spark))
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def cut(df):
    """df with its lineage cut by a reliable checkpoint in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)
