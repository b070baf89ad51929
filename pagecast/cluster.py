"""What every job needs from the cluster: a shared scratch folder, written
intermediate tables, and the package itself on the Python workers.

Intermediate results are cut by writing them as Parquet below the folder that
the session names in ``spark.checkpoint.dir`` (all executors see it), never by
a local checkpoint: a lost executor then costs a re-read, not the job.
"""

from __future__ import annotations

import os
import re
import tempfile
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession

_OWN_DIR: list[str] = []
_SHIPPED: set[str] = set()
#: Rows of a batch that a Python worker gets, at most (a setting of queries, not of the session's start).
BATCH_ROWS = 2000
#: Bytes of such a batch, about: rows are whole texts, or blocks of them.
BATCH_BYTES = 8 << 20


def scratch_root(spark: SparkSession) -> str:
    """The shared folder; a private one only where the session names none and
    driver and workers are one process. Elsewhere a folder has to be named."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get().rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir has to name a folder that all executors share")
    if not _OWN_DIR:
        _OWN_DIR.append(tempfile.mkdtemp(prefix="pagecast-"))
        spark.sparkContext.setCheckpointDir(f"file://{_OWN_DIR[0]}")
    return f"file://{_OWN_DIR[0]}"


def scratch_path(spark: SparkSession, label: str) -> str:
    return f"{scratch_root(spark)}/{label}-{uuid.uuid4().hex[:12]}"


class Written:
    """A table written to the scratch folder; ``df`` reads it back."""

    def __init__(self, df: DataFrame, label: str, compression: str = "snappy"):
        self.spark = df.sparkSession
        self.path = scratch_path(self.spark, label)
        self.schema = df.schema
        df.write.option("compression", compression).parquet(self.path)

    @property
    def df(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        drop_path(self.spark, self.path)


def exists(spark: SparkSession, path: str) -> bool:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(target)


def full_address(spark: SparkSession, path: str) -> str:
    """The path with its file system, as workers outside the JVM need it."""
    home = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    address = home.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).makeQualified(home).toString()
    return re.sub(r"^file:/+", "file:///", address)


def drop_path(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def ship(spark: SparkSession) -> None:
    """Hand this package to the workers once per application, so that a
    cluster without it on its path can run the vectorised stages. Batches to
    the workers are kept small: whole documents are long rows, and both sides
    of the pipe hold a batch. For that, and for as long as the session lives,
    its settings of rows and bytes in a batch are lowered to these bounds."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    most = spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch").rstrip("b")
    if most.isdigit() and int(most) > BATCH_BYTES:
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", f"{BATCH_BYTES}b")
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    here = os.path.dirname(os.path.abspath(__file__))
    target = os.path.join(tempfile.mkdtemp(prefix="pagecast-ship-"), "pagecast_ship.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for folder, _, names in os.walk(here):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.relpath(full, os.path.dirname(here)))
    spark.sparkContext.addPyFile(target)
    _SHIPPED.add(app)


def slots(spark: SparkSession) -> int:
    return max(2, spark.sparkContext.defaultParallelism)
