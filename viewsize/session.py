"""Session helpers."""

from __future__ import annotations

import os
import re
import tempfile
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()
_MADE: dict[str, list[str]] = {}  # scratch folders by application


#: A runtime setting of the session that bounds what a Python worker is handed at once; a lower one is left alone.
BATCH_BYTES = 8 << 20


def _bound_batches(spark: SparkSession) -> None:
    size = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.conf.get(size)
    if not (now.rstrip("b").isdigit() and 0 < int(now.rstrip("b")) <= BATCH_BYTES):
        spark.conf.set(size, f"{BATCH_BYTES}b")


def ship(spark: SparkSession) -> None:
    """Send this package's sources to the executors, once for each application, so that Python functions run wherever it isn't installed, and keep Arrow batches small."""
    _bound_batches(spark)
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = os.path.dirname(os.path.abspath(__file__))
    path = os.path.join(tempfile.mkdtemp(prefix="viewsize-"), "viewsize_sources.zip")
    with zipfile.ZipFile(path, "w") as z:
        for folder, _, names in os.walk(root):
            for name in sorted(names):
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.relpath(full, os.path.dirname(root)))
    spark.sparkContext.addPyFile(path)
    _SHIPPED.add(app)


def scratch(spark: SparkSession) -> str:
    """A new folder under the shared checkpoint folder. Where the session names none, one of this machine's is set up if all tasks run here; on a cluster that is an error."""
    ship(spark)
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="viewsize-")
        spark.sparkContext.setCheckpointDir(base)
    path = f"{base.rstrip('/')}/viewsize-{uuid.uuid4().hex}"
    _MADE.setdefault(spark.sparkContext.applicationId, []).append(path)
    return path


def settle(df: DataFrame, name: str = "table") -> DataFrame:
    """Write a result to the shared folder and read it back: lineage ends there, and a lost executor costs nothing done before it."""
    spark = df.sparkSession
    path = f"{scratch(spark)}/{name}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def clean(spark: SparkSession) -> int:
    """Delete the scratch tables that this application has written, once no result that reads them is needed any more; gives their number."""
    made = _MADE.pop(spark.sparkContext.applicationId, [])
    conf = spark._jsc.hadoopConfiguration()
    for path in made:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(conf).delete(at, True)
    return len(made)
