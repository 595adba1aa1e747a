"""Session helpers: table access, shipping the package to executors, shared scratch tables."""

from __future__ import annotations

import atexit
import io
import os
import re
import shutil
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_shipped: set[str] = set()


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


ARROW_ROWS = "1000"


def ship_package(spark: SparkSession) -> None:
    """Give the executors this package, once per application, so that workers can import it.

    Rows here hold whole texts, so batches between the JVM and Python are kept to ``ARROW_ROWS`` rows
    where the session has Spark's default.
    """
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", ARROW_ROWS)
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = Path(__file__).resolve().parent
    if root.suffix == ".zip" or not root.is_dir():
        return
    buffer = io.BytesIO()
    with zipfile.ZipFile(buffer, "w", zipfile.ZIP_DEFLATED) as archive:
        for path in sorted(root.rglob("*.py")):
            archive.write(path, str(Path(root.name) / path.relative_to(root)))
    folder = tempfile.mkdtemp(prefix="coarsesample-")
    atexit.register(shutil.rmtree, folder, True)
    target = Path(folder) / f"coarsesample-{uuid.uuid4().hex[:8]}.zip"
    target.write_bytes(buffer.getvalue())
    spark.sparkContext.addPyFile(str(target))
    _shipped.add(app)


@contextmanager
def large_batches(spark: SparkSession, rows: str = "10000") -> Iterator[None]:
    """Jobs within hand Python larger batches: for rows of numbers and short strings, where a batch's fixed cost counts."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    if before == ARROW_ROWS:
        spark.conf.set(key, rows)
    try:
        yield
    finally:
        spark.conf.set(key, before)


def scratch_path(spark: SparkSession, tag: str) -> str:
    """A fresh folder below the cluster's shared checkpoint folder.

    Where ``spark.checkpoint.dir`` is unset, a local folder is made if the master is local, as in
    tests; it goes at exit. On a cluster that is an error, for executors would not see each other's files.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not base:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        base = _local_base()
    return f"{base.rstrip('/')}/coarsesample/{tag}-{uuid.uuid4().hex}"


_local: list[str] = []


def _local_base() -> str:
    if not _local:
        _local.append(tempfile.mkdtemp(prefix="coarsesample-scratch-"))
        atexit.register(shutil.rmtree, _local[0], True)
    return "file://" + os.path.abspath(_local[0])


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` as Parquet to shared scratch and read it again: lineage ends, lost executors lose nothing."""
    spark = df.sparkSession
    path = scratch_path(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def settle(spark: SparkSession) -> None:
    """Free what finished jobs have left in the driver's JVM.

    The plans of wide aggregations are garbage once their jobs end, but until it is collected the heap
    grows for it, up to its limit, and doesn't shrink by itself. Takes some 0.2 s.
    """
    spark.sparkContext._jvm.java.lang.System.gc()


def bytes_under(spark: SparkSession, path: str) -> int:
    """Bytes of all files below a path, in whatever store it is."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(at).getLength()


def broadcast_if_small(df: DataFrame, most_rows: int = 1_000_000) -> DataFrame:
    """``df`` marked for broadcast if its rows, which are counted, are few; else as it is, for a shuffled join."""
    return F.broadcast(df) if df.limit(most_rows + 1).count() <= most_rows else df
