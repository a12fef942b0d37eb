"""Shared storage for intermediate tables.

Everything that must outlive a lost executor goes to the folder that the
session names in ``spark.checkpoint.dir``; where that is unset a temporary
folder is chosen if the master is local (tests, one machine), and any other
master is refused, as its executors would not see such a folder.
"""

from __future__ import annotations

import contextlib
import gc
import io
import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_FALLBACK: dict[str, str] = {}
_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package's source to the executors, once per application.

    Python functions that run there are found by name, so the package must be
    importable where a cluster does not have it installed.
    """
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = Path(__file__).resolve().parent.parent
    buffer = io.BytesIO()
    with zipfile.ZipFile(buffer, "w", zipfile.ZIP_DEFLATED) as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f.relative_to(root.parent))
    path = os.path.join(tempfile.mkdtemp(prefix="veil-source-"), "veil_source.zip")
    Path(path).write_bytes(buffer.getvalue())
    spark.sparkContext.addPyFile(path)  # served by the driver
    _SHIPPED.add(app)


def in_arrow(df: DataFrame, f: Callable, ddl: str, *args: object) -> DataFrame:
    """``mapInArrow`` of ``f(batches, arrow_schema, *args)`` with a result of ``ddl``."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    ship(df.sparkSession)
    schema = to_arrow_schema(_parse_datatype_string(ddl))

    def run(batches):
        try:
            yield from f(batches, schema, *args)
        finally:
            _give_back()

    return df.mapInArrow(run, ddl)


def _give_back() -> None:
    """Return freed memory to the system: Python workers stay alive between tasks."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass


#: Rows of an Arrow batch while a table is written; texts are long, batches are held on both sides.
BATCH_ROWS = 1000
_BATCH_CONF = "spark.sql.execution.arrow.maxRecordsPerBatch"


@contextlib.contextmanager
def small_batches(spark: SparkSession):
    """Batches of at most ``BATCH_ROWS`` rows for what runs inside."""
    old = spark.conf.get(_BATCH_CONF)
    small = 0 < int(old) <= BATCH_ROWS
    if not small:
        spark.conf.set(_BATCH_CONF, str(BATCH_ROWS))
    try:
        yield
    finally:
        if not small:
            spark.conf.set(_BATCH_CONF, old)


def shared_root(spark: SparkSession) -> str:
    """The folder all executors share."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    app = spark.sparkContext.applicationId
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if app not in _FALLBACK:
        _FALLBACK[app] = "file://" + tempfile.mkdtemp(prefix="veil-")
    return _FALLBACK[app]


def shared_path(spark: SparkSession, label: str) -> str:
    """A fresh path below the shared folder."""
    return f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` once as Parquet in the shared folder and return a reader of it.

    Cuts the lineage: later stages read the files, so neither a lost executor
    nor a second consumer repeats the work that made them.
    """
    spark = df.sparkSession
    path = shared_path(spark, label)
    with small_batches(spark):
        df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_at = path
    return out


def discard(df: DataFrame) -> None:
    """Delete what ``materialize`` wrote, once nothing reads it any more, and let go of shuffles that no plan holds.

    Spark removes a shuffle's files when the driver's collector finds its plan
    unused, which may be late; a large job asks for it between its steps.
    """
    spark = df.sparkSession
    drop_path(spark, df.written_at)
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def drop_written(*tables: DataFrame) -> None:
    """Delete tables that ``materialize`` wrote and that no plan reads any more."""
    for t in tables:
        drop_path(t.sparkSession, t.written_at)


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a path of the shared folder through Hadoop's file system."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
