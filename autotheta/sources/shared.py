"""The folder that driver and executors share, and tables kept there to cut lineage.

The folder is the one the session names in ``spark.checkpoint.dir``. Only where that is unset and all runs on one
machine (tests) a temporary one is made; on a cluster that is an error, as executors would write to their own disks. Tables
written there survive lost executors, unlike cached blocks or local checkpoints. ``discard`` deletes one that is not
needed any more, ``clean`` all that this application has written.
"""

from __future__ import annotations

import os
import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}
#: Paths in the shared folder by application.
_WRITTEN: dict[str, set[str]] = {}


def shared_dir(spark: SparkSession) -> str:
    """URI of the shared folder, without a slash at its end."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        app = spark.sparkContext.applicationId
        if app not in _LOCAL:
            _LOCAL[app] = "file://" + tempfile.mkdtemp(prefix="autotheta-")
        found = _LOCAL[app]
    return found.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    """A path below the shared folder that nothing else uses."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _WRITTEN.setdefault(spark.sparkContext.applicationId, set()).add(path)
    return path


def keep(df: DataFrame, name: str = "table", codec: str | None = None) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and return it read again: its lineage ends there.

    ``codec`` compresses it, else what the session has for Parquet.
    """
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path, compression=codec)
    out = spark.read.schema(df.schema).parquet(path)
    out.kept_at = path
    return out


def delete(spark: SparkSession, path: str) -> None:
    """Delete a folder that ``new_path`` named."""
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)
    _WRITTEN.get(spark.sparkContext.applicationId, set()).discard(path)


def exists(df: DataFrame) -> bool:
    """Whether a table of ``keep`` is still there."""
    return exists_at(df.sparkSession, df.kept_at)


def exists_at(spark: SparkSession, path: str) -> bool:
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    return hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).exists(hadoop)


def discard(*tables: DataFrame | None) -> None:
    """Delete tables of ``keep`` that nothing reads any more."""
    for df in tables:
        if getattr(df, "kept_at", None):
            delete(df.sparkSession, df.kept_at)


def clean(spark: SparkSession) -> None:
    """Delete all that this application has written to the shared folder; results that read from there end with it."""
    for path in list(_WRITTEN.get(spark.sparkContext.applicationId, ())):
        delete(spark, path)


#: Spark's setting by which a query deletes its shuffle files when it ends, and not when the driver's garbage is collected.
CLEANUP_CONF = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def shuffles_deleted(spark: SparkSession):
    """Queries made and run inside leave no shuffle files; for those whose results are written or collected at once."""
    before = spark.conf.get(CLEANUP_CONF, None)
    spark.conf.set(CLEANUP_CONF, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(CLEANUP_CONF)
        else:
            spark.conf.set(CLEANUP_CONF, before)


def is_local(uri: str) -> bool:
    return uri.startswith(("file:", "/"))


def open_store(uri: str):
    """``(filesystem, path)`` of pyarrow for a URI: local files, HDFS, S3, GCS. Needs no Spark."""
    from pyarrow import fs

    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri) if "://" in uri else (fs.LocalFileSystem(), os.path.abspath(uri))


_SHIPPED: set[str] = set()
#: Bytes of an Arrow batch, where the session has Spark's own default.
BATCH_CONF, BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", "16m"


def ship(spark: SparkSession) -> None:
    """Give executors this package, once an application: their Python need not find it by itself.

    Sets the bytes of Arrow batches too, a setting of the running session, if it stands at its default.
    """
    import zipfile
    from pathlib import Path

    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    # Batches of texts this large are enough for arrays, and two a core fit beside a small heap.
    if spark.conf.get(BATCH_CONF, "64m") in ("64m", "67108864b", "67108864"):
        spark.conf.set(BATCH_CONF, BATCH_BYTES)
    root = Path(__file__).resolve().parents[1]
    path = os.path.join(tempfile.mkdtemp(prefix="autotheta-"), "autotheta.zip")
    with zipfile.ZipFile(path, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    spark.sparkContext.addPyFile(path)
    _SHIPPED.add(app)


def map_arrow(df: DataFrame, run, schema: str) -> DataFrame:
    """``mapInArrow`` with this package on the executors, whose Python gives memory back after each task."""
    ship(df.sparkSession)

    def tidy(batches):
        yield from run(batches)
        release()

    return df.mapInArrow(tidy, schema)


def release() -> None:
    """Give memory that is free in this process back to the system: workers live on for later tasks."""
    import ctypes

    import pyarrow

    pyarrow.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)
