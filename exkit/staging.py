"""Tables that cut lineage: written once to the folder all executors share, then read back.

The folder is ``spark.checkpoint.dir`` of the running session. Only where that
setting is absent and the master is local (tests on one machine) a temporary
folder is made, and it is removed when the process ends; on a cluster its
absence is an error.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Bytes of a batch that goes to a Python worker while a table is staged.
BATCH_KEY, BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", 8 << 20
_own: dict[str, str] = {}
_lock, _held, _scopes = threading.Lock(), {"n": 0, "before": ""}, threading.local()


@contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """Arrow batches of at most ``BATCH_BYTES`` meanwhile; the session's own setting comes back when the last user leaves."""
    with _lock:
        if not _held["n"]:
            _held["before"] = spark.conf.get(BATCH_KEY)
            spark.conf.set(BATCH_KEY, str(BATCH_BYTES))
        _held["n"] += 1
    try:
        yield
    finally:
        with _lock:
            _held["n"] -= 1
            if not _held["n"]:
                spark.conf.set(BATCH_KEY, _held["before"])


def shared_dir(spark: SparkSession) -> str:
    """URI of the folder that the driver and every executor can read and write."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    app = spark.sparkContext.applicationId
    if app not in _own:
        folder = tempfile.mkdtemp(prefix="exkit-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        _own[app] = f"file://{folder}"
        spark.sparkContext.setCheckpointDir(_own[app])
    return _own[app]


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/exkit/{name}-{uuid.uuid4().hex}"


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and return a scan of what was written.

    The write is a Spark job with its own commit, so lost executors cost a task
    retry and never a partial table; readers start from files, not from lineage.
    """
    spark = df.sparkSession
    path = new_path(spark, name)
    with small_batches(spark):
        df.write.parquet(path)
    for made in getattr(_scopes, "open", []):
        made.append(path)
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def recorded(made: list[str]) -> Iterator[None]:
    """Adds the path of every table that this thread stages meanwhile to ``made``."""
    scopes = _scopes.__dict__.setdefault("open", [])
    scopes.append(made)
    try:
        yield
    finally:
        scopes.pop()


def delete(spark: SparkSession, paths: list[str]) -> None:
    """Remove staged tables that nothing reads any more."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for p in paths:
        path = jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(conf).delete(path, True)


def bytes_of(spark: SparkSession, path: str) -> int:
    """Bytes of the files below ``path``, 0 if it is not there; their contents are not read."""
    own = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = own.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return fs.getContentSummary(own).getLength() if fs.exists(own) else 0


def release(spark: SparkSession) -> None:
    """Delete every staged table of this session's shared folder."""
    delete(spark, [f"{shared_dir(spark)}/exkit"])
