"""Session-level helpers of the vector engine."""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Read-only tables that queries share within one application.
_stored: dict[tuple, DataFrame] = {}


_made: list = []


def _remove(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def _remove_made() -> None:
    """Delete the tables that this process has written to the shared folder."""
    for spark, path in _made:
        try:
            _remove(spark, path)
        except Exception:  # noqa: BLE001  the JVM may be gone already
            return
    _made.clear()


def at_exit(spark: SparkSession, path: str) -> str:
    """Have a path of the shared folder deleted when this process ends."""
    if not _made:
        atexit.register(_remove_made)
    _made.append((spark, path))
    return path


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or in a plain local session a folder of its own."""
    path = spark.sparkContext.getConf().get("spark.checkpoint.dir") or getattr(spark.sparkContext, "_own_shared_dir", None)
    if not path:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        path = tempfile.mkdtemp(prefix="blockgraph-")
        atexit.register(shutil.rmtree, path, ignore_errors=True)
        spark.sparkContext._own_shared_dir = path
    return path.rstrip("/")


#: Have Spark delete the shuffle files of an execution when it ends.
TIDY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


#: Rows and bytes of a batch that Spark sends to a Python worker.
BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"
BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"
#: Rows that a task holds when it reads Parquet.
READ_ROWS = "spark.sql.parquet.columnarReaderBatchSize"


@contextlib.contextmanager
def setting(spark: SparkSession, key: str, value: str):
    """Within this, actions run with a setting of the session."""
    before = spark.conf.get(key, None)
    spark.conf.set(key, value)
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


def tidy_shuffles(spark: SparkSession):
    """Within this, an action's shuffle files go as soon as it has ended."""
    return setting(spark, TIDY, "true")


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int = 1000, size: int = 1 << 20, read_rows: int = 64):
    """Within this, batches of ``rows`` rows and about ``size`` bytes at most go to
    Python, and ``read_rows`` are read at a time: the buffer of a batch is doubled
    as it fills, in every task, and the system gets little of it back."""
    with setting(spark, BATCH_ROWS, str(rows)), setting(spark, BATCH_BYTES, str(size)), setting(spark, READ_ROWS, str(read_rows)):
        yield


#: How Parquet is written when a row is up to megabytes of compressed bytes: as they
#: are, and pages and groups of rows end by their bytes after any row, where a page
#: would hold a hundred rows at least and a task all that it writes.
LARGE_ROWS = {
    "compression": "none", "parquet.enable.dictionary": "false", "parquet.page.size.row.check.min": "1", "parquet.page.size.row.check.max": "1",
    "parquet.block.size": str(4 << 20), "parquet.block.size.row.check.min": "1", "parquet.block.size.row.check.max": "1",
}


def stored(df: DataFrame, name: str = "table", partition_by: str | None = None, options: dict[str, str] | None = None) -> DataFrame:
    """Write to the shared folder and read back: the plan is cut there, a lost
    executor costs nothing that was written, and the shuffle files behind the
    table are deleted once it is whole."""
    spark = df.sparkSession
    path = at_exit(spark, f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}")
    w = df.write.options(**(options or {}))
    with tidy_shuffles(spark):
        (w.partitionBy(partition_by) if partition_by else w).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete stored tables that nothing reads any more."""
    for t in tables:
        path = getattr(t, "_stored_at", None)
        if path:
            _remove(t.sparkSession, path)


def stamp(spark: SparkSession, path: str) -> int:
    """When what a folder or file holds was last changed."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = where.getFileSystem(spark._jsc.hadoopConfiguration())
    return max([f.getModificationTime() for f in fs.listStatus(where)], default=0)


def once(spark: SparkSession, key: tuple, make) -> DataFrame:
    """A stored table made once for each application and key; a key names all
    that the table depends on, with the ``stamp`` of its input."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _stored:
        _stored[key] = make()
    return _stored[key]


def known(spark: SparkSession, key: tuple) -> bool:
    """Whether ``once`` has made the table of a key."""
    return (spark.sparkContext.applicationId, *key) in _stored
