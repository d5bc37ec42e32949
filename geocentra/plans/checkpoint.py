"""Where lineage is cut: tables in a folder that all executors share."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

from geocentra.errors import ParameterError


def shared_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder. A folder of the machine serves only where the driver is the only machine, as in tests."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None and not sc.master.startswith("local"):
            raise ParameterError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="spark-checkpoint-"))
    return sc.getCheckpointDir()


_FOLDERS: dict[str, str] = {}


def own_folder(spark: SparkSession) -> str:
    """A folder of this driver's inside the shared one, deleted when the driver ends."""
    app = spark.sparkContext.applicationId
    if app not in _FOLDERS:
        _FOLDERS[app] = f"{shared_folder(spark)}/tables-{uuid.uuid4().hex}"
        atexit.register(delete_folder, spark, _FOLDERS[app])
    return _FOLDERS[app]


def delete_folder(spark: SparkSession, folder: str) -> None:
    with contextlib.suppress(Exception):  # the session may have ended first
        jvm = spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def cut(df: DataFrame) -> DataFrame:
    """The rows, written once as a table to the shared folder and read back: a lost executor costs a read.

    (A checkpoint would compute its last stage twice.)
    """
    path = f"{own_folder(df.sparkSession)}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextlib.contextmanager
def fixed_plan(spark: SparkSession) -> Iterator[None]:
    """Adaptive replanning off: a checkpoint then keeps its plan's partitioning, and later joins do not shuffle it again."""
    was = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        yield
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", was)


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int = 1000) -> Iterator[None]:
    """Fewer rows in an Arrow batch while long texts go to Python: the batches are buffered on both sides."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    was = spark.conf.get(key)
    spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, was)


def cut_dealt(df: DataFrame) -> DataFrame:
    """The rows checkpointed with the partitioning of their plan, for a plan that ends in, or keeps, an exchange."""
    shared_folder(df.sparkSession)
    with fixed_plan(df.sparkSession):
        return df.checkpoint(eager=True)


def cut_by(df: DataFrame, parts: int, *keys: str) -> DataFrame:
    """The rows dealt to `parts` partitions by `keys` and checkpointed, so that they stay dealt."""
    return cut_dealt(df.repartition(parts, *keys))
