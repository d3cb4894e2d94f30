"""Tables that a plan writes for itself: barriers, rounds, and representations that later plans read again.

All of them lie in the folder that the driver and the executors share (``spark.checkpoint.dir``).
"""

from __future__ import annotations

import atexit
import hashlib
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType


def shared_folder(spark: SparkSession) -> str:
    """The cluster's shared folder; only a session on one machine without it gets a folder of its own."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir is not set; it must name a folder that all executors share")
    made = spark.sparkContext._jsc.sc().getCheckpointDir()
    if made.isEmpty():
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="shared-"))
        made = spark.sparkContext._jsc.sc().getCheckpointDir()
    return made.get().rstrip("/")


def _file(spark: SparkSession, path: str):
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), at


def remove(spark: SparkSession, path: str) -> None:
    system, at = _file(spark, path)
    system.delete(at, True)


def new_path(spark: SparkSession, name: str, folder: str | None = None) -> str:
    """A fresh path in the shared folder; what is there goes when the driver ends."""
    path = f"{folder or shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    atexit.register(lambda: spark.sparkContext._jsc is not None and remove(spark, path))
    return path


def write(df: DataFrame, path: str) -> DataFrame:
    """Write ``df`` to ``path`` and read it back: its plan is evaluated once and its lineage ends."""
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def barrier(df: DataFrame, folder: str | None = None) -> DataFrame:
    """Write and read back: what stands below is evaluated once, whatever reads it."""
    return write(df, new_path(df.sparkSession, "barrier", folder))


def version_of(spark: SparkSession, path: str) -> str:
    """Changes whenever a file below ``path`` does: names, lengths and times of its files."""
    system, at = _file(spark, path)
    found = []
    each = system.listFiles(at, True)
    while each.hasNext():
        status = each.next()
        found.append(f"{status.getPath().getName()} {status.getLen()} {status.getModificationTime()}")
    return hashlib.sha256("\n".join(sorted(found)).encode()).hexdigest()


def representation(spark: SparkSession, producer: str, version: str, inputs: str, build: Callable[[], DataFrame], folder: str | None = None) -> DataFrame:
    """A derived representation of ``inputs`` (a path), made by ``producer`` in ``version``: read if it is stored, made and stored if not.

    Rows are stored under a key of producer, version and the state of the input files, so another version or changed input makes a new one.
    The write is committed by a rename, so an interrupted one leaves nothing that a reader takes for whole.
    """
    key = hashlib.sha256("\x00".join([producer, version, inputs, version_of(spark, inputs)]).encode()).hexdigest()[:32]
    path = f"{folder or shared_folder(spark)}/representations/{producer}-{key}"
    system, at = _file(spark, path)
    if not system.exists(at):
        draft = f"{path}.{uuid.uuid4().hex}"
        build().write.parquet(draft)
        if not system.rename(_file(spark, draft)[1], at):
            remove(spark, draft)
    return spark.read.parquet(path)


def batches(spark: SparkSession, at: str, schema: StructType) -> DataFrame:
    """All batches stored below ``at``."""
    system, folder = _file(spark, at)
    found = [str(x.getPath()) for x in system.listStatus(folder) if x.getPath().getName().startswith("batch-")] if system.exists(folder) else []
    return spark.read.schema(schema).parquet(*found) if found else spark.createDataFrame([], schema)


def append_batch(df: DataFrame, at: str) -> None:
    """Add a batch: it is written beside the others and renamed when it is whole."""
    spark, name = df.sparkSession, uuid.uuid4().hex
    df.write.parquet(f"{at}/draft-{name}")
    system, draft = _file(spark, f"{at}/draft-{name}")
    system.rename(draft, _file(spark, f"{at}/batch-{name}")[1])
