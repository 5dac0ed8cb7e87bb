"""Tables in the storage that driver and executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Where the session names none, a temporary one serves on a single
    machine; on a cluster executors would not see each other's files, so this is an error there."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = tempfile.mkdtemp(prefix="rareblock-shared-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def _sweep() -> None:
    for spark, path in _written:
        try:
            remove(spark, path)
        except Exception:  # the session has ended before the interpreter
            local = path.removeprefix("file://").removeprefix("file:")
            if local.startswith("/"):
                shutil.rmtree(local, ignore_errors=True)


atexit.register(_sweep)


def settle(df: DataFrame, label: str = "step") -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: the lineage is cut, a lost executor
    costs no recomputation, and later readers prune columns. The files go when release() is called with what
    this returned, else when the driver ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.append((spark, path))
    made = spark.read.schema(df.schema).parquet(path)
    made._settled_at = path
    return made


def release(df: DataFrame) -> None:
    """Delete the table that settle() made df of. For steps whose successor is written; frames that settle() did not
    make, and tables of settle_at(), stay."""
    path = getattr(df, "_settled_at", None)
    if path is not None:
        df._settled_at = None
        _written[:] = [w for w in _written if w[1] != path]
        remove(df.sparkSession, path)


def settle_alone(spark: SparkSession, make: Callable[[], DataFrame], label: str = "step") -> DataFrame:
    """settle() what make() returns and delete the tables that were written for it."""
    before = {path for _, path in _written}
    made = settle(make(), label)
    for _, path in [w for w in _written if w[1] not in before and w[1] != made._settled_at]:
        _written[:] = [w for w in _written if w[1] != path]
        remove(spark, path)
    collect(spark)
    return made


def collect(spark: SparkSession) -> None:
    """Have the shuffle files of finished steps deleted now, not when the driver's JVM next runs short of memory."""
    spark.sparkContext._jvm.System.gc()


def _file(spark: SparkSession, path: str):
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at, at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def claim(spark: SparkSession, folder: str, stamp: str) -> None:
    """Note in a folder of settle_at() tables what run they are of, or check it: a folder of another run is an error."""
    at, files = _file(spark, f"{folder}/_run")
    if files.exists(at):
        stream = files.open(at)
        found = stream.readUTF()
        stream.close()
        if found != stamp:
            raise ValueError(f"{folder} holds the steps of another run: other settings, columns or rows")
        return
    stream = files.create(at, True)
    stream.writeUTF(stamp)
    stream.close()


def settle_at(df: DataFrame, path: str) -> DataFrame:
    """settle() at a path that the caller names; what a finished earlier run left there is read instead. The caller
    claims the folder first."""
    spark = df.sparkSession
    at, files = _file(spark, f"{path}/_SUCCESS")
    if not files.exists(at):
        df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)
