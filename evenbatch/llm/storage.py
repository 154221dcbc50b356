"""Where operators keep what must survive a lost executor, and what they send to all executors."""

from __future__ import annotations

import atexit
import uuid

from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession

#: Used only in local mode, where the session names no shared folder: there are no other machines then.
LOCAL_DEFAULT = "/tmp/checkpoints/evenbatch"

_written: set[str] = set()
_sent: list[Broadcast] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: that of the session's settings or else of its context. In local mode a default
    folder is used where neither names one; elsewhere that is an error, as a machine's own folder can't be read by others."""
    context = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not named:
        if not context.master.startswith("local[") and context.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        named = LOCAL_DEFAULT
        context.setCheckpointDir(named)
    return named.rstrip("/")


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh path under the shared folder, which goes when the application ends."""
    path = f"{shared_dir(spark)}/evenbatch-{label}-{uuid.uuid4().hex}"
    _written.add(path)
    return path


def materialise(df: DataFrame, label: str, partition_by: tuple[str, ...] = ()) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: lineage ends in replicated storage."""
    path = scratch(df.sparkSession, label)
    writer = df.write
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def discard(*frames: DataFrame) -> None:
    """Delete what materialise() has written for frames that nothing reads any more."""
    for df in frames:
        drop_path(df.sparkSession, df.scratch_path)


def drop_path(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    _written.discard(path)


def send(spark: SparkSession, value) -> Broadcast:
    """A broadcast that release() takes off the executors."""
    _sent.append(spark.sparkContext.broadcast(value))
    return _sent[-1]


def release() -> None:
    """Free the executors' copies of all that was sent so far; what is still used is fetched again."""
    while _sent:
        try:
            _sent.pop().unpersist()
        except Exception:  # noqa: BLE001  (its session has ended)
            continue


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@atexit.register
def _sweep() -> None:
    spark = SparkSession.getActiveSession()
    for path in list(_written) if spark is not None else []:
        try:
            drop_path(spark, path)
        except Exception:  # noqa: BLE001  (the JVM is gone)
            return
