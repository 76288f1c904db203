"""Settings of the iteration loop, set for its duration only and put back afterwards."""

from __future__ import annotations

import re
import tempfile
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession


@contextmanager
def loop_settings(spark: SparkSession, partitions: int) -> Iterator[None]:
    """Plans that keep the blocks where they are.

    Adaptive execution would forget the partitioning of a checkpointed vector and move the matrix again; an automatic
    broadcast would turn the vertical placement into b copies of the vector.
    """
    wanted = {
        "spark.sql.adaptive.enabled": "false",
        "spark.sql.autoBroadcastJoinThreshold": "-1",
        "spark.sql.shuffle.partitions": str(partitions),
        "spark.sql.join.preferSortMergeJoin": "true",
        "spark.sql.sources.bucketing.autoBucketedScan.enabled": "false",
    }
    before = {k: spark.conf.get(k, None) for k in wanted}
    try:
        for k, v in wanted.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or a folder of our own where it is unset and all executors are threads of the driver."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir is not set: no folder is known that all executors share")
        found = tempfile.mkdtemp(prefix="blockmv-")
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(found)
    return found


@contextmanager
def held(*frames: DataFrame) -> Iterator[None]:
    """Frames that are read several times, on executors' disks meanwhile; those that are persisted already stay as they are."""
    mine = [df.persist(StorageLevel.DISK_ONLY) for df in frames if df.storageLevel == StorageLevel.NONE]
    try:
        yield
    finally:
        for df in mine:
            df.unpersist()


def drop_folder(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


class Traffic:
    """Bytes that stages wrote for exchanges, as Spark itself counts them."""

    def __init__(self, spark: SparkSession) -> None:
        self._context = spark.sparkContext
        self._seen = -1
        self.taken()

    def taken(self) -> int:
        """Bytes since the last call, or since this was made."""
        sc, gateway = self._context._jsc.sc(), self._context._gateway
        sc.listenerBus().waitUntilEmpty()
        stages = sc.statusStore().stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), None)
        total, newest = 0, self._seen
        for k in range(stages.size()):  # the newest come first
            stage = stages.apply(k)
            if stage.stageId() <= self._seen:
                break
            newest = max(newest, stage.stageId())
            total += stage.shuffleWriteBytes()
        self._seen = newest
        return total


def reliable(df: DataFrame) -> DataFrame:
    """df written to the shared folder with its partitioning kept: lineage is cut, lost executors cost nothing."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def forget(df: DataFrame) -> None:
    """Delete the files of a frame that ``reliable`` returned and that nothing reads any more; others are left alone.

    Spark keeps checkpoints unless told otherwise, and an iteration would leave one copy of the vector per round.
    """
    plan = df._jdf.queryExecution().logical()
    if plan.getClass().getSimpleName() != "LogicalRDD":
        return
    file = plan.rdd().getCheckpointFile()
    if file.isDefined():
        spark = df.sparkSession
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(file.get())
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
