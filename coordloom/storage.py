"""Shared storage for iterative jobs: state is written as a table each round, so no lineage builds up."""

from __future__ import annotations

import contextlib
import tempfile
import threading
import uuid
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession, tag: str) -> str:
    """A fresh folder under ``spark.checkpoint.dir``. Where that is unset a temporary folder serves on a local master only: elsewhere executors wouldn't share it."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        if current.isDefined():
            root = current.get()
        elif spark.sparkContext.master.startswith("local"):
            root = tempfile.mkdtemp(prefix="coordloom-")
            spark.sparkContext.setCheckpointDir(root)
        else:
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"{root.rstrip('/')}/{tag}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write to the shared folder and read back."""
    path = shared_dir(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(spark: SparkSession, path: str) -> None:
    """Delete a folder of the shared storage."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


_lock = threading.Lock()
_held: dict[tuple, list] = {}


@contextlib.contextmanager
def settings(spark: SparkSession, values: dict[str, str]) -> Iterator[None]:
    """Runtime SQL settings for what is planned and run inside; the session's own come back afterwards, with the last of several threads that ask for the same."""
    who = (id(spark._jsparkSession), frozenset(values.items()))
    with _lock:
        if who not in _held:
            _held[who] = [0, {k: spark.conf.get(k, None) for k in values}]
            for k, v in values.items():
                spark.conf.set(k, v)
        _held[who][0] += 1
    try:
        yield
    finally:
        with _lock:
            _held[who][0] -= 1
            if not _held[who][0]:
                for k, v in _held.pop(who)[1].items():
                    spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def at_once(jobs: list[Callable], threads: int) -> list:
    """The results of independent jobs, so many at a time: for runs of one task each, which a cluster can do side by side."""
    with ThreadPoolExecutor(max(1, threads)) as pool:
        return [f.result() for f in [pool.submit(j) for j in jobs]]


#: What keeps a join and a sort of bucketed tables within their buckets: one file a bucket, already sorted, joined as it lies.
CO_LOCATED = {
    "spark.sql.sources.bucketing.autoBucketedScan.enabled": "false",
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.sql.legacy.bucketedTableScan.outputOrdering": "true",
    "spark.sql.autoBroadcastJoinThreshold": "-1",
    "spark.sql.adaptive.autoBroadcastJoinThreshold": "-1",
}

#: Rows that go to Python at once. Spark sizes up the whole Arrow batch for each row of lists that it adds, so large batches of short rows cost their square; the byte limit stays.
SMALL_BATCHES = {"spark.sql.execution.arrow.maxRecordsPerBatch": "256"}


class Bucketed:
    """A table of the shared folder with one bucket per slot, sorted by (slot, bid) inside."""

    def __init__(self, df: DataFrame, tag: str, buckets: int, parts: tuple[str, ...] = ()):
        self.spark, self.path = df.sparkSession, shared_dir(df.sparkSession, tag)
        self.name = f"coordloom_{tag}_{uuid.uuid4().hex}"
        self.schema = df.schema
        writer = df.write.bucketBy(buckets, "slot").sortBy("slot", "bid").option("path", self.path).option("parquet.block.size", str(8 << 20))
        (writer.partitionBy(*parts) if parts else writer).saveAsTable(self.name)

    def frame(self) -> DataFrame:
        return self.spark.table(self.name)

    def plain(self) -> DataFrame:
        """The same rows read as files, split by size and not by bucket."""
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
        discard(self.spark, self.path)
