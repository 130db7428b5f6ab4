"""Session helpers: local sessions for tests and benches, and the shared folder for cut lineage."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def local_session(cores: int | str = 4, *, shuffle_partitions: int = 8, memory: str = "4g") -> SparkSession:
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.driver.memory", memory)
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )


def shared_dir(spark: SparkSession) -> str:
    """The cluster's spark.checkpoint.dir; a temporary folder only where that is unset."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = getattr(shared_dir, "own", None)
        if base is None:
            base = shared_dir.own = tempfile.mkdtemp(prefix="blockrecover-")
            atexit.register(shutil.rmtree, base, ignore_errors=True)
    return base.rstrip("/")


def snapshot(df: DataFrame, name: str, *, compression: str | None = None) -> DataFrame:
    """A versioned table in the shared folder in place of ``df``: cuts lineage at a barrier and survives executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path, compression=compression)
    return spark.read.schema(df.schema).parquet(path)


def discard(table: DataFrame) -> None:
    """Deletes the files of a snapshot that no table needs any more."""
    spark = table.sparkSession
    jvm = spark.sparkContext._jvm
    for at in {f.rpartition("/")[0] for f in table.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(jvm.java.net.URI(at))
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def partitions_for(spark: SparkSession, size: int, *, each: int = 8 << 20) -> Iterator[int]:
    """Inside, shuffles have as many partitions as ``size`` bytes fill by ``each``, one for each core at least and no more than
    the session has: every task of a shuffle opens a file for each partition, which for little data costs more than the data."""
    key = "spark.sql.shuffle.partitions"
    before = spark.conf.get(key)
    n = max(1, min(int(before), max(spark.sparkContext.defaultParallelism, -(-size // each))))
    spark.conf.set(key, str(n))
    try:
        yield n
    finally:
        spark.conf.set(key, before)


@contextmanager
def settings(spark: SparkSession, **values: str) -> Iterator[None]:
    """Inside, these settings of spark.sql (dots as two underscores) hold."""
    named = {f"spark.sql.{k.replace('__', '.')}": v for k, v in values.items()}
    before = {k: spark.conf.get(k) for k in named}
    for k, v in named.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


def release(spark: SparkSession) -> None:
    """Shuffle files that no table needs any more go when the driver's JVM has collected what named them: done here, as
    a driver with little to do may not collect for long while executors' disks fill."""
    spark.sparkContext._jvm.System.gc()
