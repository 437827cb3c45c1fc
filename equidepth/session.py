"""A local session for tests and benches, and the folder for intermediate tables; on a cluster the given session is used as it is."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession


_made: ContextVar[list[str] | None] = ContextVar("_made", default=None)


def local_session(cores: int | None = None, **extra: str) -> SparkSession:
    cores = cores or int(os.environ.get("BENCH_CPUS", "8"))
    b = SparkSession.builder.master(f"local[{cores}]").appName("equidepth")
    conf = {
        "spark.sql.shuffle.partitions": str(cores), "spark.sql.adaptive.enabled": "true", "spark.sql.session.timeZone": "UTC",
        "spark.ui.enabled": "false", "spark.driver.memory": "8g", "spark.sql.execution.arrow.pyspark.enabled": "true", "spark.ui.showConsoleProgress": "false",
    }
    for k, v in (conf | extra).items():
        b = b.config(k, v)
    spark = b.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def work_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: spark.checkpoint.dir. Only a local master may go without; it gets one of its own."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    have = spark.sparkContext._jsc.sc().getCheckpointDir()
    if have.isDefined():
        return have.get().rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    base = tempfile.mkdtemp(prefix="equidepth-")
    spark.sparkContext.setCheckpointDir(base)
    return base


def scratch(spark: SparkSession, tag: str) -> str:
    """A path of our own in the shared folder."""
    return f"{work_dir(spark)}/equidepth-{tag}-{uuid.uuid4().hex}"


def _place(spark: SparkSession, path: str):
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    return place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), place


def drop_at_exit(spark: SparkSession, path: str) -> None:
    """Remove what was written at path when the driver ends; frames may read it until then."""
    files, place = _place(spark, path)
    files.deleteOnExit(place)
    if (own := _made.get()) is not None:
        own.append(path)


def drop(spark: SparkSession, path: str) -> None:
    """Remove what was written at path now: no frame may read it any more."""
    files, place = _place(spark, path)
    files.delete(place, True)
    files.cancelDeleteOnExit(place)


@contextmanager
def made_here() -> Iterator[list[str]]:
    """The paths that were handed to drop_at_exit inside, for those who can drop them earlier."""
    outer, own = _made.get(), []
    token = _made.set(own)
    try:
        yield own
    finally:
        _made.reset(token)
        if outer is not None:
            outer.extend(own)


@contextmanager
def shuffles_freed(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of a query that runs inside go when it ends, not when the driver happens to collect its garbage."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, before) if before is not None else spark.conf.unset(name)


def written(df: DataFrame, tag: str) -> DataFrame:
    """df, written to the shared folder and read from there: cuts lineage, survives lost executors."""
    spark, path = df.sparkSession, scratch(df.sparkSession, tag)
    df.write.parquet(path)
    drop_at_exit(spark, path)
    return spark.read.schema(df.schema).parquet(path)
