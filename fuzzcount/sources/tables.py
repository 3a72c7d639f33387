"""The given Parquet tables and the shared scratch folder."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from itertools import count
from weakref import WeakKeyDictionary

from pyspark.sql import DataFrame, SparkSession

#: Used only on one machine, where the session names no folder.
LOCAL_FOLDER = "/tmp/checkpoints"
#: Spark removes the shuffle files of a query as soon as it has run.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

_RUN, _STEPS = uuid.uuid4().hex, count(1)
_FOLDERS: WeakKeyDictionary[DataFrame, str] = WeakKeyDictionary()
_LIVE: dict[str, None] = {}


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table by name, pruned to the columns asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def spread(df: DataFrame, *keys: str) -> DataFrame:
    """`df` dealt over all cores: narrow tables come in fewer splits than there are cores, however long they are."""
    spark = df.sparkSession
    return df.repartition(max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))), *keys)


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share, which the session names; a cluster without one is refused."""
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not folder and context._jsc.sc().getCheckpointDir().isDefined():
        folder = context._jsc.sc().getCheckpointDir().get()
    if not folder and not context.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return (folder or LOCAL_FOLDER).rstrip("/")


def _place(spark: SparkSession, folder: str):
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    return path.getFileSystem(spark._jsc.hadoopConfiguration()), path


def new_folder(spark: SparkSession, name: str) -> str:
    """A folder of its own in the shared one; what is still in it when the driver ends goes then."""
    folder = f"{shared_folder(spark)}/{name}-{_RUN}-{next(_STEPS)}"
    files, path = _place(spark, folder)
    files.mkdirs(path)
    files.deleteOnExit(path)
    _LIVE[folder] = None
    return folder


def remove_folder(spark: SparkSession, folder: str) -> None:
    files, path = _place(spark, folder)
    files.delete(path, True)
    files.cancelDeleteOnExit(path)
    _LIVE.pop(folder, None)


def cut(df: DataFrame) -> DataFrame:
    """The same rows, written to the shared folder: later plans start there, also after executors are lost.

    As a table it has a known size, by which the planner decides what it broadcasts, and is read by the column.
    The shuffle files that made it go at once; the table stays until `drop` or the end of the driver.
    """
    spark = df.sparkSession
    folder, before = new_folder(spark, "step"), spark.conf.get(CLEANUP)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.mode("overwrite").parquet(folder)
    finally:
        spark.conf.set(CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(folder)
    _FOLDERS[out] = folder
    return out


def drop(*tables: DataFrame) -> None:
    """Remove tables that `cut` has written and no plan reads any more."""
    for df in tables:
        if folder := _FOLDERS.pop(df, None):
            remove_folder(df.sparkSession, folder)


@contextmanager
def passing_steps(spark: SparkSession) -> Iterator[None]:
    """Remove at the end what was written inside and not dropped: for results that are written elsewhere before."""
    before = set(_LIVE)
    yield
    for folder in [f for f in _LIVE if f not in before]:
        remove_folder(spark, folder)
