"""Session helpers: shared storage for cutting lineage, and settings of one block of code.

Intermediate results live in the folder that the cluster names in ``spark.checkpoint.dir``
(every executor and the driver see it). Where neither that setting nor a checkpoint folder is
set, a session on one machine (master ``local``) gets a temporary folder; on a cluster it is an error.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder for checkpoints and intermediate tables; sets one where none is set."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    known = spark.sparkContext._jsc.sc().getCheckpointDir()
    if named:
        if known.isEmpty():
            spark.sparkContext.setCheckpointDir(named)
        return named
    if known.isEmpty():
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="spanweave-"))
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
    return known.get()


def delete_path(spark: SparkSession, path: str) -> None:
    """Delete a folder through Hadoop's file system, wherever it is."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


class Stored:
    """A table written once to the shared folder: ``df`` reads it, ``drop()`` removes it."""

    def __init__(self, df: DataFrame, tag: str):
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/{tag}-{uuid.uuid4().hex}"
        df.write.parquet(self.path)
        self.df = self.spark.read.schema(df.schema).parquet(self.path)

    def drop(self) -> None:
        delete_path(self.spark, self.path)


def stored(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` to the shared folder and return the reread table; its plan starts at those files."""
    return Stored(df, tag).df


@contextmanager
def settings(spark: SparkSession, **values: str) -> Iterator[None]:
    """Runtime SQL settings for a block; underscores stand for dots. Restored at the end."""
    names = {k.replace("__", "."): v for k, v in values.items()}
    before = {k: spark.conf.get(k, None) for k in names}
    try:
        for k, v in names.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)
