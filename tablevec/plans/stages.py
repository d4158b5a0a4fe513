"""Tables written between steps: they cut long plans and survive lost executors."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir; a local one only where none is named and the driver runs all tasks."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    if getattr(spark, "_stage_folder", None) is None:
        spark._stage_folder = tempfile.mkdtemp(prefix="tablevec-")
    return spark._stage_folder


#: Most rows of a written table that Spark may broadcast by its own choice.
BROADCAST_ROWS = 50_000


def never_broadcast(df: DataFrame) -> DataFrame:
    """Keeps Spark from broadcasting many rows that take few bytes as a file.

    Spark judges by the size of the files, and vectors that are mostly zero or ids in order take next to nothing there,
    but all of their size on the driver. The hint holds for joins of the rows and of what is selected from them; a
    broadcast that a join asks for goes before it.
    """
    return df.hint("merge") if df.count() > BROADCAST_ROWS else df


@contextmanager
def measured_broadcasts(spark: SparkSession) -> Iterator[None]:
    """Within, Spark broadcasts by the bytes that a shuffle has measured, not by the size of files or a guess from it.

    A table of a million names takes 8 MB as a file and hundreds on the driver. Broadcasts that a join asks for stay.
    """
    fixed, adaptive = "spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold"
    before, own = spark.conf.get(fixed), spark.conf.get(adaptive, None)
    spark.conf.set(adaptive, own or before)
    spark.conf.set(fixed, "-1")
    try:
        yield
    finally:
        spark.conf.set(fixed, before)
        if own:
            spark.conf.set(adaptive, own)
        else:
            spark.conf.unset(adaptive)


class Stages:
    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.root, self.made = spark, f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}", 0

    def keep(self, df: DataFrame, **options: str) -> DataFrame:
        """The same rows, read from Parquet; many of them are never broadcast unless a join asks for it."""
        self.made += 1
        path = f"{self.root}/{self.made}"
        with measured_broadcasts(self.spark):
            df.write.options(**options).parquet(path)
        return never_broadcast(self.spark.read.schema(df.schema).parquet(path))

    def _delete(self, folder: str) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)

    def drop(self, number: int) -> None:
        self._delete(f"{self.root}/{number}")

    def clear(self) -> None:
        self._delete(self.root)
