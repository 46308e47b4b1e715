"""Tables in the folder that driver and executors share, between the rounds of iterative operators."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


_OWN: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; on a local master alone, where it is unset, a folder of our own, removed at exit."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    if not _OWN:
        _OWN.append(tempfile.mkdtemp(prefix="cutfield-"))
        atexit.register(shutil.rmtree, _OWN[0], True)
    return _OWN[0]


def remove(spark: SparkSession, path: str) -> None:
    """Remove a table's files; only for tables that no pending DataFrame reads."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


class Tables:
    """Owner of the tables that are written inside its ``with`` block.  They stay until ``drop``, because results read them lazily."""

    _open: list[Tables] = []

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def __enter__(self) -> Tables:
        Tables._open.append(self)
        return self

    def __exit__(self, *_) -> None:
        Tables._open.remove(self)

    @staticmethod
    def note(path: str) -> None:
        if Tables._open:
            Tables._open[-1].paths.append(path)

    def drop(self) -> None:
        while self.paths:
            remove(self.spark, self.paths.pop())


class Stored:
    """A DataFrame written once as Parquet and read back: lineage ends here, and lost executors do not matter."""

    def __init__(self, df: DataFrame):
        self.spark, self.schema = df.sparkSession, df.schema
        self.path = f"{shared_dir(self.spark).rstrip('/')}/round-{uuid.uuid4().hex}"
        Tables.note(self.path)
        df.write.parquet(self.path)

    def read(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        """Remove the files; only for tables that no pending DataFrame reads."""
        remove(self.spark, self.path)
