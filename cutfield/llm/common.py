"""Helpers shared by the operators of this subpackage."""

from __future__ import annotations

import ctypes
import uuid
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import Tables, remove, shared_dir

#: Word separators: space, tab, line feed, vertical tab, form feed, carriage return.
SPACE_CLASS = r"[\x20\x09-\x0D]"
SPACES = " \t\n\x0b\x0c\r"


class SharedTable:
    """A DataFrame written once as Parquet in the shared folder and read back: lineage ends here and survives lost executors."""

    def __init__(self, df: DataFrame, name: str, codec: str = "zstd"):
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
        self.schema = df.schema
        Tables.note(self.path)
        df.write.option("compression", codec).parquet(self.path)

    def read(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        """Remove the files; only for tables that no pending DataFrame reads."""
        remove(self.spark, self.path)


@contextmanager
def rows_at_once(spark: SparkSession, most: int):
    """Inside, a task hands Python at most ``most`` rows at once, for rows that are large; only for what runs inside."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    was = spark.conf.get(key)
    spark.conf.set(key, str(min(most, int(was)) if int(was) > 0 else most))
    try:
        yield
    finally:
        spark.conf.set(key, was)


def released(run):
    """``run``, after which a Python worker hands unused memory back; workers live on, and would hold it beside later stages."""

    def inner(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            if hasattr(trim := ctypes.CDLL(None), "malloc_trim"):  # of glibc alone
                trim.malloc_trim(0)

    return inner


def sliced(batches, rows: int = 1024):
    """The batches in slices of at most ``rows``, so that little of a batch is copied at once."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def text_or_empty(name: str) -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def words(text: Column) -> Column:
    """The maximal runs of non-separators, as an array; an empty array for none."""
    body = F.btrim(text, F.lit(SPACES))
    return F.when(body == "", F.array().cast("array<string>")).otherwise(F.split(body, SPACE_CLASS + "+"))


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z and nothing else; texts of ASCII alone take the fast built-in."""
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, upper, lower))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_bytes(docs: DataFrame, text_col: str) -> int:
    """UTF-8 bytes of all texts: one narrow pass, used only to size partitions."""
    return docs.agg(F.sum(F.octet_length(F.col(text_col).cast("string")).cast("long"))).first()[0] or 0
