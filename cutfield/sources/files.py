"""Edge lists in and results out, in the file formats that Spark reads and writes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import DDL, require_schema


def read_relation(spark: SparkSession, name: str, path: str, fmt: str = "parquet", columns: dict[str, str] | None = None, **options: str) -> DataFrame:
    """A declared relation from ``csv``, ``json``, ``orc``, ``parquet`` or any other format, without inference.

    ``columns`` maps declared names to SQL expressions over the file's own columns; text formats then need ``schema`` in the options.
    """
    own = options.pop("schema", None)
    reader = spark.read.format(fmt).options(**options)
    if own or (fmt in ("csv", "json") and not columns):
        reader = reader.schema(own or DDL[name])
    df = reader.load(path)
    if columns:
        df = df.select(*[F.expr(e).alias(c) for c, e in columns.items()])
    if "model_id" not in df.columns:
        df = df.withColumn("model_id", F.lit(0).cast("long"))
    return require_schema(df, name)


def read_jdbc(spark: SparkSession, name: str, url: str, query: str, partition: tuple[str, int, int, int] | None = None, **options: str) -> DataFrame:
    """A declared relation from a database; ``partition`` is (column, lowest, highest, readers)."""
    reader = spark.read.format("jdbc").options(url=url, **options)
    if partition:
        column, low, high, n = partition
        reader = reader.option("dbtable", f"({query}) q").options(partitionColumn=column, lowerBound=str(low), upperBound=str(high), numPartitions=str(n))
    else:
        reader = reader.option("query", query)
    return require_schema(reader.load(), name)


def write_by_model(df: DataFrame, path: str, buckets: int = 64, fmt: str = "parquet") -> None:
    """Files in folders by a bucket of ``model_id``, so that a model's rows are found by partition pruning."""
    rows = df.withColumn("bucket", F.pmod(F.xxhash64("model_id"), F.lit(buckets)).cast("int"))
    rows.repartition("bucket").write.mode("overwrite").partitionBy("bucket").format(fmt).save(path)


def read_model(spark: SparkSession, path: str, model_id: int, buckets: int = 64, fmt: str = "parquet") -> DataFrame:
    """One model's rows from such files; one folder is read."""
    wanted = spark.range(1).select(F.pmod(F.xxhash64(F.lit(model_id).cast("long")), F.lit(buckets)).cast("int")).first()[0]
    return spark.read.format(fmt).load(path).where((F.col("bucket") == wanted) & (F.col("model_id") == model_id)).drop("bucket")


def write_bucketed(df: DataFrame, table: str, buckets: int = 64, columns: tuple[str, ...] = ("model_id", "cluster")) -> None:
    """A table bucketed and sorted by cluster: later sweeps join it without a shuffle of its rows."""
    df.write.mode("overwrite").bucketBy(buckets, *columns).sortBy(*columns).saveAsTable(table)


def export(df: DataFrame, path: str, fmt: str = "json") -> None:
    """Diagnostics for others to read; nested columns become JSON text in ``csv``."""
    if fmt == "csv":
        nested = [c for c, t in df.dtypes if t.startswith(("array", "map", "struct"))]
        df = df.withColumns({c: F.to_json(c) for c in nested})
    df.write.mode("overwrite").format(fmt).option("header", "true").save(path)
