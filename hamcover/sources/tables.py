"""Table access: every reader goes through Spark, so any Hadoop-compatible store works."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; columns are pruned and filters pushed by Catalyst."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(rows: DataFrame) -> DataFrame:
    """Rows for work that costs far more than reading: a table of fewer files than there are cores is dealt out evenly first.

    A file of one row group is one task, however large. Tables of many files are left as they are."""
    cores = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(cores) if len(rows.inputFiles()) < cores else rows


def read_any(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """Parquet, ORC, JSON, CSV or text. A schema spares the inference pass of JSON and CSV."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_any(df: DataFrame, fmt: str, path: str, mode: str = "error", partition_by: tuple[str, ...] = (), **options) -> None:
    writer = df.write.format(fmt).mode(mode).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
