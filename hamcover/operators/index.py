"""A persisted index: bucket rows clustered by table and bucket, with a manifest of the plan."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.operators.hashers import transform_cover_hash
from hamcover.plans.params import CoverPlan


def write_index(points: DataFrame, plan: CoverPlan, path: str, partitions: int | None = None, carry: bool = False, mode: str = "error") -> None:
    """Files hold ranges of (part, v, bucket), so that a probe reads few of them; folders are by part, so that a part can be read alone."""
    rows = transform_cover_hash(points, plan, carry=carry)
    keys = ["part", "v", "bucket"]
    dealt = rows.repartitionByRange(partitions, *keys) if partitions else rows.repartitionByRange(*keys)
    dealt.sortWithinPartitions(*keys).write.mode(mode).partitionBy("part").parquet(f"{path}/buckets")
    manifest = points.sparkSession.createDataFrame([(plan.to_json(),)], "value string")
    manifest.coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def read_plan(spark: SparkSession, path: str) -> CoverPlan:
    return CoverPlan.from_json(spark.read.text(f"{path}/manifest").first()[0])


def read_index(spark: SparkSession, path: str, plan: CoverPlan | None = None) -> tuple[DataFrame, CoverPlan]:
    """The bucket rows and their plan. With a plan of the caller's, one that differs is an error."""
    stored = read_plan(spark, path)
    if plan is not None and plan != stored:
        raise ValueError("the index was made by another plan")
    return spark.read.parquet(f"{path}/buckets"), stored


def append_index(points: DataFrame, path: str) -> None:
    """Adds points whose ids the index doesn't have, under its own plan. Points without an id are left out."""
    index, plan = read_index(points.sparkSession, path)
    known = index.where((F.col("part") == 0) & (F.col("v") == 1)).select("id")
    new = points.where(F.col("id").isNotNull()).join(known, "id", "left_anti")
    transform_cover_hash(new, plan).sortWithinPartitions("part", "v", "bucket").write.mode("append").partitionBy("part").parquet(f"{path}/buckets")


def expand(near: DataFrame, members: DataFrame) -> DataFrame:
    """Answers about representatives, for all points of their codes."""
    return near.withColumnRenamed("id", "rep").join(members, "rep").select("qid", "id", "distance")


def bucket_sizes(index: DataFrame) -> DataFrame:
    """By table: buckets, rows, the largest bucket and its share. What to look at before a self-join."""
    sizes = index.groupBy("part", "v", "bucket").agg(F.count("*").alias("n"))
    return sizes.groupBy("part", "v").agg(F.count("*").alias("buckets"), F.sum("n").alias("points"), F.max("n").alias("largest"))
