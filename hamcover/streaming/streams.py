"""Streams of events and of points. All run as they are on file, socket or log sources; tests and queries read files and stop when all is read."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from hamcover.operators import hashers, search
from hamcover.plans.params import CoverPlan
from hamcover.sources.shared import shared_dir

LATENESS = "10 minutes"


def files(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    """A stream of the Parquet files of a folder or path pattern, oldest first."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def split_files(rows: DataFrame, order: list, n: int, what: str) -> str:
    """Writes rows as n files, one for each share of their order and one after the other, so that a stream meets them in turn. Returns the folder."""
    spark = rows.sparkSession
    parts, path = shared_dir(spark, f"{what}-parts"), shared_dir(spark, what)
    rows.repartitionByRange(n, *order).withColumn("__k", F.spark_partition_id()).write.partitionBy("__k").parquet(parts)
    shares = spark.read.parquet(parts)
    for k in range(n):
        shares.where(F.col("__k") == k).drop("__k").coalesce(1).write.mode("append").parquet(path)
    return path


def with_time(events: DataFrame, column: str = "ts") -> DataFrame:
    return events.withColumn(column, F.col(column).cast("timestamp"))


def run_to_end(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there and returns what it put out, from a Parquet sink (append) or a table in memory."""
    spark = stream.sparkSession
    checkpoint = shared_dir(spark, "stream-state")
    if mode == "append":
        path = shared_dir(spark, "stream-out")
        stream.writeStream.outputMode("append").format("parquet").option("checkpointLocation", checkpoint).trigger(availableNow=True).start(path).awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    name = f"stream_{uuid.uuid4().hex}"
    stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def tumbling(events: DataFrame, size: str = "1 hour") -> DataFrame:
    w = F.window("ts", size)
    return with_time(events).withWatermark("ts", LATENESS).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, size: str = "2 hours", step: str = "1 hour") -> DataFrame:
    w = F.window("ts", size, step)
    return with_time(events).withWatermark("ts", LATENESS).groupBy(w.alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    w = F.session_window("ts", gap)
    return with_time(events).withWatermark("ts", LATENESS).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(events: DataFrame, keys: list[str]) -> DataFrame:
    """The first of the rows of a key within the lateness."""
    return with_time(events).withWatermark("ts", LATENESS).dropDuplicatesWithinWatermark(keys)


def probe_static(queries: DataFrame, index: DataFrame, points: DataFrame, plan: CoverPlan, r: int, d: int, path: str) -> DataFrame:
    """A stream of queries (qid, code) against a stored index: each batch is hashed, looked up and verified as a whole."""

    def batch(rows: DataFrame, _number: int) -> None:
        hits = search.probe(index, search.hash_queries(rows, "transform_cover", plan))
        search.verify(search.candidates(hits), points, rows, r, d).write.mode("append").parquet(path)

    spark = queries.sparkSession
    queries.writeStream.foreachBatch(batch).option("checkpointLocation", shared_dir(spark, "stream-state")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("qid bigint, id bigint, distance int").parquet(path)


def append_hashed(points: DataFrame, plan: CoverPlan) -> DataFrame:
    """A stream of points to bucket rows: stateless, so it appends."""
    return hashers.transform_cover_hash(points, plan)


def near_pairs_in_time(points: DataFrame, plan: CoverPlan, r: int, d: int, within: str = "1 hour") -> DataFrame:
    """Pairs of points (id, code, ts) within r and within a time of each other. Each pair is kept in one table only, which needs no state."""
    from hamcover.functions.bits import hamming, words_of

    times = points.select("id", "code", "ts").withWatermark("ts", LATENESS)
    keys = _with_keys(times, plan)
    left = keys.select("part", "v", "bucket", F.col("id").alias("id"), F.col("code").alias("code"), F.col("ts").alias("ts"))
    right = keys.select(F.col("part").alias("part2"), F.col("v").alias("v2"), F.col("bucket").alias("bucket2"), F.col("id").alias("qid"), F.col("code").alias("qcode"), F.col("ts").alias("ts2"))
    met = (F.col("part") == F.col("part2")) & (F.col("v") == F.col("v2")) & (F.col("bucket") == F.col("bucket2")) & (F.col("id") < F.col("qid"))
    close = (F.col("ts2") >= F.col("ts") - F.expr(f"interval {within}")) & (F.col("ts2") <= F.col("ts") + F.expr(f"interval {within}"))
    pairs = left.join(right, met & close).select("qid", "id", "part", "v", "code", "qcode")
    near = pairs.where(hamming("code", "qcode", words_of(d)) <= r)
    return search.owned(near, plan).select(F.col("id").alias("a"), F.col("qid").alias("b"), hamming("code", "qcode", words_of(d)).alias("distance"))


def _with_keys(points: DataFrame, plan: CoverPlan) -> DataFrame:
    """Bucket rows with code and time, by expressions: the time stays the same column, as watermarks need."""
    if plan.parts > 1:
        raise ValueError("streams join on one part")
    keys = F.transform(hashers.cover_keys_expr(F.col("code"), plan, 0), lambda k, i: F.struct(F.lit(0).alias("part"), (i + 1).alias("v"), k.alias("bucket")))
    return points.withColumn("k", F.explode(keys)).select("id", "code", "ts", "k.part", "k.v", "k.bucket")


def first_seen(events: DataFrame) -> DataFrame:
    """user_id and the first event type met of each user: state of one value per user."""

    def first(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        if not state.exists:
            state.update((str(rows["event_type"].iloc[0]),))
            yield pd.DataFrame({"user_id": [key[0]], "event_type": [rows["event_type"].iloc[0]]})

    return events.groupBy("user_id").applyInPandasWithState(first, "user_id bigint, event_type string", "event_type string", "append", GroupStateTimeout.NoTimeout)


def totals(events: DataFrame) -> DataFrame:
    """Counts by type since the beginning: for update and complete output."""
    return events.groupBy("event_type").agg(F.count("*").alias("n"))
