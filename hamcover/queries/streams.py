"""Queries that run streams over all rows that are there. Batches come in order of time, so watermarks only hold back the last windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.functions.encoders import hold_out
from hamcover.operators import index
from hamcover.plans.params import plan_cover
from hamcover.queries import fixtures as fx
from hamcover.sources import load
from hamcover.sources.shared import shared_dir
from hamcover.streaming import streams

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of four files in order of time."""
    return streams.files(spark, streams.split_files(load(spark, sf_dir, "events"), ["ts", "event_id"], 4, "stream-events"))


# The watermark is ten minutes behind the last event; windows that end after it are still open.
_DONE = "SELECT max(ts) - INTERVAL 10 MINUTE FROM events"


@query("st_tumbling", f"SELECT * FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL) WHERE start + INTERVAL 1 HOUR <= ({_DONE})")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = streams.run_to_end(streams.tumbling(_events(spark, sf_dir)))
    return found.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("st_sliding", f"SELECT * FROM (SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 1 HOUR, ts), time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 1 HOUR]) AS start FROM events) GROUP BY start) WHERE start + INTERVAL 2 HOUR <= ({_DONE})")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = streams.run_to_end(streams.sliding(_events(spark, sf_dir)))
    return found.select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query(
    "st_session",
    f"""WITH s AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM s)
SELECT * FROM (SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", count(*) AS n FROM g GROUP BY user_id, k) WHERE "end" <= ({_DONE})""",
)
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = streams.run_to_end(streams.sessions(_events(spark, sf_dir)))
    return found.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), F.col("end").cast("timestamp_ntz").alias("end"), "n")


@query("st_dedupe", "SELECT event_id, user_id FROM events")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event twice in the stream, once in the result."""
    rows = load(spark, sf_dir, "events")
    twice = streams.files(spark, streams.split_files(rows.unionByName(rows), ["ts", "event_id"], 4, "stream-twice"))
    return streams.run_to_end(streams.deduplicated(twice, ["event_id"])).select("event_id", "user_id")


@query("st_late_rows")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Files out of order: rows that come after their window was closed don't count."""
    rows = load(spark, sf_dir, "events").withColumn("late", F.pmod(F.xxhash64("event_id"), F.lit(10)) == 0)
    path = streams.split_files(rows, ["late", "ts", "event_id"], 4, "stream-late")
    found = streams.run_to_end(streams.tumbling(streams.files(spark, path)))
    return found.groupBy("event_type").agg(F.sum("n").alias("n"))


@query("st_totals_complete", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.run_to_end(streams.totals(_events(spark, sf_dir)), "complete")


@query("st_totals_update", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last of the updates of each type."""
    return streams.run_to_end(streams.totals(_events(spark, sf_dir)), "update").groupBy("event_type").agg(F.max("n").alias("n"))


@query("st_first_seen", "SELECT user_id, arg_min(event_type, (ts, event_id)) AS event_type FROM events GROUP BY user_id")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.run_to_end(streams.first_seen(_events(spark, sf_dir)))


PLAN = plan_cover(64, 1000, 4, mode="none", construction="general")


def _near(r: int) -> str:
    return f"WITH points AS MATERIALIZED ({fx.sql_text_codes(64)}),{fx.sql_hold_out('points', fx.QUERIES)}\nSELECT q.qid, p.id, {fx.sql_distance(1)} AS distance FROM pts p, queries q WHERE {fx.sql_distance(1)} <= {r}"


@query("st_stream_static_probe", _near(4))
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    points, asked = hold_out(fx.docs(spark, sf_dir, 64), fx.QUERIES)
    path = shared_dir(spark, "index")
    index.write_index(points, PLAN, path)
    rows, plan = index.read_index(spark, path, PLAN)
    queries = streams.files(spark, streams.split_files(asked, ["qid"], 2, "stream-queries"))
    return streams.probe_static(queries, rows, points, plan, 4, 64, shared_dir(spark, "stream-near"))


@query("st_index_append", f"WITH points AS MATERIALIZED ({fx.sql_text_codes(64)}),\n{fx.sql_columns(PLAN)},{fx.sql_hashes('h', 'points', 'id', PLAN)}\nSELECT id, CAST(part AS INT) AS part, CAST(v AS INT) AS v, bucket FROM h")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    codes = streams.files(spark, streams.split_files(fx.docs(spark, sf_dir, 64), ["id"], 3, "stream-points"))
    return streams.run_to_end(streams.append_hashed(codes, PLAN))


@query(
    "st_stream_stream_pairs",
    f"WITH points AS MATERIALIZED ({fx.sql_text_codes(64)})\nSELECT p.id AS a, q.id AS b, {fx.sql_distance(1)} AS distance FROM points p JOIN points q ON p.id < q.id WHERE {fx.sql_distance(1)} <= 4 AND q.id - p.id <= 60",
)
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents one minute after each other: pairs within an hour."""
    codes = fx.docs(spark, sf_dir, 64).withColumn("ts", F.timestamp_seconds(F.col("id") * 60))
    path = streams.split_files(codes, ["ts"], 3, "stream-codes")
    return streams.run_to_end(streams.near_pairs_in_time(streams.files(spark, path), PLAN, 4, 64))


