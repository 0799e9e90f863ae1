"""Physical plans: what is shuffled, pushed down and pruned."""

import re

from pyspark.sql import functions as F

from hamcover.operators import search
from hamcover.plans.params import plan_cover
from hamcover.queries import fixtures as fx
from hamcover.sources import load
from hamcover.sources.shared import written


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_owner_searches_shuffle_nothing(spark, sf):
    points = written(fx.uniform(spark, sf), "points")
    asked = written(points.limit(20).withColumnRenamed("id", "qid"), "queries")
    near = search.report_near(points, asked, 6, 128, n=1500, mode="none", dedupe="owner")
    text = plan_of(near)
    assert "Exchange" not in text and text.count("MapInArrow") == 2


def test_joined_probes_broadcast_only_what_is_small(spark, sf, monkeypatch):
    points = written(fx.uniform(spark, sf), "points")
    asked = written(points.limit(20).withColumnRenamed("id", "qid"), "queries")
    plan = plan_cover(128, 1500, 4, mode="none")
    hits = lambda: search.hits_of(points, asked, "transform_cover", plan, fused=False)
    assert "BroadcastHashJoin" in plan_of(hits())
    monkeypatch.setattr(search, "BROADCAST_BYTES", 0)
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        assert "SortMergeJoin" in plan_of(hits())
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_filters_and_columns_reach_the_scan(spark, sf):
    text = load(spark, sf, "orders").where(F.col("o_orderkey") < 100).select("o_orderkey")._jdf.queryExecution().toString()
    assert "LessThan(o_orderkey,100)" in text and re.search(r"ReadSchema: struct<o_orderkey:bigint>", text)
    codes = fx.uniform(spark, sf, below=500)._jdf.queryExecution().toString()
    assert "LessThan(o_orderkey,500)" in codes and "ReadSchema: struct<o_orderkey:bigint>" in codes


def test_distances_stay_in_generated_code(spark, sf):
    points = written(fx.uniform(spark, sf), "points")
    asked = written(points.limit(20).withColumnRenamed("id", "qid"), "queries")
    text = plan_of(search.linear_scan(points, asked, 6, 128))
    assert "bit_count" in text and "lambdafunction" not in text


def test_first_hits_rank_before_the_shuffle(spark, sf):
    points = written(fx.uniform(spark, sf), "points")
    asked = written(points.limit(20).withColumnRenamed("id", "qid"), "queries")
    assert "WindowGroupLimit" in plan_of(search.first_hits(points, asked, 4, 2.0, 128, plan=plan_cover(128, 1500, 4, mode="none")))
