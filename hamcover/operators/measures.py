"""What searches cost and how good their answers are."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable, Iterable
from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hamcover.functions.bits import hamming, hamming_sets, words_of
from hamcover.operators import hashers, search
from hamcover.plans.params import CoverPlan, expected_collisions


def recall(near: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: true, found, micro recall, and macro recall over queries that have any true point (null if none has)."""
    found = near.select("qid", "id", F.lit(1).alias("hit")).distinct()
    per = truth.join(found, ["qid", "id"], "left").groupBy("qid").agg(F.count("*").alias("true_pairs"), F.count("hit").alias("found_pairs"))
    return per.agg(
        F.coalesce(F.sum("true_pairs"), F.lit(0)).alias("true_pairs"),
        F.coalesce(F.sum("found_pairs"), F.lit(0)).alias("found_pairs"),
        F.round(F.sum("found_pairs") / F.sum("true_pairs"), 6).alias("recall"),
        F.round(F.avg(F.col("found_pairs") / F.col("true_pairs")), 6).alias("macro_recall"),
    )


def precision(near: DataFrame, candidates: DataFrame) -> DataFrame:
    """One row: near pairs, distinct candidates, their ratio."""
    a, b = near.agg(F.count("*").alias("near_pairs")), candidates.agg(F.count("*").alias("n_candidates"))
    return a.crossJoin(b).withColumn("precision", F.round(F.col("near_pairs") / F.nullif("n_candidates", F.lit(0)), 6))


def scan_speedup(points: int, queries: int, n_candidates: int) -> float:
    """Comparisons of a scan for one of the search."""
    return points * queries / max(1, n_candidates)


def index_bytes(n: int, tables: int, each: int = 24) -> int:
    """Size of stored bucket rows before compression: part, table, bucket and id of each point in each table."""
    return n * tables * each


def collisions(hits: DataFrame) -> DataFrame:
    """By query: hits with repetitions, and distinct points."""
    return hits.groupBy("qid").agg(F.count("*").alias("n_collisions"), F.count_distinct("id").alias("n_candidates"))


def candidates_by_bitmap(hits: DataFrame) -> DataFrame:
    """By query: distinct points, counted in bitmaps that are joined together."""
    return search.bitmaps(hits).groupBy("qid").agg(F.sum(F.call_function("bitmap_count", F.col("bitmap"))).alias("n_candidates"))


def distance_histogram(points: DataFrame, queries: DataFrame, d: int | None = None) -> DataFrame:
    """Pairs of queries and points by distance. The queries are a small set."""
    value = "code" if "code" in points.columns else "ones"
    q = queries.select(F.col(value).alias("q"))
    far = hamming(value, "q", words_of(d) if d else None) if value == "code" else hamming_sets(value, "q")
    return points.select(value).join(search.small(q, queries.count(), 4096)).groupBy(far.cast("int").alias("distance")).agg(F.count("*").alias("pairs"))


def filter_rate(histogram: DataFrame, r: int, c: float) -> DataFrame:
    """Shares of near, c-near and far pairs; the far ones are what a perfect filter spares."""
    n = lambda cond: F.sum(F.when(cond, F.col("pairs")).otherwise(0))
    d = F.col("distance")
    total = F.sum("pairs")
    return histogram.agg(
        F.round(n(d <= r) / total, 6).alias("near_share"),
        F.round(n((d > r) & (d <= c * r)) / total, 6).alias("c_near_share"),
        F.round(n(d > c * r) / total, 6).alias("far_share"),
    )


def estimate_collisions(histogram: DataFrame, plan: CoverPlan) -> DataFrame:
    """Expected collisions: pairs at each distance times the bound for that distance."""
    bounds = histogram.sparkSession.createDataFrame([(k, float(expected_collisions(plan, k))) for k in range(plan.d + 1)], "distance int, bound double")
    return histogram.join(F.broadcast(bounds), "distance").agg(F.round(F.sum(F.col("pairs") * F.col("bound")), 6).alias("expected_collisions"))


def cr_success(answers: DataFrame, truth: DataFrame, r: int, c: float) -> DataFrame:
    """Of queries that have a point within r: how many got an answer within c * r."""
    asked = truth.where(F.col("distance") <= r).select("qid").distinct()
    got = answers.where(F.col("distance") <= c * r).select("qid", F.lit(1).alias("ok"))
    return asked.join(got, "qid", "left").agg(F.count("*").alias("queries"), F.count("ok").alias("answered"))


def key_accidents(hits: DataFrame, masked_hits: DataFrame) -> DataFrame:
    """Hits of integer keys whose masked codes differ."""
    keys = ["qid", "id", "part", "v"]
    return hits.select(*keys).join(masked_hits.select(*keys), keys, "left_anti").agg(F.count("*").alias("accidents"))


def timed(df: DataFrame) -> float:
    """Seconds to compute all rows, without keeping them."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def time_hash(points: DataFrame, method: str, plan, runs: int = 1, **options) -> float:
    """Mean seconds of hashing all points. The keys stay in one array for each point, so it is hashing that is timed, not rows."""
    if method == "transform_cover":
        hashed = hashers.transform_cover_hash(points, plan, layout=options.get("layout", "array"), engine=options.get("engine", "arrow"))
    else:
        hashed = {"masked_cover": hashers.masked_cover_hash, "bit_sampling": hashers.bit_sampling_hash}[method](points, plan, layout="array") if method != "multi_index" else hashers.substring_hash(points, plan)
    return sum(timed(hashed) for _ in range(runs)) / runs


def cost_breakdown(points: DataFrame, queries: DataFrame, method: str, plan, r: int, d: int) -> dict[str, float]:
    """Seconds of the steps of a search over a stored index: hashing queries, finding distinct candidates, verifying."""
    from hamcover.sources.shared import written

    index = written(search.hash_points(points, method, plan).sortWithinPartitions("part", "v", "bucket"), "index")
    s1 = timed(search.hash_queries(queries, method, plan))
    probes = written(search.hash_queries(queries, method, plan), "probes")
    n = probes.count()
    s2 = timed(search.candidates(search.probe(index, probes, n)))
    found = written(search.candidates(search.probe(index, probes, n)), "candidates")
    s3 = timed(search.verify(found, points, queries, r, d))
    return {"s1_hash": s1, "s2_candidates": s2, "s3_verify": s3}


def executor_cpu(df: DataFrame) -> float:
    """CPU seconds of the executors' JVMs to compute all rows, without keeping them, from the stages of its jobs."""
    sc = df.sparkSession.sparkContext
    group = f"cpu-{uuid.uuid4().hex}"
    sc.setJobGroup(group, "timed")
    try:
        df.write.format("noop").mode("overwrite").save()
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
    jvm, tracker, total = sc._jsc.sc(), sc.statusTracker(), 0
    jvm.listenerBus().waitUntilEmpty()
    for job in tracker.getJobIdsForGroup(group):
        for stage in tracker.getJobInfo(job).stageIds:
            total += jvm.statusStore().lastStageAttempt(stage).executorCpuTime()
    return total / 1e9


def _hash_work(column: pa.Array, method: str, plan, sets=None) -> Callable[[], list]:
    if method == "multi_index":
        bits = hashers.unpacked(column, plan.d)
        return lambda: [np.packbits(bits[:, lo:hi], axis=1) for lo, hi in plan.bounds]
    kernel = hashers.sampling_kernel(plan, sets=sets) if sets else hashers.kernel_of(method, plan)
    return lambda: [None for _ in kernel(column)]


def _cpu_ms(work: Callable[[], list], runs: int, codes: int) -> float:
    work()
    began = time.process_time()
    for _ in range(runs):
        work()
    return (time.process_time() - began) * 1000 / runs / codes


def _hashed_codes(points: DataFrame, codes: int) -> pa.Array:
    value = "code" if "code" in points.columns else "ones"
    return points.select(value).where(F.col(value).isNotNull()).limit(codes).toArrow().column(0).combine_chunks()


def hash_cost_ms(points: DataFrame, method: str, plan, runs: int = 5, codes: int = 512) -> float:
    """CPU milliseconds of hashing one code, in one thread: the mean of `runs` runs over `codes` codes, one run before not counted."""
    column = _hashed_codes(points, codes)
    return _cpu_ms(_hash_work(column, method, plan), runs, len(column)) if len(column) else 0.0


def hash_costs_ms(points: DataFrame, hashed: list[tuple], runs: int = 5, codes: int = 512, planes: dict | None = None) -> list[float]:
    """`hash_cost_ms` of many methods and plans, each measured in a task of its own, the dearest first. `planes`: by sampling plan its `sampled_planes`;
    such a plan is measured over the positions that the codes have."""
    column, sc = _hashed_codes(points, codes), points.sparkSession.sparkContext
    if not len(column):
        return [0.0] * len(hashed)
    tables = lambda plan: plan.total_tables if isinstance(plan, CoverPlan) else plan.tables
    order = sorted(range(len(hashed)), key=lambda k: -tables(hashed[k][1]))
    todo = [(*hashed[k], sc.broadcast(hashers.compact_sets(column, hashed[k][1], planes[hashed[k][1]]) if planes and hashed[k][1] in planes else (column, hashed[k][1], None))) for k in order]

    def run(it):
        for batch in it:
            for k in batch.column(0).to_pylist():
                method, _, sent = todo[k]
                own, plan, sets = sent.value
                yield pa.RecordBatch.from_arrays([pa.array([k]), pa.array([_cpu_ms(_hash_work(own, method, plan, sets), runs, len(own))])], names=["k", "ms"])

    got = points.sparkSession.range(0, len(todo), 1, max(1, len(todo))).mapInArrow(run, "k bigint, ms double").collect()
    return [ms for _, ms in sorted((order[x.k], x.ms) for x in got)]


BUCKET = ["part", "v", "bucket"]


def met_indexes(points: DataFrame, queries: DataFrame, plans: list) -> list[DataFrame]:
    """For each covering or sampling plan the bucket rows, with their codes, that some query meets, stored. Dense points are read once for all plans."""
    from hamcover.sources.shared import shared_dir

    if not plans:
        return []
    path = shared_dir(points.sparkSession, "met-buckets")
    rows = hashers.met_rows(points, queries, plans)
    rows.sortWithinPartitions("plan", *BUCKET).write.partitionBy("plan").parquet(path)
    stored = points.sparkSession.read.schema("id bigint, part int, v int, bucket bigint, code array<bigint>, plan int").parquet(path)
    return [stored.where(F.col("plan") == k).drop("plan") for k in range(len(plans))]


def sampled_probes(queries: DataFrame, plan, rows: DataFrame) -> DataFrame:
    """Bucket rows of sparse queries, each eight tables hashed by one task, from the plan's `sampled_planes`."""
    table = queries.select("qid", "ones").where(F.col("ones").isNotNull()).toArrow().combine_chunks()
    qids, ones = table["qid"].to_numpy(), table["ones"].combine_chunks()
    at = ones.flatten().to_numpy(zero_copy_only=False)
    used, place = np.unique(at, return_inverse=True)
    weights = hashers.position_weights(plan)[used]
    sets = pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum(np.diff(ones.offsets.to_numpy()))]).astype(np.int32), pa.array(place.astype(np.int32)))

    def run(it):
        for batch in it:
            for g, kept in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                own = replace(plan, tables=min(8, plan.tables - 8 * g))
                ((_, keys),) = hashers.sampling_kernel(own, sets=(np.frombuffer(kept, np.uint8)[used][None], weights))(sets)
                n = len(keys)
                arrays = [np.tile(qids, n), np.zeros(keys.size, np.int32), np.repeat(np.arange(8 * g + 1, 8 * g + 1 + n, dtype=np.int32), len(qids)), keys.ravel()]
                yield pa.RecordBatch.from_arrays([*map(pa.array, arrays)], names=["qid", *BUCKET])

    return rows.select("g", "kept").mapInArrow(run, "qid bigint, part int, v int, bucket bigint")


def prepared_search(points: DataFrame, queries: DataFrame, method: str, plan, r: int, d: int, index: DataFrame | None = None, planes: DataFrame | None = None) -> tuple[Callable[[], DataFrame], int, int]:
    """A search of all queries in a stored index, whose code is warm: what runs it, its collisions and its candidates.

    Stored are the bucket rows, with their codes, that some query meets: `index`, if `met_indexes` has made it. If it is its rows of `hashers.sparse_met`, the codes,
    which are long ones, are stored once for each point and fetched for distinct candidates.
    `planes`: the `sampled_planes` of a sampling plan of sparse points."""
    from hamcover.sources.shared import written

    value, codes = "code" if "code" in points.columns else "ones", None
    probes = written(search.hash_queries(queries, method, plan) if planes is None else sampled_probes(queries, plan, planes), "probes")
    if method == "multi_index":
        rows = hashers.substring_hash(points, plan, carry=True)
        index = written(rows.join(search.small(probes.select(*BUCKET).distinct(), probes.count()), BUCKET, "left_semi").sortWithinPartitions(*BUCKET), "met-buckets")
    elif index is None and value == "code":
        index = met_indexes(points, queries, [plan])[0]
    elif index is None:
        own = probes.select("qid", *BUCKET)
        rows = search.hits_of(points, queries, method, plan).join(own, ["qid", "part", "v"]).select("id", *BUCKET).distinct()
        index = written(rows.join(points.select("id", value), "id").sortWithinPartitions(*BUCKET), "met-buckets")
    elif value == "ones":
        met = index.select("id", "part", value, F.explode(F.arrays_zip("v", "qid")).alias("met")).select("id", "part", value, "met.v", "met.qid")
        rows = met.join(search.small(probes, probes.count()), ["qid", "part", "v"]).select("id", *BUCKET)
        codes = written(index.select("id", value).dropDuplicates(["id"]), "met-codes")
        index = written(rows.sortWithinPartitions(*BUCKET), "met-buckets")
    asked = search.small(queries.select("qid", F.col(value).alias("qvalue")), queries.count(), 4096)
    hits = search.probe(index, probes)
    counts = hits.groupBy("qid", "id").agg(F.count("*").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()

    def found() -> DataFrame:
        if codes is None:
            pairs = hits.groupBy("qid", "id").agg(F.first(value).alias("value")).join(asked, "qid")
        else:
            pairs = hits.select("qid", "id").distinct().join(codes.select("id", F.col(value).alias("value")), "id").join(asked, "qid")
        words = words_of(d) if value == "code" else None
        return pairs.where(search.distance_of(points, F.col("value"), F.col("qvalue"), words) <= r)

    timed(found())
    return found, counts[0], counts[1]


def search_cost(found: Callable[[], DataFrame], runs: int = 5) -> float:
    """CPU milliseconds (mean of `runs`) of looking all queries up and verifying."""
    return sum(executor_cpu(found()) for _ in range(runs)) * 1000 / runs


def repeat(one: Callable[[int], DataFrame], seeds: Iterable[int] = range(5)) -> DataFrame:
    """The rows of several runs under different seeds, with the seed."""
    return reduce(DataFrame.unionByName, (one(s).withColumn("seed", F.lit(s)) for s in seeds))
