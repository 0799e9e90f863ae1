"""Experiment tables that SQL doesn't hold, against brute force or for what they must list; measures and advice."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from hamcover import registry
from hamcover.functions import encoders
from hamcover.operators import hashers, measures, search
from hamcover.plans import draws
from hamcover.plans.hadamard import collision_count, collision_counts, mask_bits
from hamcover.plans.params import PARTITION_PENALTY, plan_bit_sampling, plan_cover, theory_cost
from hamcover.queries import fixtures as fx
from hamcover.queries import workloads as w


def listed(spark, sf, name):
    return registry.queries()[name](spark, sf).collect()


def expected(names, methods):
    return {(n, m, r) for n, radii in names.items() for r in radii for m in methods}


DENSE = ("transform_cover", "masked_cover", "bit_sampling 0.1", "multi_index")


@pytest.mark.parametrize(
    "name, names, methods",
    [
        ("w_cpu_images", {"images 64": range(5, 11), "images 128": range(5, 11)}, DENSE),
        ("w_cpu_text", {"text 256": range(3, 9), "text 512": range(10, 16)}, DENSE),
        ("w_cpu_ratings", {"ratings": range(2, 14)}, DENSE[:3]),
        ("w_cpu_words", {"words": w.WORD_RADII}, DENSE[:3]),
    ],
)
def test_costs_of_every_method_and_radius(spark, sf, name, names, methods, monkeypatch):
    assert w.RUNS == 5
    monkeypatch.setattr(w, "RUNS", 1)
    rows = listed(spark, sf, name)
    assert {(r.name, r.method, r.r) for r in rows} == expected(names, methods) and len(rows) == len(expected(names, methods))
    assert all(r.runs == 1 and r.cpu_ms_per_query > 0 and r.cpu_ms_per_query >= r.hash_ms for r in rows)
    by = {(r.name, r.method, r.r): r for r in rows}
    for (n, m, r), row in by.items():
        if m == "masked_cover":
            same = by[n, "transform_cover", r]
            assert (row.n_collisions, row.n_candidates, row.tables) == (same.n_collisions, same.n_candidates, same.tables)
    assert max(w.WORD_RADII) == 29


def test_count_tables_list_every_method_and_radius():
    per = lambda rows: {(x.label, x.r) for x in rows}
    four = ("transform_cover", "masked_cover random", "bit_sampling 0.1", "multi_index")
    five = (*four, "bit_sampling 0.01")
    assert per(w.IMAGE_COUNTS) == {(m, r) for m in four for r in range(5, 11)}
    assert {b: per(x) for b, x in w.TEXT_COUNTS.items()} == {256: {(m, r) for m in four for r in range(3, 9)}, 512: {(m, r) for m in four for r in range(10, 16)}}
    assert per(w.REPLICATED) == {(m, r) for m in five for r in (2, 3, 4, 5)} and per(w.PARTED) == {(m, r) for m in five for r in (10, 12, 14, 16)}
    assert all(x.T is None for x in w.IMAGE_COUNTS if x.method == "multi_index")  # the standard number


def test_counts_of_word_sets_as_brute_force(spark, sf):
    points, asked, d = w._sets(spark, sf, fx.words, fx.vocabulary_size)
    p = {r.id: r.ones for r in points.select("id", "ones").collect()}
    q = {r.qid: r.ones for r in asked.select("qid", "ones").collect()}
    matrix = lambda sets: np.array([np.bincount(s, minlength=d) for s in sets.values()], np.float32)
    one, two = matrix(p), matrix(q)
    far = one.sum(1)[:, None] + two.sum(1)[None] - 2 * one @ two.T
    rows = [x for x in w.set_methods(w.WORD_RADII, "words", None) if x.r in (5, 10, 20)]
    got = {(r[1], r[4]): r for r in w.compared("words", points, asked, d, rows)}
    differ = np.abs(one[:, None] - two[None]).reshape(-1, d)
    for x in rows:
        plan = x.plan(d, len(p))
        hits = np.zeros(len(differ), np.int64)
        if x.method == "bit_sampling":
            masks = np.zeros((plan.tables, d), np.float32)
            for t, places in enumerate(plan.positions):
                masks[t, places] = 1
            hits = (differ @ masks.T == 0).sum(1)
        else:
            for part in range(plan.parts):
                where, labels, _ = plan.columns(part)
                hits += (differ[:, where] @ mask_bits(labels, plan.bits(part)).astype(np.float32).T == 0).sum(1)
        near = (far.ravel() <= x.r)
        want = (int(hits.sum()), int((hits > 0).sum()), int((near & (hits > 0)).sum()), int(near.sum()))
        assert tuple(got[x.label, x.r][6:10]) == want
        assert x.method == "bit_sampling" or want[2] == want[3]


def test_hash_time_crossover_steps_and_advice(spark, sf, monkeypatch):
    monkeypatch.setattr(w, "RUNS", 2)
    rows = listed(spark, sf, "w_hash_time")
    assert {(r.method, r.d, r.r) for r in rows} == {(m, d, r) for m in DENSE[:2] for d, r in [(128, r) for r in range(3, 8)] + [(d, 5) for d in (32, 64, 256, 512)]}
    by = {(r.method, r.d, r.r): r.cpu_ms_per_query for r in rows}
    assert all(r.runs == 2 for r in rows) and by["transform_cover", 512, 5] < by["masked_cover", 512, 5] and by["transform_cover", 128, 7] < by["masked_cover", 128, 7]
    assert {(r.queries, r.r) for r in listed(spark, sf, "w_scan_crossover")} == {(q, r) for q in (50, 500, 5000) for r in (3, 6)}
    steps = listed(spark, sf, "w_step_costs")
    assert len(steps) == 4 and all(r.s1_hash > 0 and r.s2_candidates > 0 and r.s3_verify > 0 for r in steps)
    advice = {(r.bits, r.indexed): r.advice for r in listed(spark, sf, "w_recommend")}
    assert advice[256, True] == "transform_cover" and advice[64, False] == "linear_scan"


def test_advice_scans_where_all_points_are_near(spark):
    near = spark.range(500).select("id", F.array((F.col("id") % 4).cast("bigint")).alias("code"))
    points, asked = encoders.hold_out(near, 10)
    advice, told = search.recommend(points, asked, 6, 2.0, 64, fraction=1.0, indexed=True)
    assert advice == "linear_scan" and told["near"] == 1.0 and told["far"] == 0.0
    assert search.recommend(points, asked, 60, 1.0, 64, fraction=1.0)[0] == "linear_scan"


def test_closed_measures(spark):
    assert measures.scan_speedup(1000, 50, 500) == 100 and measures.scan_speedup(10, 1, 0) == 10
    assert measures.index_bytes(10, 127) == 10 * 127 * 24
    assert theory_cost(10_000, 2.0) == (100.0, 1_000_000.0) and PARTITION_PENALTY == pytest.approx(math.log(4))
    seeds = measures.repeat(lambda s: spark.range(2).select(F.lit(s * 10).alias("x")), (1, 2, 3)).collect()
    assert sorted((r.seed, r.x) for r in seeds) == [(1, 10)] * 2 + [(2, 20)] * 2 + [(3, 30)] * 2


def test_executor_cpu_counts_the_jobs_of_a_frame(spark):
    little, much = measures.executor_cpu(spark.range(10)), measures.executor_cpu(spark.range(3_000_000).select(F.sha2(F.col("id").cast("string"), 256)))
    assert 0 < little < much


def test_sampled_variants_search(spark):
    """Both sizes from the theory, rounding down, and bits without repetition: searches that may miss, and report nothing wrong."""
    rng = np.random.default_rng(5)
    base = rng.integers(-(1 << 62), 1 << 62, 20)
    rows = [(i, [int(base[i % 20]) ^ sum(1 << int(b) for b in rng.choice(62, 3, replace=False))]) for i in range(400)]
    points, asked = encoders.hold_out(spark.createDataFrame(rows, "id bigint, code array<bigint>"), 20)
    truth = {tuple(r) for r in search.linear_scan(points, asked, 6, 64).collect()}
    # The rule for k takes the draws as independent; without repetition all of a table's positions agree less often.
    for options, least in (({"mode": "theory", "c": 2.0}, 0.3), ({"k_rounding": "floor"}, 0.9), ({"replace": False}, 0.5)):
        plan = plan_bit_sampling(64, 400, 6, 0.01, **options)
        got = {tuple(r) for r in search.report_near(points, asked, 6, 64, "bit_sampling", plan=plan).collect()}
        assert got <= truth and len(got) >= least * len(truth)


def test_collision_counts_of_many_codes():
    rng = np.random.default_rng(2)
    labels = plan_cover(64, 1000, 5, mode="none", construction="general").columns(0)[1]
    words = rng.integers(0, 1 << 63, 300) & rng.integers(0, 1 << 63, 300) & rng.integers(0, 1 << 63, 300)
    want = [collision_count([i for i in range(64) if int(x) >> i & 1], labels, 6) for x in words]
    assert collision_counts(words, labels, 6).tolist() == want


def test_hash_cost_measures_each_kernel(spark, sf):
    points = fx.uniform(spark, sf, 128).limit(64)
    plan = plan_cover(128, 64, 4, mode="none")
    for method, p in (("transform_cover", plan), ("masked_cover", plan), ("bit_sampling", plan_bit_sampling(128, 64, 4, tables=31))):
        assert measures.hash_cost_ms(points, method, p, runs=2, codes=64) > 0
    assert hashers.kernel_of("transform_cover", plan) is not None


@pytest.mark.parametrize("name", ["io_generated", "u_table_function", "w_analytic_costs", "w_family_bounds", "w_table_counts", "w_typical_plan"])
def test_queries_read_a_given_table(spark, tmp_path, name):
    """Without tables there is no result; once these made their data up."""
    with pytest.raises(Exception, match="orders.parquet"):
        registry.queries()[name](spark, str(tmp_path)).collect()


def test_rows_that_queries_meet_are_those_of_hashing_all_points(spark, sf):
    for d in (64, 128):
        points, asked = encoders.hold_out(fx.uniform(spark, sf, d), 10)
        points = fx.with_planted(points, asked, [0, 2, 5, 9], 2, d).unionByName(spark.sql("SELECT -1L AS id, CAST(null AS array<bigint>) AS code"))
        plans = [plan_cover(d, 10**6, 5, mode="none"), plan_cover(d, 10**6, 3, mode="replicate", t=2), plan_cover(d, 10**6, 8, mode="partition", t=2), plan_bit_sampling(d, 10**6, 5, 0.1)]
        for plan, index in zip(plans, measures.met_indexes(points, asked, plans), strict=True):
            method = "bit_sampling" if plan is plans[-1] else "transform_cover"
            own = search.hash_queries(asked, method, plan).select("part", "v", "bucket").distinct()
            want = search.hash_points(points, method, plan, carry=True).join(own, ["part", "v", "bucket"], "left_semi").select("id", "part", "v", "bucket", "code")
            assert sorted(index.collect()) == sorted(want.collect()) and index.count() > 0


def test_draws_of_many_are_those_of_one():
    for prefix in ("7:s:3:", "7:m:0:0:", "x" * 53, ""):
        assert draws.numbers(prefix, 12_345).tolist() == [draws.number(f"{prefix}{i}") for i in range(12_345)]
    assert draws.order("7:perm:", 5_000).tolist() == sorted(range(5_000), key=lambda i: (draws.digest(f"7:perm:{i}"), i))


def test_sparse_rows_that_queries_meet_are_those_of_hashing_all_points(spark, monkeypatch):
    """For several plans in one pass over the points, and (with little room) in many."""
    rng, d = np.random.default_rng(4), 3_000
    base = [sorted(rng.choice(d, size, replace=False).tolist()) for size in (0, 1, 4, 30, 200, 900)]
    sets = [sorted(set(base[i % 6]) ^ set(rng.choice(d, i % 5, replace=False).tolist())) for i in range(300)]
    points, asked = encoders.hold_out(spark.createDataFrame(list(enumerate(sets)), "id bigint, ones array<int>"), 20)
    points = points.unionByName(spark.sql("SELECT -1L AS id, CAST(null AS array<int>) AS ones"))
    plans = [plan_cover(d, 10**6, 5, mode="none"), plan_cover(d, 10**6, 3, mode="replicate", t=2), plan_cover(d, 10**6, 8, mode="partition", t=2), plan_bit_sampling(d, 10**6, 5, 0.1), plan_bit_sampling(d, 10**6, 4, 0.1, tables=70)]
    want = {}
    for k, plan in enumerate(plans):
        for x in search.hits_of(points, asked, "bit_sampling" if k > 2 else "transform_cover", plan).collect():
            want.setdefault((k, x.qid, x.id), set()).add((x.part, x.v))
    for room in (hashers.PASS_BYTES, 1):
        monkeypatch.setattr(hashers, "PASS_BYTES", room)
        planes = w.planes_of(spark, plans)
        got = hashers.sparse_met(points, asked, plans, planes, counted=True).groupBy("plan", "qid", "id").agg(F.sum("n").alias("n")).collect()
        assert {(x.plan, x.qid, x.id): x.n for x in got} == {key: len(tables) for key, tables in want.items()}
    met = [(x.plan, x.id, x.part, v, qid) for x in hashers.sparse_met(points, asked, plans, planes, counted=False).collect() for v, qid in zip(x.v, x.qid, strict=True)]
    assert len(met) == len({x[:4] for x in met}) and {x[:4] for x in met} == {(k, i, part, v) for (k, _, i), tables in want.items() for part, v in tables}
    assert all((part, v) in want[k, qid, i] for k, i, part, v, qid in met)


def test_scan_of_sets_as_brute_force(spark):
    """In kernels, without an array function for each pair; null points and empty sets among them."""
    rng = np.random.default_rng(6)
    sets = [sorted(rng.choice(60, rng.integers(0, 9), replace=False).tolist()) for _ in range(200)]
    points, asked = encoders.hold_out(spark.createDataFrame(list(enumerate(sets)), "id bigint, ones array<int>"), 30)
    points = points.unionByName(spark.sql("SELECT -1L AS id, CAST(null AS array<int>) AS ones"))
    scan, known = search.linear_scan(points, asked, 6), [x.qid for x in asked.collect()]
    assert "MapInArrow" in scan._jdf.queryExecution().executedPlan().toString()
    far = {(q, i): len(set(sets[q]) ^ set(sets[i])) for q in known for i in range(200) if i not in known}
    assert sorted(map(tuple, scan.collect())) == sorted((q, i, x) for (q, i), x in far.items() if x <= 6)
