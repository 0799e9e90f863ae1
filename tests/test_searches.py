import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from hamcover.functions import bits as fb
from hamcover.functions import encoders
from hamcover.operators import hashers, index, measures, search
from hamcover.plans.hadamard import mask_bits
from hamcover.plans.params import P31, P61, plan_bit_sampling, plan_cover, plan_multi_index
from hamcover.queries import fixtures as fx
from hamcover.sources.shared import shared_dir, written


def codes(n, d, seed=0):
    words = fb.words_of(d)
    rng = np.random.default_rng(seed)
    x = rng.integers(-(1 << 63), 1 << 63, (n, words), np.int64)
    if d % 64:
        x[:, -1] &= (1 << (d % 64)) - 1
    return x


def frame(spark, x, name="id"):
    return spark.createDataFrame([(i, [int(w) for w in row]) for i, row in enumerate(x)], f"{name} bigint, code array<bigint>")


def near_codes(n=300, d=64, seed=1):
    """Clusters, so that there are neighbours at all distances."""
    rng = np.random.default_rng(seed)
    base = codes(12, d, seed)
    x = base[rng.integers(0, 12, n)].copy()
    for row in x:
        for i in rng.choice(d, rng.integers(0, 14), replace=False):
            row[i // 64] ^= np.int64(np.uint64(1 << (i % 64)).astype(np.int64))
    return x


@pytest.mark.parametrize("d,r,options", [(128, 6, {}), (300, 4, {}), (64, 5, {"construction": "general"}), (40, 3, {"skip_zero": True}), (64, 2, {"mode": "replicate", "t": 3}), (100, 9, {"mode": "partition", "t": 2}), (64, 10, {"mode": "partition", "t": 3, "radii": "general"})])
@pytest.mark.parametrize("prime", [P31, P61])
def test_transform_equals_direct_sums(d, r, options, prime):
    plan = plan_cover(d, 1000, r, prime=prime, **({"mode": "none"} | options))
    x = codes(20, d)
    column = pa.array([[int(w) for w in row] for row in x], pa.list_(pa.int64()))
    bits = hashers.unpacked(column, d)
    one, two = dict(hashers.transform_kernel(plan)(column)), dict(hashers.masked_kernel(plan)(column))
    sparse = pa.array([np.flatnonzero(b).tolist() for b in bits], pa.list_(pa.int32()))
    three, four = dict(hashers.transform_kernel(plan)(sparse)), dict(hashers.masked_kernel(plan)(sparse))
    for part in range(plan.parts):
        where, labels, seeds = plan.columns(part)
        masks = mask_bits(labels, plan.bits(part))
        direct = [[sum(s for w, s, k in zip(where, seeds, m, strict=True) if k and b[w]) % prime for b in bits] for m in masks]
        for keys in (one, two, three, four):
            assert keys[part].tolist() == direct


def test_plans_of_billions_of_points_have_pairs_of_keys(spark, clustered):
    points, asked = clustered
    plan = plan_cover(64, 2 * 10**9, 5, mode="none")
    assert plan.paired and not plan_cover(64, 10**9, 5, mode="none").paired
    truth = rows(search.linear_scan(points, asked, 5, 64))
    for fused in (True, False):
        for method in ("transform_cover", "masked_cover"):
            hits = search.hits_of(points, asked, method, plan, fused=fused)
            assert rows(search.verify(search.candidates(hits), points, asked, 5, 64)) == truth
    assert rows(search.report_near(points, asked, 5, 64, plan=plan, dedupe="owner")) == truth
    both = hashers.transform_cover_hash(points, plan).where("bucket <> check")
    assert both.count() > 0 and hashers.transform_cover_hash(points, plan).exceptAll(hashers.masked_cover_hash(points, plan)).count() == 0
    # An accident of the first keys is told by the second.
    rigged = hashers.transform_cover_hash(points, plan).withColumn("bucket", F.lit(0).cast("bigint"))
    probes = search.hash_queries(asked, "transform_cover", plan).withColumn("bucket", F.lit(0).cast("bigint"))
    assert rows(search.verify(search.candidates(search.probe(rigged, probes)), points, asked, 5, 64)) == truth


def test_sql_engine_gives_the_same_rows(spark):
    plan = plan_cover(64, 1000, 3, mode="none")
    points = frame(spark, codes(30, 64))
    a, b = hashers.transform_cover_hash(points, plan), hashers.transform_cover_hash(points, plan, engine="sql")
    assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0
    arrays = hashers.transform_cover_hash(points, plan, layout="array").select("id", F.size("buckets").alias("n")).distinct()
    assert arrays.count() == 30 and arrays.first().n == plan.total_tables


@pytest.fixture(scope="module")
def clustered(spark):
    points = frame(spark, near_codes()).persist()
    rest, asked = encoders.hold_out(points, 20)
    return rest.persist(), asked.persist()


def rows(df):
    return sorted(map(tuple, df.select("qid", "id", "distance").collect()))


@pytest.mark.parametrize("r", [0, 1, 4, 6])
@pytest.mark.parametrize("method", ["transform_cover", "masked_cover", "multi_index"])
def test_nothing_is_missed(clustered, r, method):
    points, asked = clustered
    options = {} if method == "multi_index" else {"mode": "none"}
    assert rows(search.report_near(points, asked, r, 64, method, n=300, **options)) == rows(search.linear_scan(points, asked, r, 64))


def test_variants_agree(clustered):
    points, asked = clustered
    truth = rows(search.linear_scan(points, asked, 8, 64))
    for options in ({"mode": "partition", "t": 2}, {"mode": "partition", "t": 3, "radii": "general"}, {"mode": "none"}, {}):
        assert rows(search.report_near(points, asked, 8, 64, n=300, **options)) == truth
    for dedupe in ("bitmap", "owner"):
        assert rows(search.report_near(points, asked, 8, 64, n=300, mode="partition", t=2, dedupe=dedupe)) == truth
    assert rows(search.popcount_band(points, asked, 8, 64)) == truth
    assert rows(search.report_near(points, asked, 2, 64, n=300, mode="replicate", t=3)) == rows(search.linear_scan(points, asked, 2, 64))
    assert rows(search.report_near(points, asked, 64, 64)) == rows(search.linear_scan(points, asked, 64, 64))
    assert rows(search.ball_probe(points, asked, 2, 64)) == rows(search.linear_scan(points, asked, 2, 64))


def test_joined_and_fused_hits_agree(clustered):
    points, asked = clustered
    for method, plan in (("transform_cover", plan_cover(64, 300, 5, mode="none")), ("bit_sampling", plan_bit_sampling(64, 300, 5, 0.1)), ("masked_cover", plan_cover(64, 300, 8, mode="partition", t=2))):
        a = search.hits_of(points, asked, method, plan, fused=True).select("qid", "id", "part", "v")
        b = search.hits_of(points, asked, method, plan, fused=False).select("qid", "id", "part", "v")
        assert a.count() and a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0


def test_both_covering_schemes_have_the_same_counts(clustered):
    points, asked = clustered
    plan = plan_cover(64, 300, 6, mode="none")
    a, b = (search.hits_of(points, asked, m, plan) for m in ("transform_cover", "masked_cover"))
    assert a.exceptAll(b).count() == 0 and a.count() == b.count()


def test_sampling_misses_some_at_most(clustered):
    points, asked = clustered
    truth = search.linear_scan(points, asked, 6, 64)
    got = measures.recall(search.report_near(points, asked, 6, 64, "bit_sampling", n=300, delta=0.1), truth).first()
    assert 0.7 <= got.recall <= 1
    loose = measures.precision(truth, search.candidates(search.hits_of(points, asked, "bit_sampling", plan_bit_sampling(64, 300, 6, 0.01)))).first()
    strict = measures.precision(truth, search.candidates(search.hits_of(points, asked, "bit_sampling", plan_bit_sampling(64, 300, 6, 0.1)))).first()
    assert loose.n_candidates >= strict.n_candidates


def test_nearest_and_first_hits(clustered):
    points, asked = clustered
    got = search.nearest(points, asked, 64, (0, 2, 4, 8), k=3, n=300, mode="none")
    scan = {}
    for q, i, d in sorted(rows(search.linear_scan(points, asked, 8, 64)), key=lambda x: (x[0], x[2], x[1])):
        scan.setdefault(q, []).append((i, d))
    want = sorted((q, k, i, d) for q, found in scan.items() for k, (i, d) in enumerate(found[:3], 1))
    assert sorted(map(tuple, got.collect())) == want
    first = search.first_hits(points, asked, 4, 2.0, 64, n=300, plan=plan_cover(64, 300, 4, mode="none"))
    assert first.count() == first.select("qid").distinct().count() and first.where("distance > 8").count() == 0


def test_near_pairs(spark):
    x = near_codes(200)
    x[7] = x[3]
    points = frame(spark, x)
    bits = np.bitwise_count((x[:, None, 0] ^ x[None, :, 0]).view(np.uint64))
    want = sorted((a, b, int(bits[a, b])) for a in range(200) for b in range(a + 1, 200) if bits[a, b] <= 5)
    for waves in (1, 3):
        assert sorted(map(tuple, search.every_near_pair(*search.near_pairs(points, 5, 64, n=200, waves=waves)).collect())) == want


def test_near_pairs_of_heavy_buckets(spark, monkeypatch):
    """Buckets in tiles give the same pairs, each once; groups keep apart."""
    x = near_codes(300)
    points = frame(spark, x).withColumn("group", F.col("id") % 2)
    bits = np.bitwise_count((x[:, None, 0] ^ x[None, :, 0]).view(np.uint64))
    want = sorted((a, b, int(bits[a, b])) for a in range(300) for b in range(a + 1, 300) if bits[a, b] <= 5)
    monkeypatch.setattr(search, "HEAVY_BUCKET", 6)
    pairs = search.every_near_pair(*search.near_pairs(points.drop("group"), 5, 64))
    assert sorted(map(tuple, pairs.collect())) == want
    apart = search.every_near_pair(*search.near_pairs(points, 5, 64))
    assert sorted(map(tuple, apart.collect())) == [p for p in want if p[0] % 2 == p[1] % 2]


def test_near_pairs_of_many_equal_codes(spark):
    """100,000 points of one code are one representative; nothing grows with the square of their number."""
    points = spark.range(100_000).select("id", F.array(F.lit(5).cast("bigint")).alias("code"))
    others = spark.range(100_000, 100_050).select("id", F.array(F.shiftleft(F.lit(1).cast("bigint"), 3) + F.col("id") % 2).alias("code"))
    pairs, members = search.near_pairs(points.unionByName(others), 3, 64)
    assert sorted(map(tuple, pairs.collect())) == [(0, 100_000, 3), (0, 100_001, 2), (100_000, 100_001, 1)]
    assert members.count() == 100_050 and members.where("rep = 0").count() == 100_000


def test_links_of_copies_grow_with_the_points(spark):
    """Unlike codes by their least ids, copies by the least id of their code: no row for a pair of copies, and all pairs follow."""
    points = spark.range(2_000).select("id", F.array(F.when(F.col("id") < 1_990, 5).otherwise(7).cast("bigint")).alias("code"))
    pairs, members = search.near_pairs(points, 2, 64)
    found = sorted(map(tuple, search.links(pairs, members).collect()))
    assert found == sorted([(0, i, 0) for i in range(1, 1_990)] + [(0, 1_990, 1)] + [(1_990, i, 0) for i in range(1_991, 2_000)])


def test_self_join_broadcasts_no_bucket_rows(spark, sf):
    """Small files whose bucket rows are many: the rows of all tables once went to the driver, and the tables were replicated to hundreds."""
    points = written(fx.docs(spark, sf, 64), "points")
    pairs, _ = search.near_pairs(points, 2, 64, n=5_000)
    assert "BroadcastHashJoin" not in pairs._jdf.queryExecution().executedPlan().toString()
    assert [search.pairs_plan(64, 60_000, r).total_tables for r in (1, 2, 3, 4)] == [3, 7, 15, 31]


def test_near_pairs_with_a_further_condition(spark, sf):
    """Pairs of near weights come from buckets of the covering family, not from all pairs of points of a weight."""
    from hamcover import registry

    plan = registry.queries()["j_range_popcount"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "bucket" in plan


def test_sampled_sets_drawn_by_tasks(spark):
    plan = plan_bit_sampling(1_003, 90_000, 5, 0.1, tables=9, prime=P61)
    assert all(np.array_equal(a, b) for a, b in zip(hashers.drawn_by_tasks(spark, plan), hashers.sampled_sets(plan), strict=True))


def test_sampled_sets_cost_what_is_set():
    """Sparse points of 200,000 positions: keys are equal just where the sampled sets are, and nothing is drawn as a Python integer."""
    plan = plan_bit_sampling(200_000, 90_000, 5, 0.1, tables=3, prime=P61)
    rows = [[1, 7, 199_999], [1, 7, 199_999], [], list(range(0, 200_000, 50))]
    (_, keys), = hashers.sampling_kernel(plan)(pa.array(rows, pa.list_(pa.int32())))
    for t in range(3):
        own = hashers.sampled_row(plan, t)
        assert own.tolist() == plan.positions[t]
        kept = [tuple(sorted(set(r) & set(own.tolist()))) for r in rows]
        assert all((kept[a] == kept[b]) == (keys[t][a] == keys[t][b]) for a in range(4) for b in range(4))
    batch = pa.RecordBatch.from_arrays([pa.array(range(4)), pa.array(rows, pa.list_(pa.int32()))], names=["id", "ones"])
    assert [x.num_rows for x in hashers.slices(batch, 1, 1 << 20)] == [4]


def test_empty_and_null(spark):
    points, asked = frame(spark, codes(5, 64)), frame(spark, codes(2, 64), "qid")
    none = points.where("id < 0")
    assert search.report_near(none, asked, 3, 64, n=2, mode="none").count() == 0
    assert search.report_near(points, asked.where("qid < 0"), 3, 64, n=5, mode="none").count() == 0
    holes = points.unionByName(spark.createDataFrame([(9, None)], points.schema))
    assert search.report_near(holes, asked, 3, 64, n=5, mode="none").count() == search.report_near(points, asked, 3, 64, n=5, mode="none").count()
    with pytest.raises(ValueError):
        search.report_near(points, asked, -1, 64)
    with pytest.raises(ValueError):
        search.ball_probe(points, asked, 6, 64)


def test_index_round_trip(spark, clustered):
    points, asked = clustered
    plan, path = plan_cover(64, 300, 4, mode="none"), shared_dir(spark, "test-index")
    index.write_index(points.where("id % 3 = 0"), plan, path)
    index.append_index(points, path)
    index.append_index(points, path)
    stored, got = index.read_index(spark, path)
    assert got == plan and stored.count() == points.count() * plan.total_tables
    with pytest.raises(ValueError):
        index.read_index(spark, path, plan_cover(64, 300, 5, mode="none"))
    hits = search.probe(stored, search.hash_queries(asked, "transform_cover", plan))
    assert rows(search.verify(search.candidates(hits), points, asked, 4, 64)) == rows(search.linear_scan(points, asked, 4, 64))


def test_sparse_sets(spark):
    rng = np.random.default_rng(3)
    base = [sorted(rng.choice(5000, 30, replace=False).tolist()) for _ in range(6)]
    sets = []
    for i in range(120):
        s = set(base[i % 6]) ^ set(rng.choice(5000, rng.integers(0, 9), replace=False).tolist())
        sets.append((i, sorted(s)))
    sets.append((200, []))
    points, asked = encoders.hold_out(spark.createDataFrame(sets, "id bigint, ones array<int>"), 15)
    for method in ("transform_cover", "masked_cover"):
        for options in ({"mode": "none"}, {"mode": "partition", "t": 2}):
            assert rows(search.report_near(points, asked, 6, 5000, method, n=120, **options)) == rows(search.linear_scan(points, asked, 6))


def test_layout_functions(spark):
    x = codes(6, 130)
    df = frame(spark, x)
    bits = [[int(row[i // 64]) >> (i % 64) & 1 for i in range(130)] for row in x]
    got = df.select(fb.unpack_bits("code", 130).alias("b"), fb.popcount("code", 3).alias("n"), fb.code_to_ones("code", 130).alias("o")).collect()
    assert [list(g.b) for g in got] == bits and [g.n for g in got] == [sum(b) for b in bits]
    assert [list(g.o) for g in got] == [[i for i, v in enumerate(b) if v] for b in bits]
    back = df.select(fb.pack_bits(fb.unpack_bits("code", 130), 130).alias("c"), fb.ones_to_code(fb.code_to_ones("code", 130), 130).alias("d"), "code").collect()
    assert all(list(r.c) == list(r.code) == list(r.d) for r in back)
    cut = df.select(*(c.alias(f"s{i}") for i, c in enumerate(fb.split("code", [(0, 30), (30, 94), (94, 130)])))).collect()
    for r, b in zip(cut, bits, strict=True):
        value = lambda lo, hi, b=b: sum(v << k for k, v in enumerate(b[lo:hi]))
        assert (r.s0, r.s1 % (1 << 64), r.s2) == (value(0, 30), value(30, 94), value(94, 130))
    order = list(reversed(range(130)))
    assert list(df.select(fb.permute("code", order).alias("p")).select(fb.unpack_bits("p", 130).alias("b")).first().b) == bits[0][::-1]
    twice = df.select(fb.replicate("code", 130, 2).alias("t")).select(fb.unpack_bits("t", 260).alias("b")).first().b
    assert list(twice) == bits[0] * 2
    pairs = df.crossJoin(df.select(F.col("code").alias("other")))
    same = pairs.where((fb.hamming("code", "other", 3) <= 60) != fb.hamming_leq("code", "other", 60, 3)).count()
    assert same == 0 and pairs.where(fb.hamming("code", "other", 3) != fb.hamming("code", "other")).count() == 0


def test_planted_distances(spark):
    asked = frame(spark, codes(4, 128), "qid")
    made = encoders.plant(asked, [0, 1, 5, 64, 128], 2, 128)
    both = made.join(asked.select("qid", F.col("code").alias("q")), "qid").withColumn("got", fb.hamming("code", "q", 2))
    assert both.count() == 40 and both.where("got <> distance").count() == 0


# Counts of the documents' 64-bit fingerprints at sf0.01, computed apart in SQL from masked codes.
PINNED = [
    (5, "general", 2011, 703), (5, "permuted", 1671, 437), (6, "general", 4279, 1153), (6, "permuted", 3551, 711),
    (7, "general", 8756, 1762), (7, "permuted", 7551, 1313), (8, "permuted", 15327, 1911),
]


def test_pinned_counts(spark):
    from hamcover.queries import fixtures as fx

    points, asked = encoders.hold_out(fx.docs(spark, "/root/testdata/sf0.01", 64).persist(), 50)
    near = {r: search.linear_scan(points, asked, r, 64).count() for r in (0, 3, 6, 10)}
    assert near == {0: 7, 3: 41, 6: 314, 10: 2274}
    for r, kind, collisions, candidates in PINNED:
        hits = search.hits_of(points, asked, "transform_cover", plan_cover(64, 1000, r, mode="none", construction=kind))
        assert hits.count() == collisions and search.candidates(hits).count() == candidates
    for r, delta, collisions, candidates in ((6, 0.1, 4950, 1170), (6, 0.01, 8395, 2353)):
        hits = search.hits_of(points, asked, "bit_sampling", plan_bit_sampling(64, 1000, r, delta, tables=127))
        assert hits.count() == collisions and search.candidates(hits).count() == candidates
    for r, collisions, candidates in ((6, 11709, 8362), (7, 44584, 20615)):
        hits = search.hits_of(points, asked, "multi_index", plan_multi_index(64, 1000, r))
        assert hits.count() == collisions and search.candidates(hits).count() == candidates


def test_masks_of_wide_sparse_points_take_no_memory_for_unset_positions():
    import tracemalloc

    d = 40_000
    plan = plan_cover(d, 10**6, 15, policy="words")
    sparse = pa.array([[3, 17, 39_999], [], [0, 20_000]], pa.list_(pa.int32()))
    want = dict(hashers.transform_kernel(plan)(sparse))  # columns are drawn and kept here
    tracemalloc.start()
    got = dict(hashers.masked_kernel(plan)(sparse))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert all((got[part] == want[part]).all() for part in want) and peak < 8 * plan.tables(0) * d // 20


def test_scan_of_many_queries_compares_in_kernels_as_expressions_do(spark, sf):
    for d, r in ((64, 20), (128, 40), (128, 2)):
        points, asked = encoders.hold_out(fx.uniform(spark, sf, d), 250)
        points = fx.with_planted(points, asked.limit(20), [0, 2, 3], 1, d).unionByName(spark.sql("SELECT -1L AS id, CAST(null AS array<bigint>) AS code"))
        got = search.linear_scan(points, asked, r, d)
        assert "MapInArrow" in got._jdf.queryExecution().toString()
        q = asked.select("qid", F.col("code").alias("qcode"))
        want = points.crossJoin(q).select("qid", "id", fb.hamming("code", "qcode", d // 64).cast("int").alias("distance")).where(F.col("distance") <= r)
        rows = got.collect()
        assert rows and sorted(rows) == sorted(want.collect())


def test_unreduced_keys_are_equal_where_those_of_the_prime_are():
    rng = np.random.default_rng(3)
    codes = rng.integers(-(1 << 63), (1 << 63) - 1, (40, 2))
    codes[20:] = codes[:20] ^ (np.int64(1) << rng.integers(0, 62, (20, 2)))
    column = pa.array(codes.tolist(), pa.list_(pa.int64()))
    for options in ({"mode": "none"}, {"mode": "replicate", "t": 2}, {"mode": "partition", "t": 2}):
        plan = plan_cover(128, 10**6, 6, **options)
        assert plan.prime == P61
        one, two = dict(hashers.transform_kernel(plan)(column)), dict(hashers.equal_kernel(plan)(column))
        same = lambda keys: keys[:, :, None] == keys[:, None]
        assert all((same(one[part]) == same(two[part])).all() for part in one) and sum(same(x).sum() > x.size for x in one.values())
