"""Probing buckets, removing repetitions, verifying distances, and the searches made of them.

Queries are the small side. Their bucket rows are broadcast if `broadcast_size` proves them small; beyond that
the join is left to Spark as an ordinary equi-join. Points are never collected and no bucket is cut short.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hamcover.functions.bits import hamming, hamming_sets, words_of
from hamcover.operators import hashers
from hamcover.plans.hadamard import mask_bits
from hamcover.plans.params import CoverPlan, SamplePlan, SubstringPlan, plan_bit_sampling, plan_cover, plan_multi_index
from hamcover.sources.shared import written

#: Bytes of bucket rows of queries that may be broadcast, at 64 each.
BROADCAST_BYTES = 256 << 20


def small(rows: DataFrame, count: int, each: int = 64) -> DataFrame:
    """The rows, to be broadcast if their number shows that they are small."""
    return F.broadcast(rows) if count * each <= BROADCAST_BYTES else rows


def probe(index: DataFrame, probes: DataFrame, n_probes: int | None = None) -> DataFrame:
    """All hits of query rows (qid, part, v, bucket) in bucket rows (id, part, v, bucket): qid, id, part, v, and codes that either side carries."""
    n = probes.count() if n_probes is None else n_probes
    keys = ["part", "v", "bucket"] + ["check"] * ("check" in probes.columns and "check" in index.columns)
    own = [c for c in probes.columns if c not in keys]
    rest = [c for c in index.columns if c not in (*keys, *own)]
    return index.join(small(probes, n), keys).select(*own, *rest, "part", "v")


def candidates(hits: DataFrame, dedupe: str = "distinct", plan: CoverPlan | None = None) -> DataFrame:
    """Distinct (qid, id).

    distinct: an aggregation. bitmap: one bitmap of ids for each query and range of ids, then unpacked. owner: a hit stays only
    in the first table in which the pair meets, told from both codes on the hit (qcode, code), so nothing is shuffled.
    """
    if dedupe == "distinct":
        return hits.select("qid", "id").distinct()
    if dedupe == "bitmap":
        return _from_bitmaps(bitmaps(hits))
    if dedupe == "owner":
        return owned(hits, plan).select("qid", "id")
    raise ValueError(dedupe)


def bitmaps(hits: DataFrame) -> DataFrame:
    """qid, range number, bitmap of its ids."""
    number, place = F.call_function("bitmap_bucket_number", F.col("id")), F.call_function("bitmap_bit_position", F.col("id"))
    return hits.groupBy("qid", number.alias("range")).agg(F.call_function("bitmap_construct_agg", place).alias("bitmap"))


def _from_bitmaps(maps: DataFrame) -> DataFrame:
    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for qid, number, data in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                at = np.flatnonzero(np.unpackbits(np.frombuffer(data, np.uint8), bitorder="little"))
                # Ranges are numbered from 1 for ids from 1; range 0 holds ids up to 0, counted downwards.
                ids = (number - 1) * 32768 + at + 1 if number > 0 else number * 32768 - at
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), qid, np.int64)), pa.array(ids.astype(np.int64))], names=["qid", "id"])

    return maps.mapInArrow(run, "qid bigint, id bigint")


def owned(hits: DataFrame, plan: CoverPlan) -> DataFrame:
    """The hits (with qcode and code) that are the first of their pair. Accidents of unequal keys own nothing, and go."""
    out = hits.schema

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep, tables = [], []
        for part in range(plan.parts):
            where, labels, _ = hashers.columns(plan, part)
            masks = mask_bits(labels.tolist(), plan.bits(part)).astype(np.float32)
            keep.append((where, masks.T.copy()))
            tables.append((part, len(masks)))
        part_of = np.concatenate([np.full(n, p) for p, n in tables])
        v_of = np.concatenate([np.arange(1, n + 1) for _, n in tables])
        for whole in it:
            for at in range(0, whole.num_rows, 4096):
                batch = whole.slice(at, 4096)
                names = batch.schema.names
                z = hashers.unpacked(batch.column(names.index("code")), plan.d) ^ hashers.unpacked(batch.column(names.index("qcode")), plan.d)
                # A table is shared if its mask keeps none of the differing positions.
                shared = np.concatenate([z[:, where].astype(np.float32) @ masks == 0 for where, masks in keep], axis=1)
                first = shared.argmax(axis=1)
                mine = shared.any(axis=1) & (part_of[first] == batch.column(names.index("part")).to_numpy()) & (v_of[first] == batch.column(names.index("v")).to_numpy())
                yield batch.filter(pa.array(mine))

    return hits.mapInArrow(run, out)


def distance_of(points: DataFrame, a: Column, b: Column, words: int | None = None) -> Column:
    return hamming(a, b, words) if "code" in points.columns else hamming_sets(a, b)


def _value(points: DataFrame) -> str:
    return "code" if "code" in points.columns else "ones"


def verify(pairs: DataFrame, points: DataFrame, queries: DataFrame, r: int, d: int | None = None) -> DataFrame:
    """qid, id, distance of the pairs within r. Codes are joined to distinct pairs; the queries' side is broadcast if small."""
    value = _value(points)
    words = words_of(d) if d and value == "code" else None
    q = queries.select("qid", F.col(value).alias("qvalue"))
    joined = pairs.join(points.select("id", F.col(value).alias("value")), "id").join(small(q, queries.count(), 4096), "qid")
    return joined.select("qid", "id", distance_of(points, F.col("value"), F.col("qvalue"), words).cast("int").alias("distance")).where(F.col("distance") <= r)


def hash_points(points: DataFrame, method: str, plan, carry: bool = False) -> DataFrame:
    if method == "transform_cover":
        return hashers.transform_cover_hash(points, plan, carry=carry)
    if method == "masked_cover":
        return hashers.masked_cover_hash(points, plan, carry=carry)
    if method == "bit_sampling":
        return hashers.bit_sampling_hash(points, plan, carry=carry)
    if method == "multi_index":
        return hashers.substring_hash(points, plan)
    raise ValueError(method)


def hash_queries(queries: DataFrame, method: str, plan, carry: bool = False) -> DataFrame:
    """Bucket rows of queries; multi_index lists every bucket to look at."""
    if method == "multi_index":
        return hashers.substring_probes(queries, plan)
    hashed = hash_points(queries.withColumnRenamed("qid", "id"), method, plan, carry).withColumnRenamed("id", "qid")
    return hashed.withColumnRenamed("code", "qcode") if carry and "code" in queries.columns else hashed


def default_plan(method: str, d: int, n: int, r: int, **options):
    if method in ("transform_cover", "masked_cover"):
        return plan_cover(d, n, r, **options)
    if method == "bit_sampling":
        return plan_bit_sampling(d, n, r, **options)
    if method == "multi_index":
        return plan_multi_index(d, n, r, **options)
    raise ValueError(method)


#: Bytes of queries' keys up to which points are hashed and looked up in one pass.
FUSED_BYTES = 64 << 20


def hits_of(points: DataFrame, queries: DataFrame, method: str, plan, carry: bool = False, fused: bool | None = None) -> DataFrame:
    """S1 and the lookup of S2: all (qid, id, part, v) in which a query and a point share a bucket.

    Keys of few queries go to the points, which are hashed and looked up on the fly; many queries meet the points in an equi-join.
    """
    asked = queries.count()
    n = asked * (plan.total_tables if isinstance(plan, CoverPlan) else plan.tables if isinstance(plan, SamplePlan) else sum(map(plan.probes, range(plan.tables))))
    if method != "multi_index" and (8 * n <= FUSED_BYTES and (_value(points) == "ones" or 8 * asked * plan.d <= FUSED_BYTES) if fused is None else fused):
        return hashers.fused_hits(points, queries, method, plan, carry)
    return probe(hash_points(points, method, plan, carry), hash_queries(queries, method, plan, carry), n)


def data_side_hits(points: DataFrame, queries: DataFrame, plan: SubstringPlan) -> DataFrame:
    """Hits of substrings with the neighbourhoods listed for the points: pays if queries are many times the points."""
    rows = hashers.substring_probes(points.select(F.col("id").alias("qid"), "code"), plan).withColumnRenamed("qid", "id")
    probes = hashers.substring_hash(queries.select(F.col("qid").alias("id"), "code"), plan).withColumnRenamed("id", "qid")
    return probe(rows, probes, queries.count() * plan.tables)


#: Queries from which a scan of dense codes is made in kernels, and up to which their codes are broadcast.
SCAN_ROWS = (200, 65_536)


def linear_scan(points: DataFrame, queries: DataFrame, r: int, d: int | None = None) -> DataFrame:
    """Every point against every query of a small set: exact, and the truth that others are held against."""
    value = _value(points)
    words = words_of(d) if d and value == "code" else None
    asked = queries.count()
    if words and SCAN_ROWS[0] <= asked <= SCAN_ROWS[1]:
        return _scanned(points, queries, r, words)
    if value == "ones" and asked <= SCAN_ROWS[1]:
        return _scanned_sets(points, queries, r)
    q = queries.select("qid", F.col(value).alias("qvalue"))
    pairs = points.select("id", value).join(small(q, asked, 4096))
    return pairs.select("qid", "id", distance_of(points, F.col(value), F.col("qvalue"), words).cast("int").alias("distance")).where(F.col("distance") <= r)


def _scanned(points: DataFrame, queries: DataFrame, r: int, words: int) -> DataFrame:
    """A scan in kernels, by words: a pair that differs in more than r positions of the words so far isn't compared in the others."""
    table = queries.select("qid", "code").where(F.col("code").isNotNull()).toArrow().combine_chunks()
    matrix = lambda codes: np.ascontiguousarray(codes.flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(len(codes), -1 if len(codes) else words)[:, :words].T)
    asked = points.sparkSession.sparkContext.broadcast((table["qid"].to_numpy().astype(np.int64), matrix(table["code"].combine_chunks())))

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, theirs = asked.value
        for whole in it:
            for at in range(0, whole.num_rows if len(qids) else 0, 8192):
                batch = whole.slice(at, 8192)
                ids, own = batch.column(0).to_numpy(), matrix(batch.column(1))
                rows, asks, far = [], [], []
                moved, ones = np.empty(len(ids), np.int64), np.empty(len(ids), np.uint8)
                for k in range(len(qids)):
                    np.bitwise_xor(own[0], theirs[0, k], out=moved)
                    np.bitwise_count(moved.view(np.uint64), out=ones)
                    mine = np.flatnonzero(ones <= r)
                    if not len(mine):
                        continue
                    distance = ones[mine].astype(np.int32)
                    for w in range(1, words):
                        distance += np.bitwise_count((own[w, mine] ^ theirs[w, k]).view(np.uint64))
                        near = distance <= r
                        mine, distance = mine[near], distance[near]
                    rows.append(mine)
                    asks.append(np.full(len(mine), k))
                    far.append(distance)
                if rows:
                    arrays = [qids[np.concatenate(asks)], ids[np.concatenate(rows)], np.concatenate(far)]
                    yield pa.RecordBatch.from_arrays([*map(pa.array, arrays)], names=["qid", "id", "distance"])

    return points.select(F.col("id").cast("bigint").alias("id"), "code").where(F.col("code").isNotNull()).mapInArrow(run, "qid bigint, id bigint, distance int")


def _scanned_sets(points: DataFrame, queries: DataFrame, r: int) -> DataFrame:
    """A scan of sparse points in kernels: what a point has in common with a query is counted by looking its positions up."""
    table = queries.select("qid", "ones").where(F.col("ones").isNotNull()).toArrow().combine_chunks()
    asked = points.sparkSession.sparkContext.broadcast((table["qid"].to_numpy().astype(np.int64), [np.array(x, np.int64) for x in table["ones"].to_pylist()]))

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, sets = asked.value
        width = 1 + max((int(x.max()) for x in sets if len(x)), default=0)
        every, own = np.zeros(width, bool), np.zeros(width, bool)
        for one in sets:
            every[one] = True
        for whole in it:
            for batch in hashers.slices(whole, 1, 1 << 16):
                ids, sizes = batch.column(0).to_numpy(), np.diff(batch.column(1).offsets.to_numpy())
                at = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.int64)
                row = np.repeat(np.arange(len(ids)), sizes)
                known = at < width
                known[known] = every[at[known]]
                at, row = at[known], row[known]
                for qid, one in zip(qids, sets, strict=True):
                    own[one] = True
                    common = np.bincount(row[own.take(at)], minlength=len(ids))
                    own[one] = False
                    distance = sizes + len(one) - 2 * common
                    near = np.flatnonzero(distance <= r)
                    if len(near):
                        arrays = [np.full(len(near), qid), ids[near], distance[near].astype(np.int32)]
                        yield pa.RecordBatch.from_arrays([*map(pa.array, arrays)], names=["qid", "id", "distance"])

    return points.select(F.col("id").cast("bigint").alias("id"), "ones").where(F.col("ones").isNotNull()).mapInArrow(run, "qid bigint, id bigint, distance int")


def equal_codes(points: DataFrame, queries: DataFrame) -> DataFrame:
    """Radius 0: an equi-join."""
    value = _value(points)
    q = queries.select("qid", value)
    return points.select("id", value).join(small(q, queries.count(), 4096), value).select("qid", "id", F.lit(0).alias("distance"))


def ball_probe(points: DataFrame, queries: DataFrame, r: int, d: int) -> DataFrame:
    """Looks up every code of the ball around a query."""
    from hamcover.plans.params import ball_size

    probes = hashers.ball_probes(queries, d, r)
    found = points.select("id", "code").join(small(probes, queries.count() * ball_size(d, r)), "code").select("qid", "id")
    return verify(found, points, queries, r, d)


def report_near(points: DataFrame, queries: DataFrame, r: int, d: int, method: str = "transform_cover", plan=None, n: int | None = None, dedupe: str = "distinct", **options) -> DataFrame:
    """All points within r of each query: qid, id, distance. By a covering family or multi_index none is missed.

    With `dedupe='owner'` codes ride on the hits, and of all steps none shuffles the points when the queries are broadcast.
    """
    if r < 0:
        raise ValueError("radius from 0")
    if method == "linear_scan" or r >= d:
        return linear_scan(points, queries, r, d)
    if r == 0 and method != "bit_sampling":
        return equal_codes(points, queries)
    if method == "ball_probe":
        return ball_probe(points, queries, r, d)
    if plan is None:
        plan = default_plan(method, d, points.count() if n is None else n, r, **options)
    if dedupe == "owner":
        if not isinstance(plan, CoverPlan) or "code" not in points.columns:
            raise ValueError("owner needs a covering plan and dense codes")
        mine = owned(hits_of(points, queries, method, plan, carry=True), plan)
        return mine.select("qid", "id", hamming("code", "qcode", words_of(d)).alias("distance")).where(F.col("distance") <= r)
    return verify(candidates(hits_of(points, queries, method, plan), dedupe, plan if isinstance(plan, CoverPlan) else None), points, queries, r, d)


def first_hits(points: DataFrame, queries: DataFrame, r: int, c: float, d: int, method: str = "transform_cover", plan=None, budget: int | None = None, n: int | None = None) -> DataFrame:
    """At most one point for each query: the closest of its first hits (three for each table, repetitions counted), if within c * r.

    Hits are taken in the order of part, table and id.
    """
    if plan is None:
        plan = default_plan(method, d, points.count() if n is None else n, r)
    tables = plan.total_tables if isinstance(plan, CoverPlan) else plan.tables
    order = Window.partitionBy("qid").orderBy("part", "v", "id")
    seen = hits_of(points, queries, method, plan).withColumn("k", F.row_number().over(order)).where(F.col("k") <= (budget or 3 * tables))
    near = verify(seen.select("qid", "id").distinct(), points, queries, int(c * r), d)
    best = F.min(F.struct("distance", "id")).alias("b")
    return near.groupBy("qid").agg(best).select("qid", "b.id", "b.distance")


def nearest(points: DataFrame, queries: DataFrame, d: int, radii: tuple[int, ...] = (0, 1, 2, 4, 8), k: int = 1, method: str = "transform_cover", n: int | None = None, **options) -> DataFrame:
    """The k nearest points of each query, by growing radii: qid, rank, id, distance. A query leaves when k points lie within a radius;
    those without so many within the last radius get what there is. Ties go to the smaller id."""
    n = points.count() if n is None else n
    left, found = queries, None
    for step, r in enumerate(radii):
        near = written(report_near(points, left, r, d, method, n=n, **options), "near")
        full = near.groupBy("qid").count().where(F.col("count") >= k).select("qid")
        mine = near if step == len(radii) - 1 else near.join(full, "qid", "left_semi")
        found = mine if found is None else found.union(mine)
        left = written(left.join(full, "qid", "left_anti"), "left")
    order = Window.partitionBy("qid").orderBy("distance", "id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("qid", "rank", "id", "distance")


def collapsed(points: DataFrame) -> tuple[DataFrame, DataFrame]:
    """One point for each distinct code (of each `group`, if points have that column), by the least id, and the membership (rep, id).
    Equal codes share all tables, so they are never hashed twice."""
    keys = [_value(points)] + ["group"] * ("group" in points.columns)
    reps = points.groupBy(*keys).agg(F.min("id").alias("rep"))
    # Codes that only one point has are not joined to anything.
    members = points.select("id", *keys).join(reps, keys).select("rep", "id")
    return reps.select(F.col("rep").alias("id"), *keys), members


#: Points of a bucket beyond which a self-join compares it in tiles.
HEAVY_BUCKET = 8_192


def _met(rows: DataFrame, keys: list[str], condition: Column) -> DataFrame:
    """Pairs of bucket rows that meet, the lesser id first."""
    right = rows.select(*keys, F.col("id").alias("qid"), F.col("code").alias("qcode"), *([F.col("block").alias("qblock")] if "block" in rows.columns else []))
    # Spark takes the output of a kernel for no longer than its input, so it would broadcast all bucket rows: they are sorted and merged.
    return rows.hint("merge").join(right, keys).where(condition).select("qid", "id", "part", "v", "code", "qcode")


def _self_hits(rows: DataFrame, near: Column, heavy: int | None) -> DataFrame:
    """Pairs id < qid of bucket rows (id, part, v, bucket, code; perhaps the hash of a group) that share a bucket and are near.

    A bucket of more than `heavy` rows is cut into blocks by id; each pair of blocks is a tile, and a task of its own."""
    keys = ["part", "v", "bucket"] + ["in_group"] * ("in_group" in rows.columns)
    ordered = F.col("id") < F.col("qid")
    if heavy is None:
        return _met(rows, keys, ordered & near)
    large = written(rows.groupBy(*keys).agg(F.count("*").alias("n")).where(F.col("n") > heavy), "heavy-buckets")
    light = _met(rows.join(large, keys, "left_anti").select(*rows.columns), keys, ordered & near)
    blocks = F.ceil(F.col("n") / heavy).cast("int")
    dealt = rows.join(large, keys).withColumn("block", F.pmod(F.xxhash64("id", "bucket"), blocks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    dealt = dealt.select("id", *keys, "code", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block")
    once = ordered & (F.col("i") == F.col("j")) | (F.col("block") != F.col("qblock")) & ordered
    return light.union(_met(dealt, [*keys, "i", "j"], once & near))


def near_pairs(points: DataFrame, r: int, d: int, plan: CoverPlan | None = None, n: int | None = None, waves: int = 1, also: Column | None = None) -> tuple[DataFrame, DataFrame]:
    """All pairs a < b of distinct codes within r (a, b, distance; each code by its least id), and the membership (rep, id) of all points.

    Rows grow with the points and with the pairs of unlike codes, however many points share a code; see `every_near_pair` for pairs of all points. A self-join of buckets in which
    each pair is kept in one table only. `waves` splits the tables into so many joins, each of which holds fewer rows at a time. With a column `group`, only points of one group are paired.
    `also`: a condition on code and qcode that pairs have to meet, too.
    """
    n = points.count() if n is None else n
    if plan is None:
        plan = pairs_plan(d, n, r)
    reps, members = collapsed(points)
    reps = written(reps, "distinct-codes")
    if "group" in points.columns:
        # One more word, behind those that are hashed and compared, takes the group to the buckets.
        hashed = hashers.transform_cover_hash(reps.select("id", F.concat("code", F.array(F.xxhash64("group"))).alias("code")), plan, carry=True)
        hashed = hashed.withColumn("in_group", F.element_at("code", -1))
    else:
        hashed = hashers.transform_cover_hash(reps, plan, carry=True)
    # Far pairs go before the kernel: the distance is one generated expression.
    near = hamming("code", "qcode", words_of(d)) <= r
    near = near if also is None else near & also
    found = None
    for wave in range(waves):
        rows = hashed.where(F.pmod("v", F.lit(waves)) == wave) if waves > 1 else hashed
        # No bucket has more rows than there are points.
        hits = _self_hits(rows, near, HEAVY_BUCKET if n > HEAVY_BUCKET else None)
        mine = owned(hits, plan).select(F.col("id").alias("a"), F.col("qid").alias("b"), hamming("code", "qcode", words_of(d)).alias("distance"))
        found = mine if found is None else found.union(mine)
    if "group" in points.columns:  # groups of one hash are told apart
        group = lambda x: reps.select(F.col("id").alias(x), F.col("group").alias(f"group_{x}"))
        found = found.join(group("a"), "a").join(group("b"), "b").where(F.col("group_a") == F.col("group_b")).select("a", "b", "distance")
    return found, members


def pairs_plan(d: int, n: int, r: int) -> CoverPlan:
    """The plan of a self-join: parts for large radii, but no replication. A query is hashed once, however many its tables; in a join each table
    is a row of every point, and small radii replicated by the size of the data would make hundreds of them."""
    plan = plan_cover(d, n, r)
    return plan_cover(d, n, r, mode="none") if plan.mode == "replicate" else plan


def links(pairs: DataFrame, members: DataFrame) -> DataFrame:
    """The pairs of `near_pairs` and the membership as one table a, b, distance: two unlike codes by their least ids, or (distance 0) a code's least id
    and another point that has it. All pairs of points follow from these rows; copies make one row each, not one with every other."""
    own = members.where(F.col("rep") != F.col("id")).select(F.col("rep").alias("a"), F.col("id").alias("b"), F.lit(0).alias("distance"))
    return pairs.unionByName(own)


def every_near_pair(pairs: DataFrame, members: DataFrame) -> DataFrame:
    """The pairs of `near_pairs`, for all points of their codes: a, b, distance. Copies of one code make rows with the square of their number."""
    left, right = members.select(F.col("rep").alias("a"), F.col("id").alias("i")), members.select(F.col("rep").alias("b"), F.col("id").alias("j"))
    apart = pairs.join(left, "a").join(right, "b").select(F.least("i", "j").alias("a"), F.greatest("i", "j").alias("b"), "distance")
    same = members.join(members.select("rep", F.col("id").alias("other")), "rep").where(F.col("id") < F.col("other"))
    return apart.union(same.select(F.col("id").alias("a"), F.col("other").alias("b"), F.lit(0).alias("distance")))


def popcount_band(points: DataFrame, queries: DataFrame, r: int, d: int) -> DataFrame:
    """Exact reporting by weights: within r, weights differ by r at most. A range join as an equi-join on bins of weights."""
    from hamcover.functions.bits import popcount

    w = words_of(d)
    width = max(1, r)
    left = points.select("id", "code", popcount("code", w).alias("weight")).withColumn("bin", F.floor(F.col("weight") / width))
    right = queries.select("qid", F.col("code").alias("qcode"), popcount("code", w).alias("qweight"))
    right = right.withColumn("bin", F.explode(F.sequence(F.floor((F.col("qweight") - r) / width), F.floor((F.col("qweight") + r) / width))))
    joined = left.join(small(right, queries.count() * 3, 256), "bin").where(F.abs(F.col("weight") - F.col("qweight")) <= r)
    return joined.select("qid", "id", hamming("code", "qcode", w).alias("distance")).where(F.col("distance") <= r)


def recommend(points: DataFrame, queries: DataFrame, r: int, c: float, d: int, n: int | None = None, fraction: float = 0.01, indexed: bool = False) -> tuple[str, dict]:
    """Which method to use, from a sampled distance histogram: scan when most points are near anyhow, or when hashing all points costs more
    than comparing them with few queries and no index is kept."""
    from hamcover.operators.measures import distance_histogram
    from hamcover.plans.params import hash_cost

    n = points.count() if n is None else n
    asked = queries.count()
    hist = {x["distance"]: x["pairs"] for x in distance_histogram(points.sample(fraction, seed=7), queries, d).collect()}
    total = sum(hist.values()) or 1
    near = sum(v for k, v in hist.items() if k <= r) / total
    far = sum(v for k, v in hist.items() if k > c * r) / total
    words = words_of(d)
    scan = asked * words
    try:
        tables = plan_cover(d, n, r, c).total_tables
    except ValueError:
        return "linear_scan", {"near": near, "far": far, "scan_cost": scan}
    told = {"near": near, "far": far, "scan_cost": scan, "hash_cost": hash_cost("transform_cover", d, tables) + tables}
    if far < 0.3 or not indexed and scan < told["hash_cost"]:
        return "linear_scan", told
    return ("multi_index" if r <= 2 and d <= 64 else "transform_cover"), told
