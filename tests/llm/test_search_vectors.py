"""Collision-counting search against brute force."""

import numpy as np
import pyarrow.parquet as pq
from pyspark.sql import functions as F

from hamcover.llm import ann


def brute(ids, x, k, every=20):
    want = {}
    for q, v in zip(ids, x, strict=True):
        if q % every == 0:
            s = (x * v).sum(axis=1)
            other = ids != q
            order = np.lexsort((ids[other], -s[other]))[:k]
            want[int(q)] = list(zip(ids[other][order].tolist(), s[other][order].tolist(), strict=True))
    return want


def test_recall_on_the_table(spark, sf):
    got = {}
    for r in ann.op1_collision_search(spark, sf).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").collect()
    ids, x = np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], np.float64)
    want = brute(ids, x, 20)
    assert set(got) == set(want)
    hits = [len({i for _, i, _ in got[q]} & {i for i, _ in want[q]}) / 20 for q in want]
    assert np.mean(hits) >= 0.9
    for found in got.values():
        found.sort()
        assert [r for r, _, _ in found] == list(range(1, len(found) + 1))
        assert all((a[2], -a[1]) >= (b[2], -b[1]) for a, b in zip(found, found[1:], strict=False))
    scores = {(q, i): s for q, ws in want.items() for i, s in ws}
    assert all(abs(scores[q, i] - s) == 0 for q, found in got.items() for _, i, s in found if (q, i) in scores)


def verified_share(x, queries, k=20):
    shard = ann.Shard(np.arange(len(x)), x)
    place, ids, _ = shard.nearest(queries, x[queries], k)
    want = brute(np.arange(len(x)), x, k, 1) if len(x) <= 2000 else {q: (lambda s, q=q: [(i, 0) for i in np.lexsort((np.arange(len(x)), -s)) if i != q][:k])((x * x[q]).sum(axis=1)) for q in queries.tolist()}
    hits = [len({int(i) for i in ids[place == n]} & {i for i, _ in want[int(q)]}) / k for n, q in enumerate(queries)]
    return shard.verified / len(queries) / len(x), np.mean(hits)


def test_few_vectors_are_verified():
    """Collisions, not a scan, find the neighbours: at most a fifth of the rows of the table is verified."""
    rows = pq.read_table("/root/testdata/sf0.1/embeddings.parquet")["embedding"].to_pylist()
    share, recall = verified_share(np.array(rows), np.arange(0, len(rows), 20))
    assert share <= 0.2 and recall >= 0.9
    rng = np.random.default_rng(0)
    share, recall = verified_share(rng.standard_normal((8192, 64)), np.arange(0, 8192, 200))
    assert share <= 0.3 and recall >= 0.9  # of unequal lengths
    clusters = rng.standard_normal((100, 64))[rng.integers(0, 100, 8192)] + 0.4 * rng.standard_normal((8192, 64))
    share, recall = verified_share(clusters, np.arange(0, 8192, 200))
    assert share <= 0.03 and recall >= 0.95


def test_shards_and_blocks_give_the_same_kind_of_answer(spark, sf):
    rows = ann.usable(spark.read.parquet(f"{sf}/embeddings.parquet"))
    asked = rows.where("vec_id % 20 = 0")
    a = ann.search(rows, asked, 5, shard_rows=60, query_rows=7)
    b = ann.search(rows, asked, 5)
    same = a.join(b, ["query_id", "vec_id"]).count()
    assert a.count() == b.count() and same / b.count() > 0.9


def test_odd_vectors(spark):
    ok = [1.0, 0.0, 0.0]
    rows = [(0, ok), (20, ok), (40, ok), (1, [0.5, 0.5, 0.0]), (2, None), (3, []), (4, [0.0, 0.0, 0.0]), (5, [1.0, None, 0.0]), (6, [float("nan"), 1.0, 0.0]), (7, [float("inf"), 1.0, 0.0]), (None, ok), (8, [1.0, 2.0]), (1, [0.5, 0.5, 0.0])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").withColumn("score", F.lit("x"))
    usable = ann.usable(df)
    got = ann.search(usable, usable.where("vec_id % 20 = 0"), 20).orderBy("query_id", "rank").collect()
    found = {q: [(r.vec_id, r.score) for r in got if r.query_id == q] for q in (0, 20, 40)}
    assert found[0] == [(20, 1.0), (40, 1.0), (1, 0.5), (1, 0.5)]
    assert found[20] == [(0, 1.0), (40, 1.0), (1, 0.5), (1, 0.5)]
    assert ann.search(usable.where("vec_id < 0"), usable.where("vec_id < 0"), 20).count() == 0


def test_many_equal_vectors(spark):
    rng = np.random.default_rng(0)
    hot = rng.standard_normal(16)
    rows = [(i, hot.tolist() if i % 3 == 0 else rng.standard_normal(16).tolist()) for i in range(300)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    usable = ann.usable(df)
    got = ann.search(usable, usable.where("vec_id % 60 = 0"), 20).collect()
    for q in (0, 60, 120):
        mine = sorted((r.rank, r.vec_id) for r in got if r.query_id == q)
        assert [i for _, i in mine] == [i for i in range(0, 300, 3) if i != q][:20]
