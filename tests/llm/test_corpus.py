"""Decontamination, set join, substring removal and the pipeline, against brute force."""

import hashlib
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from hamcover.llm import decontaminate, setjoin, substrings
from hamcover.llm import common
from hamcover.llm.common import folded_words, hashed_words, plain_words
from hamcover.llm.components import components
from hamcover.llm.fmindex import FmIndex
from hamcover.llm.suffixes import Shard, suffix_array

FOLDED = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
PLAIN = re.compile(r"[^\x20\x09-\x0D]+")
HARD = ["", None, "one", "Ünïcode ÀB c_d 1.5 x\x00y", "a\xa0b c", "tab\tnew\x0bline\x1fq", "İstanbul K"]


def test_words():
    lower = lambda t: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t)
    for t in HARD:
        assert [w.decode() for w in folded_words(t)] == FOLDED.findall(lower(t or ""))
        assert [w.decode() for w in plain_words(t)] == PLAIN.findall(t or "")


def test_hashed_words(monkeypatch):
    texts = [*HARD, "same words here", "here same", "", "x" * 500 + " y", None, "words"]
    for folded, split in ((False, plain_words), (True, folded_words)):
        for size in (1 << 20, 64, 7):
            monkeypatch.setattr(common, "HASH_BYTES", size)
            h, bounds = hashed_words(texts, folded)
            every = [w for t in texts for w in split(t)]
            assert np.diff(bounds).tolist() == [len(split(t)) for t in texts] and len(h) == len(every)
            known = {}
            assert all(known.setdefault(w, x) == x for w, x in zip(every, h.tolist(), strict=True)) and len(set(known.values())) == len(known)
            if size == 1 << 20:
                first = h
            assert (h == first).all()


def vocabulary_texts(n, words, low, high, seed):
    rng = np.random.default_rng(seed)
    return [" ".join(f"w{rng.integers(words)}" for _ in range(rng.integers(low, high))) for _ in range(n)]


# Suffix arrays and the full-text index.


def test_suffix_array_and_matches():
    rng = np.random.default_rng(0)
    for n in (1, 2, 50, 400):
        text = rng.integers(1, 4, n)
        order = suffix_array(text, n)
        assert sorted(range(n), key=lambda i: text[i:].tolist()) == order.tolist()
        pattern = np.append(rng.integers(1, 5, 30), -1)
        starts = np.arange(30)
        got = Shard(text, n).longest(pattern, starts)
        whole = text.tolist()
        for s, length in zip(starts, got, strict=True):
            p = pattern[s:-1].tolist()
            best = max(next((k for k in range(min(len(p), n - i)) if whole[i + k] != p[k]), min(len(p), n - i)) for i in range(n))
            assert best == length


def test_backward_search():
    rng = np.random.default_rng(1)
    sizes = np.append(rng.integers(1, 90, 15), 1)
    index = FmIndex(rng.integers(1, 6, sizes.sum()), sizes, 6)
    text, owner = index.text, np.repeat(np.arange(16), sizes + 1)
    assert not hasattr(index, "order") and len(index.samples) < len(text) / 3
    stream = rng.integers(0, 6, 90)
    ends = np.arange(1, 91)
    flat = text.tolist()
    for least in (1, 2):
        length, lo, hi = index.matching_statistics(stream, ends, 8, least)
        for e, n, a, b in zip(ends, length, lo, hi, strict=True):
            places = lambda m, e=e: [i for i in range(len(flat) - m + 1) if flat[i : i + m] == stream[e - m : e].tolist()]
            ok = [m for m in range(1, min(8, e) + 1) if 0 not in stream[e - m : e] and len(places(m)) >= least]
            assert n == (max(ok) if ok else 0)
            if n:
                assert sorted(index.owners(np.arange(a, b)).tolist()) == sorted(owner[places(n)].tolist())


# Decontamination.


def brute_hits(docs, items, window):
    out = {}
    grams = []
    for item, t in items:
        w = [x.decode() for x in folded_words(t)]
        k = min(window, len(w))
        grams += [(item, tuple(w[i : i + k])) for i in range(len(w) - k + 1) if k]
    for doc, t in docs:
        w = [x.decode() for x in folded_words(t)]
        hit, found = set(), set()
        for item, g in grams:
            for i in range(len(w) - len(g) + 1):
                if tuple(w[i : i + len(g)]) == g:
                    hit |= set(range(i, i + len(g)))
                    found.add(str(item) if item is not None else "")
        out[doc] = (len(w), len(hit), found)
    return out


def test_decontamination(spark, make_docs, monkeypatch):
    texts = vocabulary_texts(40, 6, 0, 60, 2) + [None, "", "W1, w2! W3", "x " * 5000]
    items = [(1, texts[0]), (2, "w1 w2 w3"), (3, None), (4, "!!"), (None, " ".join(texts[3].split()[:12])), (2, "w5 w5"), (6, " ".join(texts[5].split()[4:19]))]
    docs = make_docs(texts).withColumn("decontamination", F.lit(1)).repartition(3)
    tests = spark.createDataFrame(items, "item_id bigint, text string").withColumn("id", F.lit(0))
    want = brute_hits(list(enumerate(texts)), items, 4)
    for block in (32_000_000, 100):
        monkeypatch.setattr(decontaminate, "TEST_BLOCK_CHARS", block)
        monkeypatch.setattr(decontaminate, "SHARD_BYTES", 2_000 if block == 100 else 24_000_000)
        monkeypatch.setattr(decontaminate, "SHARD_MATCHES", 20 if block == 100 else 2_000_000)
        found = decontaminate.find_matches(docs, tests, window=4)
        got = found.select("doc_id", "decontamination.n_words", decontaminate.n_hit("decontamination").alias("n_hit"), decontaminate.item_ids("decontamination").alias("ids"), "decontamination.matches", "text").collect()
        assert {r.doc_id: (r.n_words, r.n_hit, set(r.ids)) for r in got} == want
    item_words = {k: [w for i, t in items if ("" if i is None else str(i)) == k for w in [folded_words(t)]] for k in ("1", "2", "", "6")}
    for r in got:
        words = folded_words(r.text)
        for m in r.matches:
            assert any(words[m.doc_start : m.doc_start + m.length] == w[m.item_start : m.item_start + m.length] for w in item_words[m.item_id])
    kept = decontaminate.decontaminated(docs, tests, window=4)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {i for i, (_, n, _) in want.items() if not n}
    assert decontaminate.find_matches(docs, tests.where("false")).where("size(decontamination.matches) > 0").count() == 0


def test_a_passage_of_many_items_in_many_documents(monkeypatch):
    """Matches are named once for each item and document, not once for each of their windows."""
    passage = vocabulary_texts(1, 900, 40, 41, 3)[0]
    tests = decontaminate.TestTexts([(str(i), f"a{i} {passage} b{i}") for i in range(1000)], 10)
    texts = [f"c{i} {passage} d{i} e" for i in range(1000)]
    assert decontaminate.shard_matches(texts, tests) is not None
    monkeypatch.setattr(decontaminate, "SHARD_MATCHES", 10**7)
    n_words, (doc, item, begin, at, length) = decontaminate.shard_matches(texts, tests)
    assert len(doc) == 1_000_000 and len(set(zip(doc.tolist(), item.tolist(), strict=True))) == 1_000_000
    assert set(begin.tolist()) == set(at.tolist()) == {1} and set(length.tolist()) == {40} and set(n_words.tolist()) == {43}
    again = decontaminate.TestTexts([("x", "a " * 2000)], 10)
    _, (doc, *_) = decontaminate.shard_matches(["a " * 20_000], again)
    assert len(doc) < 25_000


# Set join.


def brute_classes(texts):
    words = [[w.decode() for w in folded_words(t)] for t in texts]
    sets = [{tuple(w[i : i + min(5, len(w))]) for i in range(len(w) - min(5, len(w)) + 1)} if w else set() for w in words]
    parent = list(range(len(texts)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    degree = [0] * len(texts)
    for a in range(len(texts)):
        for b in range(a + 1, len(texts)):
            if sets[a] and sets[b] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                degree[a] += 1
                degree[b] += 1
                x, y = sorted((find(a), find(b)))
                parent[y] = x
    return [find(i) for i in range(len(texts))], degree


def edited(text, n, rng):
    words = text.split()
    for i in rng.choice(len(words), n, replace=False):
        words[i] = f"new{rng.integers(10**6)}"
    return " ".join(words)


def test_set_join_as_brute_force(spark, make_docs):
    rng = np.random.default_rng(5)
    base = vocabulary_texts(25, 5000, 150, 220, 6)
    texts = []
    for t in base:
        texts += [t, edited(t, 1, rng), edited(t, 3, rng), edited(t, 6, rng), t.upper()]
    passage = vocabulary_texts(1, 5000, 60, 61, 7)[0]
    texts += [passage + " " + t for t in vocabulary_texts(60, 9000, 60, 90, 8)]
    texts += [None, "", "two words", "Two, words!", "!!", "x " * 30_000, "x " * 20_000]
    docs = make_docs(texts).withColumn("a", F.lit(1)).withColumn("rep", F.lit(2)).repartition(4)
    got = {r.doc_id: r for r in setjoin.similar_documents(docs).collect()}
    classes, degree = brute_classes(texts)
    assert [got[i].class_id for i in range(len(texts))] == classes
    assert [got[i].n_links for i in range(len(texts))] == degree
    every = {r.doc_id: r for r in setjoin.similar_documents(docs, exact=True).collect()}
    assert [(every[i].class_id, every[i].n_links) for i in range(len(texts))] == list(zip(classes, degree, strict=True))
    kept = setjoin.one_of_each(docs)
    assert kept.columns == docs.columns and sorted(r.doc_id for r in kept.collect()) == sorted(set(classes))


def test_set_join_recall_at_the_threshold(spark, make_docs):
    """600 near copies, nearly all of their pairs at 0.80 to 0.85: links as brute force has them."""
    rng = np.random.default_rng(9)
    base = vocabulary_texts(1, 9000, 300, 301, 9)[0]
    texts = [edited(base, 3, rng) for _ in range(600)]
    sets = setjoin.shingles(texts)
    every, ids = np.unique(np.concatenate(sets), return_inverse=True)
    sizes = np.array([len(x) for x in sets])
    has = np.zeros((600, len(every)), np.float32)
    has[np.repeat(np.arange(600), sizes), ids] = 1
    shared = has @ has.T
    alike = shared / (sizes[:, None] + sizes - shared)
    np.fill_diagonal(alike, 0)
    degree = (alike >= 0.8 - 1e-9).sum(axis=1)
    assert ((alike >= 0.8) & (alike < 0.85)).sum() > 0.9 * degree.sum()
    got = {r.doc_id: r for r in setjoin.similar_documents(make_docs(texts)).collect()}
    assert sum(r.n_links for r in got.values()) >= 0.999 * degree.sum() and all(got[i].n_links <= degree[i] for i in got)
    assert {r.class_id for r in got.values()} == {0}


def test_set_join_of_one_large_group(spark, make_docs, monkeypatch):
    """More near copies than a leaf holds: one class, links linear in the group."""
    rng = np.random.default_rng(9)
    t = vocabulary_texts(1, 9000, 300, 301, 10)[0]
    texts = [edited(t, 2, rng) for _ in range(300)] + [t] * 200 + vocabulary_texts(30, 9000, 100, 200, 11)
    pairs = []
    verified = setjoin.verified
    monkeypatch.setattr(setjoin, "verified", lambda p, d: pairs.append(p.count()) or verified(p, d))
    got = setjoin.similar_documents(make_docs(texts)).collect()
    assert {r.class_id for r in got if r.doc_id < 500} == {0} and all(r.class_id == r.doc_id for r in got if r.doc_id >= 500)
    assert pairs[0] < 300 * 60


def test_set_join_counts_all_links_of_large_buckets(spark, make_docs, monkeypatch):
    """Buckets of more than a leaf: near copies, texts at the threshold that hang on one of them, and a shared passage."""
    rng = np.random.default_rng(12)
    t = vocabulary_texts(1, 9000, 300, 301, 13)[0]
    texts = [edited(t, int(n), rng) for n in rng.integers(1, 8, 160)]
    texts += [edited(x, 6, rng) for x in texts[:40]] + texts[:3]
    passage = vocabulary_texts(1, 5000, 60, 61, 14)[0]
    texts += [passage + " " + x for x in vocabulary_texts(150, 9000, 70, 80, 15)]
    texts += [edited(x, 2, rng) for x in texts[-150:]]
    classes, degree = brute_classes(texts)
    assert max(degree[:200]) > 2 * setjoin.LEAF and len(set(degree[:200])) > 20

    def held(**sizes):
        levels, write = [], setjoin.written
        for name, value in sizes.items():
            monkeypatch.setattr(setjoin, name, value)
        monkeypatch.setattr(setjoin, "written", lambda df, what: levels.append(what == "buckets") or write(df, what))
        got = {r.doc_id: r for r in setjoin.similar_documents(make_docs(texts).repartition(4)).collect()}
        monkeypatch.setattr(setjoin, "written", write)
        assert [got[i].class_id for i in range(len(texts))] == classes
        assert [got[i].n_links for i in range(len(texts))] == degree
        return sum(levels)

    assert held(BLOCK=20) == 1
    assert held(SPLIT=setjoin.LEAF) > 1


def test_set_join_odd_rows(spark, make_docs):
    docs = make_docs(["a b c d e f", "a b c d e f", "a b c d e f", "q"], ids=[5, 5, None, 3])
    got = sorted(((r.doc_id, r.class_id) for r in setjoin.similar_documents(docs).collect()), key=str)
    assert got == [(3, 3), (5, 5), (5, 5), (None, None)]
    assert setjoin.similar_documents(docs.where("false")).count() == 0


def test_components(spark):
    rng = np.random.default_rng(0)
    links = [(i, i + 1) for i in range(40)] + [(100, i) for i in range(101, 160)] + [(int(a), int(b)) for a, b in rng.integers(200, 300, (60, 2))] + [(7, 7)]
    got = {r.id: r.label for r in components(spark.createDataFrame(links, "a bigint, b bigint")).collect()}
    parent = {x: x for ab in links for x in ab}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        x, y = sorted((find(a), find(b)))
        parent[y] = x
    assert all(got[x] == find(x) for x in got) and set(got) >= {0, 40, 100, 159}


# Substrings.


def brute_removal(docs, window=13):
    first = {}
    for doc, t in docs:
        w = PLAIN.findall(t or "")
        for i in range(len(w) - window + 1):
            g = tuple(w[i : i + window])
            first[g] = min(first.get(g, doc), doc)
    out = {}
    for doc, t in docs:
        w = PLAIN.findall(t or "")
        gone = set()
        for i in range(len(w) - window + 1):
            if first[tuple(w[i : i + window])] < doc:
                gone |= set(range(i, i + window))
        left = [x for i, x in enumerate(w) if i not in gone]
        out[doc] = (len(w), len(gone), hashlib.sha256(" ".join(left).encode()).hexdigest())
    return out


@pytest.mark.parametrize("shard, hot", [(500_000, 65_536), (300, 65_536), (2_000, 60)])
def test_substring_removal(spark, make_docs, monkeypatch, shard, hot):
    monkeypatch.setattr(substrings, "SHARD_CODES", shard)
    monkeypatch.setattr(substrings, "HOT_CODES", hot)
    rng = np.random.default_rng(12)
    pool = vocabulary_texts(6, 5000, 14, 60, 13)
    texts = []
    for _ in range(80):
        parts = vocabulary_texts(2, 5000, 0, 30, int(rng.integers(10**6)))
        texts.append("\n".join([parts[0], *(pool[k] for k in rng.integers(0, 6, rng.integers(0, 3))), parts[1]]))
    texts += [texts[3], texts[3], None, "", "a b", "x " * 3000, "x " * 2000, "y z " * 500, "é " * 40, vocabulary_texts(1, 3, 400, 401, 1)[0], vocabulary_texts(1, 3, 400, 401, 2)[0]]
    docs = make_docs(texts).withColumn("key", F.lit(1)).withColumn("gone", F.lit(1)).repartition(5)
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substrings.without_repeats(docs).collect()}
    assert got == brute_removal(list(enumerate(texts)))


def test_substring_odd_rows(spark, make_docs):
    long = " ".join(map(str, range(20)))
    docs = make_docs([long, long, long], ids=[4, 4, None])
    got = sorted(((r.doc_id, r.n_removed) for r in substrings.without_repeats(docs).collect()), key=str)
    assert got == [(4, 0), (4, 0), (None, 0)]
    assert substrings.without_repeats(docs.where("false")).count() == 0


def test_hot_keys_fill_no_shard(monkeypatch):
    """2 million words share one key: with the four words that are its least hash in all windows around them."""
    rng = np.random.default_rng(3)
    phrase = min((f"a{k} b{k} c{k} d{k}" for k in range(20_000)), key=lambda p: int(common.gram_hashes(hashed_words([p])[0], 4)[0]))
    texts = [" ".join([*(f"w{x}" for x in rng.integers(10**6, size=9)), phrase, *(f"w{x}" for x in rng.integers(10**6, size=9))]) for _ in range(20_000)]
    hot_text, most = texts * 5, []  # copies in other slices
    batches = [pa.RecordBatch.from_arrays([pa.array(range(i, i + 20_000)), pa.array(hot_text[i : i + 20_000])], names=["doc_id", "text"]) for i in range(0, 100_000, 20_000)]
    asked = pa.Table.from_batches(list(substrings._emit_keys(iter(batches)))).sort_by("key")
    found = pa.Table.from_batches(list(substrings._repeated(iter(asked.to_batches(max_chunksize=1000)))))
    key = hashed_key(phrase)
    hot = found.filter(pc.is_null(found["doc_id"]))["key"].to_pylist()
    assert key in hot
    told = found.filter(pc.is_valid(found["doc_id"])).group_by("doc_id").aggregate([("key", "list")]).sort_by("doc_id")
    keys = pa.array(told["key_list"].to_pylist(), pa.list_(pa.int64()))
    cut = pa.array([[k for k in row if k in set(hot)] for row in keys.to_pylist()], pa.list_(pa.int64()))
    ids = told["doc_id"].to_pylist()
    rows = pa.RecordBatch.from_arrays([pa.array(ids), pa.array([hot_text[i] for i in ids]), keys, cut], names=["doc_id", "text", "keys", "hot"])
    contents = pa.Table.from_batches(list(substrings._segment_rows(True)(iter([rows])))).sort_by([("key", "ascending"), ("seg", "ascending")])
    assert len(set(contents["key"].to_pylist())) > 100_000  # single windows
    sizes, real = [], substrings.shard_minima
    monkeypatch.setattr(substrings, "shard_minima", lambda words, size, low: sizes.append(len(words)) or real(words, size, low))
    minima = pa.Table.from_batches(list(substrings._search_shards(iter(contents.to_batches(max_chunksize=5000)))))
    assert max(sizes) < substrings.SHARD_CODES + 2 * substrings.HOT_CODES and len(sizes) > 2
    assert minima.num_rows == contents.group_by(["key", "seg"]).aggregate([]).num_rows and all(m[0] < 20_000 for m in minima["minima"].to_pylist())


def hashed_key(phrase: str) -> int:
    return int(common.gram_hashes(hashed_words([phrase])[0], 4)[0].view(np.int64))


# Pipeline.


def test_pipeline_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["language_id", "set_join", "decontaminate", "secret_links", "pieces"]
    one = stages["language_id"](spark, docs, sf)
    two = stages["set_join"](spark, one, sf)
    three = stages["decontaminate"](spark, two, sf)
    four = stages["secret_links"](spark, three, sf)
    five = stages["pieces"](spark, four, sf)
    assert one.columns == two.columns == three.columns == four.columns == docs.columns
    texts = {r.doc_id: r.text for r in docs.collect()}
    ids = sorted(texts)
    classes, _ = brute_classes([texts[i] for i in ids])
    kept = {ids[c] for c in set(classes)}
    assert {r.doc_id for r in two.collect()} == kept
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    dirty = {d for d, (_, n, _) in brute_hits([(i, texts[i]) for i in kept], items, 10).items() if n}
    assert {r.doc_id for r in three.collect()} == kept - dirty
    out = {r.doc_id: r for r in five.collect()}
    assert set(out) == kept - dirty and all(r.n_pieces == len(r.piece_ids) and r.round_trip for r in out.values())
    run = corpus_pipeline.run(spark, sf)
    assert {(r.doc_id, r.n_pieces) for r in run.collect()} == {(i, r.n_pieces) for i, r in out.items()}


def test_pipeline_of_no_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("false")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf)
    assert docs.count() == 0
