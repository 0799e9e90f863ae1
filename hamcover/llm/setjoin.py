"""Similarity join of documents' word shingles by chosen paths.

A document is the set of its five-word shingles, and links are pairs of Jaccard similarity 0.8 or more. Documents with the
same set are joined first; the rest works on one of each such class.

A set becomes `COORDINATES` min-hash values, each a shingle drawn alike for all sets. A run begins with a
bucket for each value of one coordinate. Every bucket is compared in full, and no row leaves one before that: up to `LEAF` sets in one
piece, more in tiles of two blocks of at most about `BLOCK` sets each, which are dealt to different tasks. Only a bucket of more than `SPLIT` sets whose
sampled sets are so unlike that it saves half of the comparisons is split further instead: all its rows go on to `CHILDREN` buckets of `DEPTH` sampled coordinates each.

A pair at the threshold misses all first buckets of `RUNS` runs with a chance of 0.2 ** RUNS, about 3e-6, whatever the buckets' sizes; a split adds
(1 - 0.8 ** DEPTH) ** CHILDREN, about 2e-6, for each level. More alike pairs are missed less often.

Comparisons use 64 bytes, one for each coordinate; pairs whose estimate is `SCREEN` or more are then verified with their whole texts.
A pair counts in the first of its common buckets only. Pairs of tiles are verified where they meet: a tile gives each set's links as a number
and one link for each set to the rest of its class, so rows made grow with the sets while every pair counts.

With `exact=True` candidates are all pairs that share one of their least shingle hashes, as many as a pair at the threshold can't do without: no link is missed,
but rows grow with the square of a group of near copies. The query and the pipeline take the chosen paths.

Defined results: fewer than five words make one shingle of all words; a document without words is a class of its own with no
links; rows of one doc_id are one document; a row without doc_id has no class; repeated rows get one result each; ties go to the least doc_id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.llm.common import Steps, gram_hashes, hashed_words, mixed, text_slices, written
from hamcover.llm.components import components

WORDS, SIMILARITY = 5, 0.8
COORDINATES, RUNS, LEAF, BLOCK, SPLIT = 64, 8, 48, 512, 1 << 14
DEPTH, CHILDREN, SAMPLED, LEVELS = 4, 25, 24, 8
SCREEN = 0.55
SEED = 7

_RNG = np.random.default_rng(SEED)
_A = _RNG.integers(0, 1 << 63, COORDINATES, np.uint64) * np.uint64(2) + np.uint64(1)
_B = _RNG.integers(0, 1 << 63, COORDINATES, np.uint64)


def shingles(texts: list[str | None]) -> list[np.ndarray]:
    """Sorted hashes of each text's distinct shingles."""
    h, bounds = hashed_words(texts, folded=True)
    out = []
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        out.append(np.unique(gram_hashes(h[a:b], min(WORDS, b - a))) if b > a else np.empty(0, np.uint64))
    return out


def signature(grams: np.ndarray) -> np.ndarray:
    """The least hash of the set under each of the hash functions."""
    least = np.full(COORDINATES, ~np.uint64(0))
    for at in range(0, len(grams), 1024):
        np.minimum(least, (grams[at : at + 1024, None] * _A + _B).min(axis=0), out=least)
    return mixed(least)


def _signatures(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in text_slices(it, SLICE_BYTES):
        keys, keys2, bytes_, roots = [], [], [], []
        for grams in shingles(batch.column(1).to_pylist()):
            if not len(grams):
                for x in (keys, keys2, bytes_, roots):
                    x.append(None)
                continue
            s = signature(grams)
            keys.append(int(grams.sum().view(np.int64)))
            keys2.append(int((np.bitwise_xor.reduce(mixed(grams)) + np.uint64(len(grams))).view(np.int64)))
            bytes_.append((s & np.uint64(255)).astype(np.uint8).tobytes())
            roots.append(s[:RUNS].tobytes())
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(keys, pa.int64()), pa.array(keys2, pa.int64()), pa.array(bytes_, pa.binary()), pa.array(roots, pa.binary())],
            names=["doc_id", "k1", "k2", "sig", "roots"],
        )


#: Bytes of texts that a task hashes at once, but for a single longer text.
SLICE_BYTES = 1 << 20


def _roots(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """First buckets of a set: one per run. `path` has the bucket and the child's number of each split on the way."""
    for batch in it:
        if batch.num_rows:
            reps = batch.column(0).to_numpy()
            values = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint64).reshape(-1, RUNS)
            nodes = mixed(values + np.arange(1, RUNS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
            runs = np.tile(np.arange(RUNS, dtype=np.int32), len(reps))
            path = pa.ListArray.from_arrays(np.zeros(len(runs) + 1, np.int32), pa.array([], pa.int64()))
            yield pa.RecordBatch.from_arrays([pa.array(nodes.ravel().view(np.int64)), pa.array(np.repeat(reps, RUNS)), pa.array(runs), path], names=["node", "rep", "run", "path"])


def _alike(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Estimated similarity: share of equal bytes, less what unequal values have in common by chance."""
    return ((a == b).mean(axis=1) - 1 / 256) / (1 - 1 / 256)


def _bytes(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(-1, COORDINATES)


def _child(nodes: np.ndarray, j: int, sigs: np.ndarray) -> np.ndarray:
    """The j-th bucket that rows of `nodes` go on to: `DEPTH` coordinates, drawn by the bucket."""
    child = mixed(mixed(nodes.view(np.uint64)) + np.uint64(j + 1))
    for _ in range(DEPTH):
        coordinate = (child >> np.uint64(20)) % np.uint64(COORDINATES)
        value = sigs[np.arange(len(sigs)), coordinate.astype(np.int64)].astype(np.uint64)
        child = mixed(child + (value + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15))
    return child.view(np.int64)


def _first(run: np.ndarray, paths: list[list[int]], a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """For pairs of rows of a bucket, each given as signatures and roots: true where no bucket of an earlier run, or earlier child on the path, has both."""
    first = (a[1] == b[1]).argmax(axis=1) == run
    for k in np.flatnonzero(first).tolist() if any(map(len, paths)) else ():
        for node, j in zip(paths[k][::2], paths[k][1::2], strict=True):
            at = np.array([node])
            first[k] &= not any(_child(at, i, a[0][k : k + 1]) == _child(at, i, b[0][k : k + 1]) for i in range(j))
    return first


def _hashes(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint64).reshape(-1, RUNS)


def _leaves(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All pairs of each small bucket that pass the screen. Rows come sorted by bucket; the last rows of a batch wait for the next."""
    nodes, reps, sigs = np.empty(0, np.int64), np.empty(0, np.int64), np.empty((0, COORDINATES), np.uint8)
    runs, roots, paths = np.empty(0, np.int32), np.empty((0, RUNS), np.uint64), []
    for batch in it:
        if not batch.num_rows:
            continue
        first = len(nodes)
        nodes, reps = np.append(nodes, batch.column(0).to_numpy()), np.append(reps, batch.column(1).to_numpy())
        sigs, roots = np.concatenate([sigs, _bytes(batch.column(2))]), np.concatenate([roots, _hashes(batch.column(3))])
        runs, paths = np.append(runs, batch.column(4).to_numpy()), paths + batch.column(5).to_pylist()
        left, right = [], []
        for d in range(1, LEAF):
            at = np.flatnonzero(nodes[d:] == nodes[:-d]) if d < len(nodes) else np.empty(0, np.int64)
            at = at[at + d >= first]
            if len(at):
                at = at[_alike(sigs[at], sigs[at + d]) >= SCREEN]
                at = at[_first(runs[at], [paths[k] for k in at.tolist()], (sigs[at], roots[at]), (sigs[at + d], roots[at + d]))]
                left.append(reps[at])
                right.append(reps[at + d])
        if left:
            a, b = np.concatenate(left), np.concatenate(right)
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["a", "b"])
        nodes, reps, sigs, runs, roots, paths = nodes[-LEAF:], reps[-LEAF:], sigs[-LEAF:], runs[-LEAF:], roots[-LEAF:], paths[-LEAF:]


def _splitting(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Buckets, each with signatures of some of its rows: those that are worth a split."""
    for batch in it:
        keep = []
        for node, sample in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            sigs = np.frombuffer(b"".join(sample), np.uint8).reshape(-1, COORDINATES)
            a, b = np.triu_indices(len(sigs), 1)
            if CHILDREN * (np.maximum(0, _alike(sigs[a], sigs[b])) ** DEPTH).mean() <= 0.5:
                keep.append(node)
        yield pa.RecordBatch.from_arrays([pa.array(keep, pa.int64())], names=["node"])


def _descend(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of buckets that are split, in all of their next buckets."""
    for whole in it:
        for at in range(0, whole.num_rows, 1024):
            batch = whole.slice(at, 1024)
            nodes, sigs = batch.column(0).to_numpy(), _bytes(batch.column(2))
            runs, paths = batch.column(3), batch.column(4).to_pylist()
            for j in range(CHILDREN):
                on = pa.array([[*p, n, j] for p, n in zip(paths, nodes.tolist(), strict=True)], pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([pa.array(_child(nodes, j, sigs)), batch.column(1), runs, on], names=["node", "rep", "run", "path"])


def _tiles(it: Iterator[pa.RecordBatch]) -> Iterator[list[pa.RecordBatch]]:
    """The rows of each tile, from rows that come sorted by the tile's node, i and j."""
    held, last = [], None
    for batch in it:
        if not batch.num_rows:
            continue
        keys = np.stack([batch.column(batch.schema.get_field_index(k)).to_numpy() for k in ("node", "i", "j")], axis=1)
        cuts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            if held and keys[a].tolist() != last:
                yield held
                held = []
            last = keys[a].tolist()
            held.append(batch.slice(a, b - a))
    if held:
        yield held


def _pairs_of(tile: list[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray]:
    """Places of the pairs of a tile that pass the screen and count here, by the first place."""
    column = lambda name: pa.concat_arrays([x.column(x.schema.get_field_index(name)) for x in tile])
    sigs, roots, block = _bytes(column("sig")), _hashes(column("roots")), column("block").to_numpy()
    run, path = tile[0]["run"][0].as_py(), tile[0]["path"][0].as_py()
    i, j = tile[0]["i"][0].as_py(), tile[0]["j"][0].as_py()
    others, left, right = np.flatnonzero(block == j), [], []
    for a in np.flatnonzero(block == i).tolist():
        b = others[others > a] if i == j else others
        b = b[_alike(sigs[b], sigs[a]) >= SCREEN] if len(b) else b
        if len(b):
            same = np.full(len(b), a)
            b = b[_first(np.full(len(b), run), [path] * len(b), (sigs[same], roots[same]), (sigs[b], roots[b]))]
        left.append(np.full(len(b), a))
        right.append(b)
    return (np.concatenate(left), np.concatenate(right)) if left else (np.empty(0, np.int64), np.empty(0, np.int64))


def _meeting(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of tiles that are in one of the tile's pairs: only their texts are needed."""
    for tile in _tiles(it):
        a, b = _pairs_of(tile)
        if len(a):
            yield pa.Table.from_batches(tile).take(pa.array(np.union1d(a, b))).combine_chunks().to_batches()[0]


def _sets_of(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts become their sets, so that a tile holds no texts."""
    for batch in text_slices(it, SLICE_BYTES):
        at = batch.schema.get_field_index("text")
        grams = pa.array([x.tobytes() for x in shingles(batch.column(at).to_pylist())], pa.large_binary())
        yield pa.RecordBatch.from_arrays([grams if k == at else batch.column(k) for k in range(batch.num_columns)], names=batch.schema.names)


def _joined(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least place of each place's component."""
    label = np.arange(n)
    while True:
        was = label.copy()
        least = np.minimum(label[a], label[b])
        np.minimum.at(label, a, least)
        np.minimum.at(label, b, least)
        label = label[label]
        if (label == was).all():
            return label


def _verify_tiles(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For each set of a tile that has links: a, b (a set of the same class, or itself) and the number of documents it is linked to here."""
    for tile in _tiles(_sets_of(it)):
        a, b = _pairs_of(tile)
        column = lambda name, tile=tile: pa.concat_arrays([x.column(x.schema.get_field_index(name)) for x in tile])
        sets = [np.frombuffer(x, np.uint64) for x in column("text").to_pylist()]
        sizes = np.array([len(x) for x in sets])
        every, ids = np.unique(np.concatenate(sets), return_inverse=True)
        ends = np.cumsum(sizes)
        own, keep = np.zeros(len(every), bool), []
        for x in np.unique(a).tolist():
            own[:] = False
            own[ids[ends[x] - sizes[x] : ends[x]]] = True
            at = np.flatnonzero(a == x)
            for k in at.tolist():
                y = b[k]
                shared = np.count_nonzero(own[ids[ends[y] - sizes[y] : ends[y]]])
                both = sizes[x] + sizes[y]
                if shared >= SIMILARITY * (both - shared) - 1e-9 * both:
                    keep.append(k)
        if keep:
            a, b = a[keep], b[keep]
            reps, copies = column("rep").to_numpy(), column("copies").to_numpy()
            links = np.zeros(len(reps), np.int64)
            np.add.at(links, a, copies[b])
            np.add.at(links, b, copies[a])
            at = np.flatnonzero(links)
            yield pa.RecordBatch.from_arrays([pa.array(reps[at]), pa.array(reps[_joined(len(reps), a, b)][at]), pa.array(links[at])], names=["a", "b", "links"])


def candidates(sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """sets: rep, sig, roots, copies. Returns the pairs a < b of small buckets whose estimate passes the screen, and the rows of large ones with their sizes n."""
    sigs = sets.select("rep", "sig", "roots", "copies")
    rows, small, large, level = sets.select("rep", "roots").mapInArrow(_roots, "node bigint, rep bigint, run int, path array<bigint>"), [], [], 0
    drawn = F.xxhash64("node", "rep")  # another order in each bucket
    while True:
        sizes = rows.groupBy("node").agg(F.count("*").alias("n")).where("n > 1")
        live = rows.join(written(sizes, "bucket-sizes"), "node")
        live = written(live.join(sigs, "rep").select("node", "rep", "sig", "roots", "run", "path", "n", "copies"), "buckets")
        few = live.where(F.col("n") <= LEAF).select("node", "rep", "sig", "roots", "run", "path").repartition("node").sortWithinPartitions("node", "rep")
        small.append(few.mapInArrow(_leaves, "a bigint, b bigint"))
        many = live.where(F.col("n") > LEAF)
        # One row of each of several slots: at most SAMPLED rows of a bucket meet.
        one = many.where(F.col("n") > SPLIT).groupBy("node", F.pmod(drawn, F.lit(SAMPLED)).alias("slot")).agg(F.min(F.struct(drawn.alias("o"), "sig")).alias("x"))
        splits = written(one.groupBy("node").agg(F.collect_list("x.sig").alias("sample")).mapInArrow(_splitting, "node bigint"), "splits")
        if level == LEVELS or not splits.limit(1).count():
            large.append(many)
            break
        large.append(many.join(splits, "node", "left_anti").select(*many.columns))
        down = many.join(splits, "node", "left_semi").select("node", "rep", "sig", "run", "path")
        rows, level = down.mapInArrow(_descend, "node bigint, rep bigint, run int, path array<bigint>"), level + 1
    found, tiled = small[0], large[0]
    for part in small[1:]:
        found = found.union(part)
    for part in large[1:]:
        tiled = tiled.union(part)
    return written(found, "pairs"), tiled


def tile_links(rows: DataFrame, docs: DataFrame) -> DataFrame:
    """rows: of large buckets. Returns a, b, links as _verify_tiles() has them."""
    blocks = F.ceil(F.col("n") / BLOCK).cast("int")
    rows = rows.withColumn("block", F.pmod(F.xxhash64("node", "rep"), blocks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    rows = rows.select("node", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "rep", "sig", "roots", "run", "path", "copies")
    dealt = lambda x: x.repartition("node", "i", "j").sortWithinPartitions("node", "i", "j", "rep")
    meeting = written(dealt(rows).mapInArrow(_meeting, rows.schema), "meeting")
    texts = written(docs.hint("merge").join(meeting.select(F.col("rep").alias("doc_id")).distinct(), "doc_id", "left_semi").dropDuplicates(["doc_id"]), "tile-texts")
    with_texts = meeting.join(texts.select(F.col("doc_id").alias("rep"), "text").hint("merge"), "rep").select(*meeting.columns, "text")
    return dealt(with_texts).mapInArrow(_verify_tiles, "a bigint, b bigint, links bigint")


def _verify(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by a, so its shingles are mostly those of the row before."""
    last, grams = None, np.empty(0, np.uint64)
    for batch in text_slices(it, SLICE_BYTES, "two"):
        keep = []
        others = shingles(batch.column(3).to_pylist())
        for k, (a, other) in enumerate(zip(batch.column(0).to_pylist(), others, strict=True)):
            if a != last:
                last, grams = a, shingles([batch.column(2)[k].as_py()])[0]
            both = np.concatenate([grams, other])
            both.sort()
            shared = int((both[1:] == both[:-1]).sum())
            if shared >= SIMILARITY * (len(both) - shared) - 1e-9 * len(both):
                keep.append(k)
        at = pa.array(keep, pa.int64())
        yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at)], names=["a", "b"])


def verified(pairs: DataFrame, docs: DataFrame) -> DataFrame:
    """The pairs (a, b) of ids whose whole texts have the similarity."""
    ids = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    texts = written(docs.hint("merge").join(ids, "doc_id", "left_semi").dropDuplicates(["doc_id"]), "texts")
    right = texts.select(F.col("doc_id").alias("b"), F.col("text").alias("two"))
    left = texts.select(F.col("doc_id").alias("a"), F.col("text").alias("one"))
    rows = pairs.join(right, "b").join(left.hint("merge"), "a").select("a", "b", "one", "two")
    return rows.mapInArrow(_verify, "a bigint, b bigint")


def _prefixes(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(rep, n, gram) of the least shingle hashes of each set: sets of similarity 0.8 or more share one of those."""
    for batch in text_slices(it, SLICE_BYTES):
        for rep, grams in zip(batch.column(0).to_pylist(), shingles(batch.column(1).to_pylist()), strict=True):
            n = len(grams)
            first = grams[: n - int(np.ceil(SIMILARITY * n - 1e-9)) + 1]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(first), rep, np.int64)), pa.array(np.full(len(first), n, np.int64)), pa.array(first.view(np.int64))], names=["rep", "n", "gram"])


def exact_pairs(sets: DataFrame, docs: DataFrame) -> DataFrame:
    """All pairs a < b of ids that can be similar."""
    texts = docs.hint("merge").join(sets.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi").dropDuplicates(["doc_id"])
    rows = written(texts.select("doc_id", "text").mapInArrow(_prefixes, "rep bigint, n bigint, gram bigint"), "prefixes")
    other = rows.select("gram", F.col("rep").alias("b"), F.col("n").alias("m"))
    alike = (F.col("rep") < F.col("b")) & (F.least("n", "m") >= SIMILARITY * F.greatest("n", "m") - 1e-9)
    return rows.join(other, "gram").where(alike).select(F.col("rep").alias("a"), "b").distinct()


def similar_documents(docs: DataFrame, exact: bool = False) -> DataFrame:
    """docs: doc_id, text. One row per row of docs: doc_id, class_id (least doc_id of its class), n_links.

    n_links counts the other documents that the verified links and the copies of its set connect it to directly.
    """
    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    with Steps() as steps:
        made = written(docs.mapInArrow(_signatures, "doc_id bigint, k1 bigint, k2 bigint, sig binary, roots binary"), "signatures")
        keyed = made.where("doc_id is not null and k1 is not null")
        own = keyed.groupBy("doc_id").agg(F.min(F.struct("k1", "k2")).alias("k")).select("doc_id", "k.k1", "k.k2")
        own = written(own, "set-keys")
        classes = written(own.groupBy("k1", "k2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies")), "set-classes")
        sets = keyed.join(classes.select(F.col("rep").alias("doc_id"), "k1", "k2", "copies"), ["doc_id", "k1", "k2"]).dropDuplicates(["doc_id"]).select(F.col("doc_id").alias("rep"), "sig", "roots", "copies")
        sets = written(sets, "sets")
        if exact:
            links = written(verified(written(exact_pairs(sets, docs), "pairs"), docs), "verified")
            tiled = links.select("a", "b", F.lit(0).cast("long").alias("links")).where("false")
        else:
            pairs, large = candidates(sets)
            links = written(verified(pairs, docs), "verified")
            tiled = written(tile_links(large, docs), "tile-links")
        copies = classes.select("rep", "copies").where("copies > 1")
        ends = links.select("a", "b").union(links.select("b", "a"))
        ends = ends.join(copies, F.col("b") == F.col("rep"), "left").select("a", F.coalesce("copies", F.lit(1)).alias("links"))
        degree = ends.union(tiled.select("a", "links")).groupBy("a").agg(F.sum("links").alias("links"))
        labels = components(links.union(tiled.where("a <> b").select("a", "b")))
        by_set = labels.join(degree, F.col("id") == F.col("a"), "left").select(F.col("id").alias("rep"), "label", "links")
        # Only sets with copies or links have anything to tell their documents.
        told = classes.join(by_set, "rep", "left").where("copies > 1 or label is not null")
        told = written(told.select("k1", "k2", F.coalesce("label", "rep").alias("label"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("links")), "told")
        steps.keep(made, own, told)
    result = own.join(told, ["k1", "k2"], "left").select("doc_id", F.coalesce("label", "doc_id").alias("class_id"), F.coalesce("links", F.lit(0)).cast("long").alias("n_links"))
    rest = made.select("doc_id").join(result, "doc_id", "left")
    return rest.select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))


def one_of_each(docs: DataFrame) -> DataFrame:
    """One document of each class, the one of the least doc_id, with its own columns; documents without an id stay."""
    found = similar_documents(docs).where("doc_id <> class_id").select("doc_id").distinct()
    return docs.join(found, "doc_id", "left_anti").select(*docs.columns)


def op8_set_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_documents(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


QUERIES = {"op8_set_join": op8_set_join}
ORACLES: dict[str, str] = {}
