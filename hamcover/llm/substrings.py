"""Removal of repeated passages with compressed full-text indexes.

A window is `WINDOW` consecutive words of a document. Equal windows have the same key: the least hash among the
four-grams inside. Neighbouring windows of one document that share a key make a segment (of 17 words on average), and segments go to the
shard of their key. So all places of a window meet in one shard, however many shards there are, and each document is streamed
only through the shards that can hold a part of it. A key with more than `HOT_CODES` words in its segments is hot: its segments are cut
into single windows, each with the window's own hash as key, so no key's distinct words fill a shard.

A shard is an index of the distinct segments of its keys: a Burrows-Wheeler transform in a wavelet matrix, with the segment of every
fourth place sampled. Backward search gives matching statistics of each segment, and where they reach the window, the range of all its places;
going back from these to sampled ones tells the segments, hence the least doc_id that has the window. Words covered by a window of a smaller doc_id go.

Steps: keys that only one document has are found out first, by a pass that shuffles keys and ids only; the other segments
are shuffled once, without the repetitions inside a batch of documents. Places of a segment don't go to the shard, only
its text does; shards' results are joined to places by the segment's key and hash, a join Spark can split where a segment is very common.
The shuffle files of a step go when its table is written.

Segments travel as text, and words are compared by 64 bits of their hash inside a shard. Segments are known by 128 bits: their own hash and their key.

Defined results: null texts have no words; documents of fewer than `WINDOW` words keep all; a row without doc_id keeps all and removes nothing elsewhere; rows that
repeat a doc_id don't remove from each other; other columns are not looked at.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.llm.common import SHA256_OF_NOTHING, gram_hashes, hashed_bytes, hashed_words, mixed, plain_words, span_hashes, text_slices, written
from hamcover.llm.fmindex import FmIndex

WINDOW, ANCHOR = 13, 4
#: A shard is closed at so many codes, at the end of a key.
SHARD_CODES = 500_000
#: Words in a key's segments, equal ones of a slice counted once, beyond which the key is hot.
HOT_CODES = 65_536
#: Hot keys up to so many are broadcast (8 bytes each); more are joined as Spark sees fit.
HOT_KEYS = 1 << 20


def segments(h: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of texts' word hashes: text, key, first word (in h) and number of windows of each segment, in order."""
    n = len(h) - WINDOW + 1
    if n <= 0:
        return tuple(np.empty(0, t) for t in (np.int64, np.uint64, np.int64, np.int64))
    # Least four-gram hash of each window: of ten of them, by eights and what is left.
    least, span = gram_hashes(h, ANCHOR), 1
    width = WINDOW - ANCHOR + 1
    while 2 * span <= width:
        least, span = np.minimum(least[:-span], least[span:]), 2 * span
    key = np.minimum(least[:n], least[width - span : width - span + n])
    text = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    whole = text[:n] == text[WINDOW - 1 :]
    new = whole.copy()
    new[1:] &= (key[1:] != key[:-1]) | (text[1:n] != text[: n - 1])
    start = np.flatnonzero(new)
    # A segment ends where the next begins, or where its text has no more windows.
    last = np.maximum(bounds[text[start] + 1] - WINDOW + 1, start)
    stop = np.minimum(np.append(start[1:], n), last)
    return text[start], key[start], start, stop - start


def _segment_hashes(h: np.ndarray, start: np.ndarray, windows: np.ndarray) -> np.ndarray:
    return span_hashes(h, start, start + windows + WINDOW - 1)


def _emit_keys(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (dest, key, doc_id, codes, kind). Kind 0 asks whether the key has another document; 1 only tells that it has one here; 2 is known to be repeated.
    Kinds 0 and 1 have the words in the key's distinct segments here.

    A key that several documents of a slice have is told once, however many they are, and their own rows go
    anywhere (dest), so a common key makes no large partition."""
    for batch in text_slices(it, SLICE_BYTES):
        h, bounds = hashed_words(batch.column(1).to_pylist())
        text, key, start, windows = segments(h, bounds)
        if not len(key):
            continue
        seg = _segment_hashes(h, start, windows)
        order = np.lexsort((seg, key))
        fresh = np.concatenate([[True], (key[order][1:] != key[order][:-1]) | (seg[order][1:] != seg[order][:-1])])
        counted = np.zeros(len(key), np.int64)
        counted[order] = np.where(fresh, windows[order] + WINDOW - 1, 0)
        order = np.lexsort((text, key))
        key, text, counted = key[order], text[order], counted[order]
        starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        codes = np.add.reduceat(counted, starts)
        once = np.concatenate([[True], (key[1:] != key[:-1]) | (text[1:] != text[:-1])])
        key, doc = key[once], batch.column(0).to_numpy()[text[once]]
        first = np.concatenate([[True], key[1:] != key[:-1]])
        group, starts = np.cumsum(first) - 1, np.flatnonzero(first)
        varied = np.maximum.reduceat(doc, starts) != np.minimum.reduceat(doc, starts)
        known = varied[group]
        asks, tell = first & ~known, first & known  # the same id again asks once
        dest = np.where(known, mixed(doc.view(np.uint64)), key)
        nothing = np.zeros(np.count_nonzero(known), np.int64)
        parts = [(dest[known], key[known], doc[known], nothing, 2), (key[tell], key[tell], doc[tell], codes[varied], 1), (key[asks], key[asks], doc[asks], codes[~varied], 0)]
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.concatenate([p[k].view(np.int64) for p in parts])) for k in range(4)] + [pa.array(np.concatenate([np.full(len(p[0]), p[4], np.int8) for p in parts]))],
            names=["dest", "key", "doc_id", "codes", "kind"],
        )


#: Bytes of texts that a task works on at once, but for a single longer text.
SLICE_BYTES = 4 << 20


def _repeated(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by key. Those that ask stay if another row has the key; a key whose codes are too many is told without a document.

    The last row of a batch waits for the next one, with the codes of its key so far."""
    rows = lambda doc, key: pa.RecordBatch.from_arrays([doc, pa.array(key)], names=["doc_id", "key"])
    hot = lambda key: rows(pa.nulls(len(key), pa.int64()), key)
    held = tuple(np.empty(0, t) for t in (np.int64, np.int64, np.int64, np.int8))
    for batch in it:
        now = [batch.column(k).to_numpy() for k in (1, 2, 3, 4)]
        through = now[3] == 2
        if through.any():
            yield rows(pa.array(now[1][through]), now[0][through])
        key, doc, codes, kind = (np.append(a, b[~through]) for a, b in zip(held, now, strict=True))
        if not len(key):
            continue
        starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        size = np.diff(np.append(starts, len(key)))
        out = (kind == 0) & np.repeat(size > 1, size)
        total = np.add.reduceat(codes, starts)
        # A row of the last key that has found its like asks no more.
        held = key[-1:], doc[-1:], total[-1:], np.where(size[-1:] > 1, 1, kind[-1:]).astype(np.int8)
        if out.any():
            yield rows(pa.array(doc[out]), key[out])
        if (total[:-1] > HOT_CODES).any():
            yield hot(key[starts[:-1]][total[:-1] > HOT_CODES])
    if (held[2] > HOT_CODES).any():
        yield hot(held[0])


def _single_windows(h: np.ndarray, hot: np.ndarray, text: np.ndarray, key: np.ndarray, start: np.ndarray, windows: np.ndarray) -> tuple[np.ndarray, ...]:
    """The segments, those of hot keys cut into windows with keys of their own."""
    pieces = np.where(hot, windows, 1)
    at = np.repeat(start, pieces) + np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    cut, keys = np.repeat(hot, pieces), np.repeat(key, pieces)
    keys[cut] = mixed(keys[cut] + span_hashes(h, at[cut], at[cut] + WINDOW))
    return np.repeat(text, pieces), keys, at, np.where(cut, 1, np.repeat(windows, pieces))


def _segment_rows(contents: bool):
    """From (doc_id, text, keys, hot): segments with repeated keys. Contents: (key, seg, low, high, body), once for a slice, with the least and greatest id;
    else places: (key, seg, doc_id, start)."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in text_slices(it, SLICE_BYTES):
            names = batch.schema.names
            column = lambda name, batch=batch, names=names: batch.column(names.index(name))
            h, bounds, data, begins = hashed_bytes([(t or "").encode("utf-8", "surrogatepass") for t in column("text").to_pylist()])
            text, key, start, windows = segments(h, bounds)
            own = mixed(key + mixed(text.astype(np.uint64)))

            def among(name: str, own: np.ndarray, column=column) -> np.ndarray:
                lists = column(name)
                asked = lists.flatten().to_numpy().view(np.uint64)
                of = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
                return np.isin(own, mixed(asked + mixed(of.astype(np.uint64))))

            wanted = among("keys", own)
            text, key, start, windows = text[wanted], key[wanted], start[wanted], windows[wanted]
            if not len(key):
                continue
            hot = among("hot", own[wanted])
            if hot.any():
                text, key, start, windows = _single_windows(h, hot, text, key, start, windows)
            doc, seg = column("doc_id").to_numpy()[text], _segment_hashes(h, start, windows).view(np.int64)
            if not contents:
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(seg), pa.array(doc), pa.array((start - bounds[text]).astype(np.int32))], names=["key", "seg", "doc_id", "start"])
                continue
            order = np.lexsort((seg, key))
            one = np.flatnonzero(np.concatenate([[True], (key[order][1:] != key[order][:-1]) | (seg[order][1:] != seg[order][:-1])]))
            low, high = np.minimum.reduceat(doc[order], one), np.maximum.reduceat(doc[order], one)
            at = order[one]
            ends = np.append(begins, len(data))[start[at] + windows[at] + WINDOW - 1]
            bodies = [data[a:b].rstrip() for a, b in zip(begins[start[at]].tolist(), ends.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays(
                [pa.array(key[at].view(np.int64)), pa.array(seg[at]), pa.array(low), pa.array(high), pa.array(bodies, pa.binary())], names=["key", "seg", "low", "high", "body"]
            )

    return run


def _ramp(size: np.ndarray) -> np.ndarray:
    """0 to n - 1 for each size n."""
    return np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)


def shard_minima(words: np.ndarray, size: np.ndarray, low: np.ndarray) -> np.ndarray:
    """For each window of each segment, in order: the least id of all segments of the shard that have the window. Segments come by `low`, the least first."""
    codes = np.unique(words, return_inverse=True)[1].astype(np.int32) + 1
    index = FmIndex(codes, size, int(codes.max()) + 1)
    windows = size - WINDOW + 1
    stop = np.repeat(index.begins + WINDOW, windows) + _ramp(windows)
    # A window that is left with one place has only its own.
    length, lo, hi = index.matching_statistics(index.text, stop, WINDOW, least=2)
    found = np.repeat(low, windows)
    shared = np.flatnonzero(length == WINDOW)
    if len(shared):
        lows, first, back = np.unique(lo[shared], return_index=True, return_inverse=True)
        places = hi[shared][first] - lows
        owners = index.owners(np.repeat(lows, places) + _ramp(places))
        found[shared] = low[np.minimum.reduceat(owners, np.cumsum(places) - places)][back]
    return found


class _Pile:
    """Distinct segments, in order of key and seg, until a shard is full."""

    def __init__(self):
        self.parts: list[list[np.ndarray]] = []  # key, seg, low, high, size, words
        self.codes = 0

    def add(self, key: np.ndarray, seg: np.ndarray, low: np.ndarray, high: np.ndarray, bodies: pa.Array) -> None:
        """Rows of one segment become one, also with the last row from before."""
        if not len(key):
            return
        fresh = np.concatenate([[True], (key[1:] != key[:-1]) | (seg[1:] != seg[:-1])])
        one = np.flatnonzero(fresh)
        low, high = np.minimum.reduceat(low, one), np.maximum.reduceat(high, one)
        key, seg = key[one], seg[one]
        if self.parts and self.parts[-1][0][-1] == key[0] and self.parts[-1][1][-1] == seg[0]:
            last = self.parts[-1]
            last[2][-1], last[3][-1] = min(last[2][-1], low[0]), max(last[3][-1], high[0])
            key, seg, low, high, one = key[1:], seg[1:], low[1:], high[1:], one[1:]
        if len(key):
            words, bounds = hashed_bytes(bodies.take(pa.array(one)).to_pylist())[:2]
            self.parts.append([key, seg, low, high, np.diff(bounds), words])
            self.codes += len(words)

    def searched(self) -> Iterator[pa.RecordBatch]:
        """(key, seg, minima) of segments that some document has to give up a part of."""
        if not self.parts:
            return
        key, seg, low, high, size, words = (np.concatenate([p[k] for p in self.parts]) for k in range(6))
        self.parts, self.codes = [], 0
        order = np.argsort(low, kind="stable")
        begins = np.cumsum(size) - size
        key, seg, low, high, size = (x[order] for x in (key, seg, low, high, size))
        minima = shard_minima(words[np.repeat(begins[order], size) + _ramp(size)], size, low)
        offsets = np.concatenate([[0], np.cumsum(size - WINDOW + 1)]).astype(np.int32)
        matter = np.flatnonzero(np.minimum.reduceat(minima, offsets[:-1]) < high)
        lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(minima))
        for i in range(0, len(matter), 20_000):
            take = matter[i : i + 20_000]
            yield pa.RecordBatch.from_arrays([pa.array(key[take]), pa.array(seg[take]), lists.take(pa.array(take))], names=["key", "seg", "minima"])


def _search_shards(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (key, seg, low, high, body) come sorted by key and seg."""
    pile = _Pile()
    for whole in it:
        for i in range(0, whole.num_rows, 4096):
            batch = whole.slice(i, 4096)
            key, seg, low, high = (batch.column(k).to_numpy() for k in range(4))
            bodies, cut = batch.column(4), 0
            if pile.codes >= SHARD_CODES:
                # The shard ends with the last key's last row; that key may go on in this batch.
                ends = np.flatnonzero(key != pile.parts[-1][0][-1])
                cut = int(ends[0]) if len(ends) else len(key)
                pile.add(key[:cut], seg[:cut], low[:cut], high[:cut], bodies.slice(0, cut))
                if cut < len(key):
                    yield from pile.searched()
            pile.add(key[cut:], seg[cut:], low[cut:], high[cut:], bodies.slice(cut))
    yield from pile.searched()


def _remove(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From (doc_id, text, gone: list of first words of windows): counts and the digest and text of what is kept."""
    for whole in it:
        for i in range(0, whole.num_rows, 512):
            batch = whole.slice(i, 512)
            column = {n: batch.column(k) for k, n in enumerate(batch.schema.names)}
            n_words, n_removed, digests, kept = [], [], [], []
            for text, gone in zip(column["text"].to_pylist(), column["gone"], strict=True):
                words = plain_words(text)
                n = len(words)
                left = words
                if gone.is_valid and len(gone.values):
                    starts = gone.values.to_numpy()
                    starts = starts[starts <= n - WINDOW]
                    level = np.zeros(n + 1, np.int32)
                    np.add.at(level, starts, 1)
                    np.add.at(level, starts + WINDOW, -1)
                    level = np.cumsum(level[:-1]).tolist()
                    left = [w for w, x in zip(words, level, strict=True) if not x]
                joined = b" ".join(left)
                n_words.append(n)
                n_removed.append(n - len(left))
                digests.append(hashlib.sha256(joined).hexdigest() if left else SHA256_OF_NOTHING)
                kept.append(joined.decode("utf-8", "replace"))
            yield pa.RecordBatch.from_arrays([column["doc_id"], pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(digests, pa.string()), pa.array(kept, pa.string())], names=["doc_id", "n_words", "n_removed", "kept_sha256", "kept"])


def repeated_keys(docs: DataFrame) -> DataFrame:
    """Rows doc_id, key: the keys of a document's segments that other documents have, too; and hot keys, without a document."""
    asked = docs.where("doc_id is not null and text is not null").mapInArrow(_emit_keys, "dest bigint, key bigint, doc_id bigint, codes bigint, kind tinyint")
    found = asked.repartition("dest").sortWithinPartitions("key").mapInArrow(_repeated, "doc_id bigint, key bigint")
    return written(found, "repeated-keys")


def without_repeats(docs: DataFrame) -> DataFrame:
    """docs: doc_id, text. One row for each: doc_id, n_words, n_removed, kept_sha256, kept (words joined by one space)."""
    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    found = repeated_keys(docs)
    hot = found.where("doc_id is null").select("key").distinct()
    n_hot = hot.count()
    told = found.where("doc_id is not null")
    if n_hot:
        hot = hot.withColumn("is_hot", F.lit(True))
        told = told.join(F.broadcast(hot) if n_hot <= HOT_KEYS else hot, "key", "left")
    else:
        told = told.withColumn("is_hot", F.lit(None).cast("boolean"))
    told = told.groupBy("doc_id").agg(F.collect_list("key").alias("keys"), F.collect_list(F.when(F.col("is_hot"), F.col("key"))).alias("hot"))
    # Documents are shuffled by id; in the last statement both joins read the same exchange.
    with_keys = docs.hint("merge").join(told, "doc_id")
    contents = with_keys.mapInArrow(_segment_rows(True), "key bigint, seg bigint, low bigint, high bigint, body binary")
    minima = contents.repartition("key").sortWithinPartitions("key", "seg").mapInArrow(_search_shards, "key bigint, seg bigint, minima array<bigint>")
    minima = written(minima, "minima")
    places = with_keys.mapInArrow(_segment_rows(False), "key bigint, seg bigint, doc_id bigint, start int")
    gone = F.filter(F.transform("minima", lambda m, i: F.when(m < F.col("doc_id"), F.col("start") + i)), lambda x: x.isNotNull())
    gone = places.join(minima, ["key", "seg"]).select("doc_id", gone.alias("gone")).where(F.size("gone") > 0).groupBy("doc_id").agg(F.flatten(F.collect_list("gone")).alias("gone"))
    return docs.hint("merge").join(gone, "doc_id", "left").select("doc_id", "text", "gone").mapInArrow(_remove, "doc_id bigint, n_words bigint, n_removed bigint, kept_sha256 string, kept string")


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return without_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")).drop("kept")


QUERIES = {"op10_substring_dedup": op10_substring_dedup}
ORACLES = {
    "op10_substring_dedup": r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents
), win AS (
  SELECT doc_id, i, md5(array_to_string(w[i : i + 12], ' ')) AS h
  FROM (SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS i FROM d WHERE len(w) >= 13)
), firsts AS (
  SELECT h, min(doc_id) AS first_doc FROM win GROUP BY h
), gone AS (
  SELECT DISTINCT doc_id, unnest(range(i, i + 13)) AS p FROM win JOIN firsts USING (h) WHERE first_doc < doc_id
), words AS (
  SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS p FROM d
), kept AS (
  SELECT words.doc_id, count(*) AS n_kept, sha256(string_agg(word, ' ' ORDER BY p)) AS kept_sha256
  FROM words ANTI JOIN gone USING (doc_id, p) GROUP BY words.doc_id
)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - coalesce(n_kept, 0) AS BIGINT) AS n_removed, coalesce(kept_sha256, sha256('')) AS kept_sha256
FROM d LEFT JOIN kept USING (doc_id)
"""
}
