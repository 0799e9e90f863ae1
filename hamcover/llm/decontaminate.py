"""Benchmark decontamination with training suffix arrays.

Each task sorts the suffixes of the documents it reads, shard by shard of a bounded size, and looks up
every suffix of the test texts in them by binary search. That gives the longest verbatim match of each
test suffix and, for those of at least a window, all places where it occurs. Equal windows of many test texts are one
group, whose places are listed once; a test text is only named where a match begins, so the work grows with the words and the matches, not with
windows times texts times documents. A document's matches are known where the document is read, so nothing is shuffled and no group can grow large.

Words that no test text has cannot be part of a match; a shard keeps the runs of other words that are
as long as the shortest window, which loses no match. Test texts go to the executors in blocks of at
most `TEST_BLOCK_CHARS` characters (a longer single text is a block of its own); for each block the
documents are searched once more, up to `STAGE_BLOCKS` of them in the same stage.

Defined results: a null text has no words and no match; a test text without words matches nothing; a
null item_id is named by the empty string; rows of one item_id count as one item; repeated documents are each judged;
empty tables give no rows or no matches; a column that already has the name of the output is replaced.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hamcover.llm.common import folded_words, written
from hamcover.llm.suffixes import Shard

WINDOW = 10
#: Bound of what one block broadcasts.
TEST_BLOCK_CHARS = 32_000_000
#: A shard ends at so many bytes of documents.
SHARD_BYTES = 12_000_000
#: Blocks that one stage searches for, each with a worker of its own; then the rows are written.
STAGE_BLOCKS = 4
#: A shard of more matches is searched in two halves.
SHARD_MATCHES = 2_000_000

MATCHES = "array<struct<item_id:string,item_start:int,doc_start:int,length:int>>"
_ARROW_MATCHES = pa.list_(pa.struct([("item_id", pa.string()), ("item_start", pa.int32()), ("doc_start", pa.int32()), ("length", pa.int32())]))


class TestTexts:
    """Words of a block of test texts as codes, their suffixes and windows."""

    __test__ = False

    def __init__(self, items: list[tuple[str, str]], window: int):
        self.codes: dict[bytes, int] = {}
        pattern, starts, sizes, left, owner, offset, self.ids = [], [], [], [], [], [], []
        for item, text in items:
            words = folded_words(text)
            if not words:
                continue
            at, w = len(pattern), min(window, len(words))
            pattern += [self.codes.setdefault(x, len(self.codes) + 1) for x in words] + [-1]
            n = len(words)
            starts += range(at, at + n)
            left += range(n, 0, -1)
            sizes += [w] * n
            owner += [len(self.ids)] * n
            offset += range(n)
            self.ids.append(item)
        as_array = lambda x: np.array(x, np.int64)
        self.pattern, self.starts, self.sizes, self.left, self.owner, self.offset = map(as_array, (pattern, starts, sizes, left, owner, offset))
        self.shortest = int(self.sizes.min()) if len(sizes) else 1
        self.depth = int(self.left.max()) if len(left) else 1
        self.id_order = np.array(self.ids, dtype=object)


def _kept_runs(codes: np.ndarray, shortest: int) -> tuple[np.ndarray, np.ndarray]:
    """Start and length of the runs of test words that can hold a window."""
    edge = np.flatnonzero(np.diff(np.concatenate([[0], (codes > 0).view(np.int8), [0]])))
    starts, ends = edge[::2], edge[1::2]
    long = ends - starts >= shortest
    return starts[long], (ends - starts)[long]


def shard_matches(texts: list[str | None], tests: TestTexts) -> tuple[np.ndarray, tuple[np.ndarray, ...]] | None:
    """For documents of one shard: word counts, and (document, item, item start, document start, length) of maximal matches.
    None if several documents have more matches together than are held at once."""
    n_words, parts, docs, offsets, total = np.zeros(len(texts), np.int64), [], [], [], 0
    code_of = tests.codes.get
    for d, text in enumerate(texts):
        words = folded_words(text)
        n_words[d] = len(words)
        if len(words) < tests.shortest:
            continue
        codes = np.fromiter((code_of(w, 0) for w in words), np.int64, len(words))
        for at, n in zip(*_kept_runs(codes, tests.shortest), strict=True):
            parts += [codes[at : at + n], _GAP]
            docs.append(d)
            offsets.append(at - total)
            total += n + 1
    none = tuple(np.empty(0, np.int64) for _ in range(5))
    if not parts:
        return n_words, none
    text = np.concatenate(parts)
    lengths = np.array([len(p) + 1 for p in parts[::2]])
    doc_of, offset_of = np.repeat(docs, lengths), np.repeat(offsets, lengths)
    shard = Shard(text, tests.depth)
    longest = shard.longest(tests.pattern, tests.starts)
    found = np.flatnonzero((longest >= tests.sizes) & (tests.left >= tests.sizes))
    if not len(found):
        return n_words, none
    starts, sizes = tests.starts[found], tests.sizes[found]
    lo = shard.bound(tests.pattern, starts, sizes)
    # Groups of equal windows: those of one size that sort to one place.
    _, one, group = np.unique(np.stack([lo, sizes], axis=1), axis=0, return_index=True, return_inverse=True)
    group, size = group.ravel(), sizes[one]
    lo, hi = lo[one], shard.bound(tests.pattern, starts[one], size, upper=True)
    many = hi - lo
    of = np.repeat(np.arange(len(one)), many)
    places = shard.order[np.repeat(lo - np.cumsum(many) + many, many) + np.arange(many.sum())]
    # The group of the window one word before: of test windows (-1: none that occurs), and of places in documents (-2: none).
    at = np.full(len(tests.starts) + 1, -1)
    at[found] = group
    before_test = np.where(tests.offset[found] > 0, at[found - 1], -1)
    key = places * (int(size.max()) + 1) + size[of]
    order = np.argsort(key)
    seek = key - (int(size.max()) + 1)
    near = order[np.minimum(np.searchsorted(key[order], seek), len(key) - 1)]
    before_place = np.where(key[near] == seek, of[near], -2)
    # A match begins at each pair of a place and a test window of its group whose windows before differ.
    sort = np.lexsort((before_test, group))
    width = len(one) + 3
    ranked = group[sort] * width + before_test[sort] + 2
    edge = lambda previous, side: np.searchsorted(ranked, of * width + previous + 2, side)
    first, last = edge(np.full(len(of), -2), "left"), edge(np.full(len(of), len(one)), "right")
    skip, resume = edge(before_place, "left"), edge(before_place, "right")
    sizes_of = np.concatenate([skip - first, last - resume])
    if sizes_of.sum() > SHARD_MATCHES and len(texts) > 1:
        return None
    begin = np.concatenate([first, resume])
    which = sort[np.repeat(begin - np.cumsum(sizes_of) + sizes_of, sizes_of) + np.arange(sizes_of.sum())]
    places = np.repeat(np.concatenate([places, places]), sizes_of)
    suffix = found[which]
    length = shard.common(places, tests.pattern, tests.starts[suffix])
    return n_words, (doc_of[places], tests.owner[suffix], tests.offset[suffix], places + offset_of[places], length)


_GAP = np.zeros(1, np.int64)


def _search(schema: pa.Schema, text_column: str, output: str, tests_of) -> callable:
    """A mapInArrow function that adds a block's matches to those in `output`, or begins that column."""

    def flush(rows: list[pa.RecordBatch], tests: TestTexts) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(rows).combine_chunks()
        found = shard_matches(table[text_column].to_pylist(), tests)
        if found is None:
            half = table.num_rows // 2
            yield from flush(table.slice(0, half).to_batches(), tests)
            yield from flush(table.slice(half).to_batches(), tests)
            return
        n_words, (doc, item, begin, at, length) = found
        order = np.lexsort((begin, at, doc))
        item_ids = tests.id_order[item[order]] if len(order) else []
        flat = pa.StructArray.from_arrays([pa.array(item_ids, pa.string()), *(pa.array(x[order].astype(np.int32)) for x in (begin, at, length))], fields=list(_ARROW_MATCHES.value_type))
        bounds = np.searchsorted(doc[order], np.arange(len(n_words) + 1)).astype(np.int32)
        new = pa.StructArray.from_arrays([pa.array(n_words), pa.ListArray.from_arrays(bounds, flat)], names=["n_words", "matches"])
        if output in table.column_names:
            old = table[output].combine_chunks()
            both = [(a or []) + (b or []) for a, b in zip(old.field("matches").to_pylist(), new.field("matches").to_pylist(), strict=True)]
            new = pa.StructArray.from_arrays([pa.array(n_words), pa.array(both, _ARROW_MATCHES)], names=["n_words", "matches"])
            table = table.drop_columns([output])
        yield from table.append_column(output, new).cast(schema).to_batches(max_chunksize=2000)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tests, rows, size = tests_of(), [], 0
        for whole in it:
            for i in range(0, whole.num_rows, 512):
                batch = whole.slice(i, 512)
                rows.append(batch)
                size += batch.get_total_buffer_size() * batch.num_rows // max(1, whole.num_rows)
                if size >= SHARD_BYTES:
                    yield from flush(rows, tests)
                    rows, size = [], 0
        if rows:
            yield from flush(rows, tests)

    return run


def find_matches(docs: DataFrame, tests: DataFrame, window: int = WINDOW, text: str = "text", output: str = "decontamination") -> DataFrame:
    """All columns of docs and a struct `output`: n_words, and matches of at least a window, each with its longest extent:
    item_id, item_start, doc_start and length in words."""
    spark = docs.sparkSession
    from pyspark.sql.pandas.types import to_arrow_schema

    tests = tests.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("id"), F.col("text")).where("text is not null")
    chars = tests.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    n_blocks = max(1, -(-int(chars) // TEST_BLOCK_CHARS))
    found = docs.drop(output)
    plain = found.schema
    struct = T._parse_datatype_string(f"n_words bigint, matches {MATCHES}")
    out = T.StructType([*plain.fields, T.StructField(output, struct)])
    arrow = to_arrow_schema(out)
    name = uuid.uuid4().hex
    for block in range(n_blocks):
        part = tests.where(F.pmod(F.xxhash64("id", "text"), F.lit(n_blocks)) == block) if n_blocks > 1 else tests
        shared = spark.sparkContext.broadcast([(r.id, r.text) for r in part.toLocalIterator()])
        found = found.mapInArrow(_search(arrow, text, output, _tests_of(shared, window, f"{name}-{block}")), out)
        if (block + 1) % STAGE_BLOCKS == 0 and block + 1 < n_blocks:
            found = written(found, "decontamination")
    return found


#: Test texts of this process by their block: a worker that runs several tasks prepares them once.
_PREPARED: dict[str, TestTexts] = {}


def _tests_of(shared, window: int, name: str):
    def prepared() -> TestTexts:
        if name not in _PREPARED:
            _PREPARED.clear()
            _PREPARED[name] = TestTexts(shared.value, window)
        return _PREPARED[name]

    return prepared


def n_hit(found: F.Column | str) -> F.Column:
    """Document words inside any match: sizes of the union of the matches' intervals."""
    col = F.col(found) if isinstance(found, str) else found
    spans = F.array_sort(F.transform(col["matches"], lambda m: F.struct(m["doc_start"].alias("s"), (m["doc_start"] + m["length"]).alias("e"))))
    zero = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).alias("to"))
    return F.aggregate(
        spans,
        zero,
        lambda a, x: F.struct((a["n"] + F.greatest(x["e"] - F.greatest(x["s"], a["to"]), F.lit(0))).cast("long").alias("n"), F.greatest(a["to"], x["e"]).alias("to")),
        lambda a: a["n"],
    )


def item_ids(found: str) -> F.Column:
    return F.sort_array(F.array_distinct(F.transform(F.col(found)["matches"], lambda m: m["item_id"])))


def decontaminated(docs: DataFrame, tests: DataFrame, window: int = WINDOW) -> DataFrame:
    """The documents without a match, with their own columns."""
    mark = "__decontamination"
    return find_matches(docs, tests, window, output=mark).where(F.size(F.col(mark)["matches"]) == 0).select(*docs.columns)


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    tests = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text")
    found = find_matches(docs, tests)
    ids = item_ids("decontamination")
    return found.select(
        "doc_id",
        F.col("decontamination.n_words").alias("n_words"),
        n_hit("decontamination").alias("n_hit"),
        F.size(ids).cast("long").alias("n_items"),
        F.sha2(F.array_join(ids, ","), 256).alias("items_sha256"),
        (F.size("decontamination.matches") > 0).alias("contaminated"),
    )


QUERIES = {"op7_decontaminate": op7_decontaminate}
ORACLES = {
    "op7_decontaminate": r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark
), bw AS (
  SELECT DISTINCT item_id, k, md5(array_to_string(w[i : i + k - 1], ' ')) AS h
  FROM (SELECT item_id, w, least(10, len(w)) AS k, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS i FROM b WHERE len(w) > 0)
), dw AS (
  SELECT doc_id, i, k, md5(array_to_string(w[i : i + k - 1], ' ')) AS h
  FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM d CROSS JOIN (SELECT DISTINCT k FROM bw) WHERE len(w) >= k)
), m AS (
  SELECT dw.doc_id, dw.i, dw.k, bw.item_id FROM dw JOIN bw USING (k, h)
), hit AS (
  SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM m) GROUP BY doc_id
), it AS (
  SELECT doc_id, count(*) AS n_items, sha256(string_agg(s, ',' ORDER BY s)) AS items_sha256
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM m) GROUP BY doc_id
)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, coalesce(hit.n_hit, 0) AS n_hit, coalesce(it.n_items, 0) AS n_items,
  coalesce(it.items_sha256, sha256('')) AS items_sha256, coalesce(hit.n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN hit USING (doc_id) LEFT JOIN it USING (doc_id)
"""
}
