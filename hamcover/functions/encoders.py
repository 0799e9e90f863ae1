"""From rows of tables to binary codes. All draws come from md5 and all sums are of integers, so other engines get the same bits."""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hamcover.functions.bits import pack_bits, words_of
from hamcover.plans import draws
from hamcover.sources.shared import written

TOKEN = r"[\p{L}\p{N}]+"
QUANTUM = 1 << 20


def hex_word(digits: Column) -> Column:
    """16 hex digits as a signed 64-bit word."""
    return F.conv(digits, 16, -10).cast("bigint")


def uniform_code(key: Column | str, d: int) -> Column:
    """A code drawn from the key: two words of one digest for 128 bits, else a digest for each word."""
    k = (F.col(key) if isinstance(key, str) else key).cast("string")
    if d == 128:
        h = F.md5(F.concat(F.lit("u:"), k))
        return F.array(hex_word(F.substring(h, 1, 16)), hex_word(F.substring(h, 17, 16)))
    words = []
    for j in range(words_of(d)):
        w = hex_word(F.substring(F.md5(F.concat(F.lit(f"u:{j}:"), k)), 1, 16))
        left = d - 64 * j
        words.append(w if left >= 64 else w.bitwiseAND(F.lit((1 << left) - 1).cast("bigint")))
    return F.array(*words)


def md5_number(key: Column) -> Column:
    """The first 15 hex digits of the key's md5 as an integer."""
    return F.conv(F.substring(F.md5(key), 1, 15), 16, 10).cast("bigint")


def hold_out(points: DataFrame, k: int, seed: int = draws.SEED) -> tuple[DataFrame, DataFrame]:
    """The k ids least by md5 become queries (qid, then the other columns) and leave the points. k is a small number, so queries are broadcast."""
    order = F.md5(F.concat(F.lit(f"{seed}:q:"), F.col("id").cast("string")))
    chosen = points.orderBy(order, "id").limit(k)
    queries = chosen.withColumnRenamed("id", "qid")
    return points.join(F.broadcast(chosen.select("id")), "id", "left_anti"), queries


def plant(queries: DataFrame, radii: list[int], copies: int, d: int, seed: int = draws.SEED, first_id: int = 10**9) -> DataFrame:
    """For each query, copies with exactly as many bits flipped as each radius: the positions of least md5. Returns id, code, qid, distance."""
    words = words_of(d)
    at = queries.select("qid", "code", F.explode(F.array(*map(F.lit, radii))).alias("distance")).withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    key = lambda i: F.md5(F.concat_ws(":", F.lit(str(seed)), F.lit("p"), F.col("qid").cast("string"), F.col("copy").cast("string"), i.cast("string")))
    ranked = F.array_sort(F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.struct(key(i).alias("h"), i.alias("i"))))
    flips = F.transform(F.slice(ranked, 1, F.greatest(F.col("distance"), F.lit(1))), lambda x: x["i"])
    flips = F.when(F.col("distance") > 0, flips).otherwise(F.array().cast("array<int>"))
    at = at.withColumn("flips", flips)
    one = F.lit(1).cast("bigint")

    def flipped(w: int) -> Column:
        own = F.filter("flips", lambda x: F.floor(x / 64) == w)
        return F.aggregate(own, F.col("code")[w], lambda acc, x: acc.bitwiseXOR(F.call_function("shiftleft", one, F.pmod(x, F.lit(64)).cast("int"))))

    new = [flipped(w) for w in range(words)]
    number = F.row_number().over(Window.orderBy("qid", "distance", "copy")) - 1 + first_id
    return at.select(number.cast("bigint").alias("id"), F.array(*new).alias("code"), "qid", "distance")


def plant_sets(queries: DataFrame, radii: list[int], copies: int, d: int, seed: int = draws.SEED, first_id: int = 10**9) -> DataFrame:
    """As `plant`, for sparse points: as many positions as each radius, drawn by md5, are put in or taken out. Returns id, ones, qid, distance."""
    at = queries.select("qid", "ones", F.explode(F.array(*map(F.lit, radii))).alias("distance")).withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    key = lambda i: F.concat_ws(":", F.lit(str(seed)), F.lit("p"), F.col("qid").cast("string"), F.col("copy").cast("string"), i.cast("string"))
    drawn = F.array_distinct(F.transform(F.sequence(F.lit(0), 4 * F.col("distance") + 8), lambda i: (md5_number(key(i)) % d).cast("int")))
    flips = F.slice(drawn, 1, F.greatest(F.col("distance"), F.lit(1)))
    at = at.withColumn("flips", F.when(F.col("distance") > 0, flips).otherwise(F.array().cast("array<int>")))
    ones = F.sort_array(F.concat(F.array_except("ones", "flips"), F.array_except("flips", "ones")))
    number = F.row_number().over(Window.orderBy("qid", "distance", "copy")) - 1 + first_id
    return at.select(number.cast("bigint").alias("id"), ones.alias("ones"), "qid", "distance")


def sign_code(vector: Column | str, d: int) -> Column:
    """Bit i tells whether coordinate i is above zero."""
    v = F.col(vector) if isinstance(vector, str) else vector
    return pack_bits(F.transform(v, lambda x: (x > 0).cast("int")), d)


def sign_projection(points: DataFrame, vector: str, bits: int, seed: int = draws.SEED) -> DataFrame:
    """id and code: signs of integer dot products with planes of +1 and -1. `points` has id and the vector."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        planes = None
        for batch in it:
            if not batch.num_rows:
                continue
            flat = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64)
            x = np.rint(flat * QUANTUM).astype(np.int64).reshape(batch.num_rows, -1)
            if planes is None:
                planes = np.array([[1 - 2 * (draws.number(f"{seed}:h:{j}:{i}") & 1) for j in range(bits)] for i in range(x.shape[1])], np.int64)
            yield _codes(batch.column(0), x @ planes > 0)

    return points.select("id", vector).mapInArrow(run, "id bigint, code array<bigint>")


def _codes(ids: pa.Array, bits: np.ndarray) -> pa.RecordBatch:
    """Rows of booleans as codes."""
    n, d = bits.shape
    words = words_of(d)
    packed = np.zeros((n, words * 8), np.uint8)
    data = np.packbits(bits, axis=1, bitorder="little")
    packed[:, : data.shape[1]] = data
    flat = packed.view(np.int64).ravel()
    return pa.RecordBatch.from_arrays([ids.cast(pa.int64()), pa.ListArray.from_arrays(np.arange(0, n * words + 1, words, dtype=np.int32), flat)], names=["id", "code"])


def text_fingerprint(points: DataFrame, text: str, bits: int) -> DataFrame:
    """id and code of `points` (id and a text): signs of the sums of the tokens' md5 bits, counted as +1 and -1 for each occurrence.

    A map over whole texts: nothing is shuffled. A task remembers the bits of tokens, up to a bound.
    """
    words = words_of(bits)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        token, known = regex.compile(TOKEN), {}

        def digest(word: str) -> bytes:
            keys = [word] if words == 1 else [f"{j}:{word}" for j in range(words)]
            return b"".join(hashlib.md5(k.encode("utf-8", "surrogatepass")).digest()[:8][::-1] for k in keys)

        for whole in it:
            for at in range(0, whole.num_rows, 512):
                batch = whole.slice(at, 512)
                sums = np.zeros((batch.num_rows, words * 64), np.int64)
                for row, value in enumerate(batch.column(1).to_pylist()):
                    counts = Counter(token.findall((value or "").lower()))
                    if len(known) > 200_000:
                        known.clear()
                    items = list(counts.items())
                    for i in range(0, len(items), 4096):
                        part = items[i : i + 4096]
                        data = b"".join(known.get(w) or known.setdefault(w, digest(w)) for w, _ in part)
                        signs = np.unpackbits(np.frombuffer(data, np.uint8).reshape(len(part), -1), axis=1, bitorder="little").astype(np.float64)
                        n = np.array([c for _, c in part], np.float64)
                        sums[row] += (2 * (n @ signs) - n.sum()).astype(np.int64)
                yield _codes(batch.column(0), sums[:, :bits] > 0)

    return points.select("id", text).mapInArrow(run, "id bigint, code array<bigint>")


def tokens(text: Column | str) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(TOKEN), 0)


#: Frequent words of the languages of the given texts, without meaning of their own: fixed values.
STOP_WORDS = (
    "a", "an", "and", "as", "at", "be", "by", "for", "from", "in", "is", "it", "of", "on", "or", "that", "the", "this", "to", "was", "with",
    "au", "de", "des", "du", "en", "est", "et", "il", "la", "le", "les", "pour", "que", "un", "une",
    "das", "den", "der", "die", "ein", "eine", "ist", "mit", "und", "von", "zu",
    "con", "del", "el", "los", "para", "por", "se", "y",
)


def vocabulary(docs: DataFrame, text: str = "text", min_freq: int = 10, stop_words: Iterable[str] = ()) -> DataFrame:
    """pos, word: words that occur more than min_freq times in all, but for stop words, numbered in their order.

    The words are dealt to ranges and numbered there; a range begins where those before it end. Only a row for each range meets in one task."""
    return _numbered(docs.select(tokens(F.col(text)).alias("words")), min_freq, stop_words)


def _numbered(docs: DataFrame, min_freq: int, stop_words: Iterable[str]) -> DataFrame:
    words = docs.select(F.explode("words").alias("word"))
    if stop_words:
        words = words.where(~F.col("word").isin(list(stop_words)))
    counts = words.groupBy("word").count().where(F.col("count") > min_freq).select("word")
    ranged = written(counts.repartitionByRange("word").withColumn("range", F.spark_partition_id()), "vocabulary")
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    begins = ranged.groupBy("range").agg(F.count("*").alias("n")).select("range", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("begin"))
    place = F.row_number().over(Window.partitionBy("range").orderBy("word")) - 1
    return ranged.withColumn("place", place).join(F.broadcast(begins), "range").select((F.col("begin") + F.col("place")).cast("int").alias("pos"), "word")


def word_sets(docs: DataFrame, min_freq: int = 10, stop_words: Iterable[str] = ()) -> DataFrame:
    """id, ones: the vocabulary positions of a document's words, sorted, without repetition. `docs` has id and text."""
    return sized_word_sets(docs, min_freq, stop_words)[0]


def sized_word_sets(docs: DataFrame, min_freq: int = 10, stop_words: Iterable[str] = ()) -> tuple[DataFrame, DataFrame]:
    """`word_sets` and the vocabulary. Texts are cut into words once."""
    cut = written(docs.select("id", tokens(F.col("text")).alias("words")), "words")
    known = written(_numbered(cut, min_freq, stop_words), "numbered")
    own = cut.select("id", F.explode(F.array_distinct("words")).alias("word"))
    # A word is there once for each document, and has one position.
    return own.join(known, "word").groupBy("id").agg(F.sort_array(F.collect_list("pos")).alias("ones")), known


def rating_sets(ratings: DataFrame, threshold: float = 2.5) -> DataFrame:
    """id, ones: items that a user rated with the threshold or more. `ratings` has user, item (a number) and score."""
    liked = ratings.where(F.col("score") >= threshold)
    return liked.groupBy(F.col("user").alias("id")).agg(F.sort_array(F.collect_set(F.col("item").cast("int"))).alias("ones"))


def unary_code(columns: list[Column | str], upper: int) -> Column:
    """Integers from 0 to upper, one behind the other in unary: Hamming distance is the sum of absolute differences."""
    cols = [F.col(c) if isinstance(c, str) else c for c in columns]

    def unary(c: Column) -> Column:
        return F.transform(F.sequence(F.lit(1), F.lit(upper)), lambda i: (i <= c).cast("int"))

    bits = F.concat(*map(unary, cols))
    return pack_bits(bits, upper * len(cols))


def strip_html(html: Column | str) -> Column:
    """Text between tags, without scripts, styles, comments and entities."""
    h = F.col(html) if isinstance(html, str) else html
    for pattern in (r"(?is)<(script|style)\b.*?</\1\s*>", r"(?s)<!--.*?-->", r"(?s)<[^>]*>", r"&#?[A-Za-z0-9]+;"):
        h = F.regexp_replace(h, pattern, " ")
    return F.trim(F.regexp_replace(h, r"\s+", " "))
