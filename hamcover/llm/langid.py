"""Language identification: known words first, then ever shorter character n-grams.

A word that the model knows scores by its log frequency in each language. A word it doesn't know
scores by the longest order of character n-grams, from five down to one, of which it has any that the model knows.
A text's score for a language is the sum over its words, and the reported score the softmax of those sums.

The model is fitted on a sample of labelled rows of bounded size: `SAMPLE_DOCS` rows of each language, expected, drawn by a hash of
id and text, all rows of a language that has fewer. Of each language's words the `VOCABULARY` most frequent are kept (ties by word), with all their n-grams. So
what is broadcast is bounded by the number of languages, and no language loses words, or its place, to another.
Words and n-grams are known by 64-bit hashes; a batch of texts is scored by searches in sorted arrays. Prediction reads whole texts and is a map: nothing is shuffled.

Defined results: `und` with score 0 for a text that is null or has no letter; ties go to the language first by
name; rows without a language teach nothing; with nothing to learn from, all is `und`; repeated rows are each told, and each teaches.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hamcover.llm.batchwise import with_struct
from hamcover.llm.common import crc_bucket, hashed_bytes, mixed

SAMPLE_DOCS = 5_000
VOCABULARY = 30_000
ORDERS = (5, 4, 3, 2, 1)
SMOOTH = 0.5
#: Unknown words that are backed off together.
TOGETHER = 20_000

#: Latin letters and all non-ASCII characters make up words.
_LETTERS = bytes(i if 97 <= i <= 122 or i >= 128 else 32 for i in range(256))
_STEP = np.uint64(0x9E3779B97F4A7C15)


def _letters(text: str | None) -> bytes:
    """The lower-cased text with all but letters blank; nothing if no character is a letter."""
    if not text:
        return b""
    raw = text.lower().encode("utf-8", "surrogatepass").translate(_LETTERS)
    if raw.isascii() or any(map(str.isalpha, text)):
        return raw
    return b""


def words_of(text: str | None) -> list[bytes]:
    """Lower-cased words; none if no character is a letter."""
    return _letters(text).split()


def gram_hashes_of(words: list[bytes], order: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words' character n-grams, and the word each is of. Orders above one see a mark before and behind the word."""
    edge = ("^", "$") if order > 1 else ("", "")
    marked = [f"{edge[0]}{w.decode('utf-8', 'replace')}{edge[1]}" for w in words]
    sizes = np.fromiter(map(len, marked), np.int64, len(marked))
    chars = np.frombuffer("".join(marked).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    counts = np.maximum(sizes - order + 1, 0)
    word = np.repeat(np.arange(len(words)), counts)
    at = np.repeat(np.cumsum(sizes) - sizes, counts) + np.arange(len(word)) - np.repeat(np.cumsum(counts) - counts, counts)
    h = np.full(len(at), np.uint64(order))
    for j in range(order):
        h = h * _STEP + chars[at + j] + np.uint64(1)
    return mixed(h), word


class Table:
    """Log frequencies of hashed words or n-grams in each language."""

    def __init__(self, hashes: np.ndarray, langs: np.ndarray, counts: np.ndarray, n_langs: int):
        self.hashes, back = np.unique(hashes, return_inverse=True)
        rows = np.zeros((len(self.hashes), n_langs))
        np.add.at(rows, (back, langs), counts)
        self.logs = np.log((rows + SMOOTH) / (rows.sum(axis=0) + SMOOTH * max(1, len(rows)))).astype(np.float32)

    def find(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rows of the hashes, and which are known."""
        if not len(self.hashes):
            return np.zeros(len(hashes), np.int64), np.zeros(len(hashes), bool)
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        return at, self.hashes[at] == hashes


class Model:
    def __init__(self, counts: list[tuple[str, bytes, int]]):
        """counts: (language, word, occurrences), no word twice in a language."""
        self.languages = sorted({lang for lang, _, _ in counts})
        place = {lang: i for i, lang in enumerate(self.languages)}
        langs = np.array([place[lang] for lang, _, _ in counts], np.int64)
        words, n = [w for _, w, _ in counts], np.array([c for _, _, c in counts], np.float64)
        self.words = Table(hashed_bytes(words)[0], langs, n, len(place))
        self.grams = []
        for order in ORDERS:
            h, word = gram_hashes_of(words, order)
            self.grams.append(Table(h, langs[word], n[word], len(place)))

    def _unknown(self, words: list[bytes]) -> np.ndarray:
        """Scores of words the model doesn't know: means over the known n-grams of the longest order that has any."""
        out, live = np.zeros((len(words), len(self.languages))), np.arange(len(words))
        for order, table in zip(ORDERS, self.grams, strict=True):
            if not len(live):
                break
            h, word = gram_hashes_of([words[i] for i in live.tolist()], order)
            at, known = table.find(h)
            at, word = at[known], word[known]
            hits = np.bincount(word, minlength=len(live))
            sums = np.stack([np.bincount(word, table.logs[at, k], len(live)) for k in range(len(self.languages))], axis=1)
            some = hits > 0
            out[live[some]] = sums[some] / hits[some, None]
            live = live[~some]
        return out

    def predict(self, texts: list[str | None]) -> list[tuple[str, float]]:
        h, bounds, data, begins = hashed_bytes([_letters(t) for t in texts])
        if not len(h) or not self.languages:
            return [("und", 0.0)] * len(texts)
        distinct, first, back = np.unique(h, return_index=True, return_inverse=True)
        at, known = self.words.find(distinct)
        scores = np.zeros((len(distinct), len(self.languages)))
        scores[known] = self.words.logs[at[known]]
        ends = np.append(begins[1:], len(data))
        rest = np.flatnonzero(~known)
        for i in range(0, len(rest), TOGETHER):
            part = rest[i : i + TOGETHER]
            words = [data[a:b].rstrip() for a, b in zip(begins[first[part]].tolist(), ends[first[part]].tolist(), strict=True)]
            scores[part] = self._unknown(words)
        text = np.repeat(np.arange(len(texts)), np.diff(bounds))
        total = np.stack([np.bincount(text, scores[:, k][back], len(texts)) for k in range(len(self.languages))], axis=1)
        best = total.argmax(axis=1)
        share = 1 / np.exp(total - total[np.arange(len(texts)), best][:, None]).sum(axis=1)
        return [(self.languages[b], float(s)) if n else ("und", 0.0) for b, s, n in zip(best.tolist(), share, np.diff(bounds).tolist(), strict=True)]


def _count_words(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in it:
        counts: Counter = Counter()
        for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            counts.update((lang, w) for w in words_of(text))
        if counts:
            langs, words = zip(*counts, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(langs, pa.string()), pa.array(words, pa.binary()), pa.array(list(counts.values()), pa.int64())], names=["lang", "word", "n"])


def word_counts(labelled: DataFrame, sample_docs: int = SAMPLE_DOCS, vocabulary: int = VOCABULARY) -> DataFrame:
    """lang, word, n of a sample of labelled (doc_id, text, lang): the words that a model keeps."""
    labelled = labelled.where("lang is not null and text is not null").select("doc_id", "text", "lang")
    sizes = labelled.groupBy("lang").agg(F.count("*").alias("of"))
    drawn = F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    # A row for each language, of which the model has up to `vocabulary`: smaller than what is broadcast anyway.
    sample = labelled.join(F.broadcast(sizes), "lang").where(drawn * F.col("of") < sample_docs)
    counts = sample.select("lang", "text").mapInArrow(_count_words, "lang string, word binary, n bigint").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    best = Window.partitionBy("lang").orderBy(F.desc("n"), "word")
    return counts.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= vocabulary).select("lang", "word", "n")


def fit(labelled: DataFrame, sample_docs: int = SAMPLE_DOCS, vocabulary: int = VOCABULARY) -> Model:
    """labelled: doc_id, text, lang. Uses `sample_docs` rows of a language at most, but for the deviation of a hash draw."""
    table = word_counts(labelled, sample_docs, vocabulary).toArrow()
    return Model(list(zip(*(table[c].to_pylist() for c in ("lang", "word", "n")), strict=True)))


def identify(docs: DataFrame, model: Model, text: str = "text", output: str = "language") -> DataFrame:
    """All columns of docs and a struct: lang_pred and score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        model = shared.value
        return model.predict

    return with_struct(docs, text, output, "struct<lang_pred:string,score:double>", make)


def learnable(docs: DataFrame) -> DataFrame:
    """Rows from which the contract lets a model learn."""
    return docs.where(crc_bucket("doc_id", 3) != 1)


def identified(docs: DataFrame) -> DataFrame:
    """Documents whose language can be told, with their own columns."""
    mark = "__language"
    return identify(docs, fit(learnable(docs)), output=mark).where(F.col(mark)["lang_pred"] != "und").select(*docs.columns)


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    found = identify(docs.select("doc_id", "text"), fit(learnable(docs)))
    return found.select("doc_id", F.coalesce(crc_bucket("doc_id", 3) == 1, F.lit(False)).alias("held_out"), F.col("language.lang_pred"), F.col("language.score"))


QUERIES = {"op2_language_id": op2_language_id}
ORACLES: dict[str, str] = {}
