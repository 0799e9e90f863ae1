"""Quality by nearest-neighbour voting in a latent-semantic space.

A text's features are hashed byte trigrams and hashed four-grams of character classes, with log counts, weighted by how
few of the labelled texts have them. A truncated singular value decomposition of the labelled texts' features gives the
latent space. The labelled vectors (at most `SAMPLE_DOCS`, expected, drawn by a hash of id and text) are broadcast; the
cosines of every document with all of them are computed exactly, in blocks, and the labels of the `NEIGHBOURS` nearest
vote, weighted by a power of their cosine. Prediction reads whole texts and is a map: nothing is shuffled.

Defined results: null and empty texts, which have no vector, score the mean label of the sample; rows with a null or
other label than 0 and 1 teach nothing; cosines are compared to seven digits, and ties go to the labelled row that is first by doc_id, then by
checksum of its text, then by label; with no labels all score 0.5; repeated rows are each scored, and a document labelled twice votes twice; an empty
table gives no rows. The labelled rows are brought into that order before the decomposition, so scores don't hang on partitions.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.llm.batchwise import with_struct
from hamcover.llm.common import crc_bucket

SAMPLE_DOCS = 3_000
GRAM_BUCKETS, CLASS_BUCKETS = 2048, 1024
LATENT = 48
NEIGHBOURS = 25
POWER = 4
THRESHOLD = 0.3
#: Bytes of a text that are hashed at a time; the counts add up to those of the whole text.
CHUNK = 1 << 20

#: Character classes by byte: letters small and large, digits, spaces, non-ASCII; other marks stand for themselves.
_CLASSES = np.array([97 if 97 <= i <= 122 else 65 if 65 <= i <= 90 else 48 if 48 <= i <= 57 else 128 if i >= 128 else i for i in range(256)], np.uint32)


def _counts(codes: np.ndarray, n: int, buckets: int) -> np.ndarray:
    if len(codes) < n:
        return np.zeros(buckets)
    h = codes[: len(codes) - n + 1].copy()
    for j in range(1, n):
        h *= np.uint32(0x01000193)
        h ^= codes[j : len(codes) - n + 1 + j]
    h *= np.uint32(0x9E3779B1)
    return np.bincount(h >> np.uint32(32 - buckets.bit_length() + 1), minlength=buckets)


def features(text: str | None) -> np.ndarray:
    """Log counts of a whole text, chunks overlapping by what an n-gram needs."""
    raw = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
    total = np.zeros(GRAM_BUCKETS + CLASS_BUCKETS)
    for at in range(0, max(1, len(raw)), CHUNK):
        part = raw[at : at + CHUNK + 3]
        last = at + CHUNK >= len(raw)
        total[:GRAM_BUCKETS] += _counts(part[: len(part) if last else CHUNK + 2].astype(np.uint32), 3, GRAM_BUCKETS)
        total[GRAM_BUCKETS:] += _counts(_CLASSES[part], 4, CLASS_BUCKETS)
    return np.log1p(total).astype(np.float32)


def _unit(rows: np.ndarray) -> np.ndarray:
    size = np.linalg.norm(rows, axis=1, keepdims=True)
    return rows / np.where(size > 0, size, 1)


class Voter:
    def __init__(self, rows: np.ndarray, labels: np.ndarray, latent: int = LATENT, seed: int = 7):
        self.prior = float(labels.mean()) if len(labels) else 0.5
        self.labels = labels.astype(np.float32)
        width = GRAM_BUCKETS + CLASS_BUCKETS
        rows = rows.reshape(-1, width)
        self.weight = np.log((1 + len(rows)) / (1 + (rows > 0).sum(axis=0))).astype(np.float32) + 0.1
        a = _unit(rows * self.weight)
        k = min(latent, *a.shape) if len(rows) else 1
        # Randomised subspace iteration for the leading right singular vectors.
        basis = np.random.default_rng(seed).standard_normal((width, k + 8)).astype(np.float32)
        for _ in range(3):
            basis = np.linalg.qr(a.T @ (a @ basis))[0] if len(rows) else np.linalg.qr(basis)[0]
        _, _, vt = np.linalg.svd(a @ basis, full_matrices=False) if len(rows) else (None, None, np.eye(k + 8, dtype=np.float32))
        self.project = (basis @ vt[:k].T).astype(np.float32)
        self.vectors = _unit(a @ self.project).astype(np.float32)

    def scores(self, texts: list[str | None]) -> np.ndarray:
        if not len(self.labels):
            return np.full(len(texts), 0.5)
        rows = np.array([features(t) for t in texts])
        latent = (rows * self.weight).astype(np.float64) @ self.project.astype(np.float64)
        known = np.linalg.norm(latent, axis=1) > 0
        cosines = np.rint(_unit(latent) @ self.vectors.T.astype(np.float64) * 1e7).astype(np.int64)
        k, n = min(NEIGHBOURS, len(self.labels)), len(self.labels)
        # No two keys are equal: of equal cosines the first row has the least.
        near = np.sort(np.partition(np.arange(n) - cosines * n, k - 1, axis=1)[:, :k], axis=1) % n
        weight = np.maximum(np.take_along_axis(cosines, near, 1) / 1e7, 0) ** POWER
        vote = (weight * self.labels[near]).sum(axis=1) + 1e-3 * self.prior
        return np.where(known, vote / (weight.sum(axis=1) + 1e-3), self.prior)


def _featurise(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in it:
        for i in range(0, batch.num_rows, 256):
            part = batch.slice(i, 256)
            rows = [features(t).astype(np.float16).tobytes() for t in part.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(rows, pa.binary()), *part.columns[1:]], names=["row", "label", "doc_id", "checksum"])


def fit(labelled: DataFrame, sample_docs: int = SAMPLE_DOCS) -> Voter:
    """labelled: doc_id, text, label (0 or 1). Uses `sample_docs` rows at most, but for the deviation of a hash draw."""
    labelled = labelled.where("label in (0, 1) and text is not null").select(F.col("doc_id").cast("bigint").alias("doc_id"), "text", F.col("label").cast("int").alias("label"))
    n = labelled.count()
    if n > sample_docs:
        labelled = labelled.where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 30)) < int((1 << 30) * sample_docs / n))
    # Text, label and what orders the rows; at most `sample_docs` of them come to the driver.
    table = labelled.select("text", "label", "doc_id", F.xxhash64("text").alias("checksum")).mapInArrow(_featurise, "row binary, label int, doc_id bigint, checksum bigint").toArrow()
    table = table.sort_by([(name, "ascending") for name in ("doc_id", "checksum", "label")])
    rows = np.frombuffer(b"".join(table["row"].to_pylist()), np.float16).astype(np.float32)
    return Voter(rows, np.array(table["label"].to_pylist(), np.float32))


def score_quality(docs: DataFrame, voter: Voter, text: str = "text", output: str = "quality") -> DataFrame:
    """All columns of docs and a struct: score, predicted."""
    shared = docs.sparkSession.sparkContext.broadcast(voter)

    def make():
        model = shared.value
        return lambda texts: [(float(x), int(x >= THRESHOLD)) for x in model.scores(texts)]

    return with_struct(docs, text, output, "struct<score:double,predicted:int>", make)


def op6_quality_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", F.col("quality").alias("label"))
    learn = crc_bucket("doc_id", 5) != 0
    voter = fit(docs.where(learn).join(labels.where(learn), "doc_id"))
    found = score_quality(docs, voter)
    return found.select("doc_id", F.coalesce(crc_bucket("doc_id", 5) == 0, F.lit(False)).alias("held_out"), F.col("quality.score"), F.col("quality.predicted"))


QUERIES = {"op6_quality_knn": op6_quality_knn}
ORACLES: dict[str, str] = {}
