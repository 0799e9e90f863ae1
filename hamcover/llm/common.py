"""What several operators of this folder share: shared storage, word splitting, Arrow batches."""

from __future__ import annotations

import contextvars
import os
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession, what: str) -> str:
    """A new folder in the store that driver and executors share.

    The cluster names it in spark.checkpoint.dir. Where that is unset, as in tests, a local
    folder is used, which is right for local masters only.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file:///tmp/checkpoints"
    if "://" not in base and not base.startswith("file:"):
        base = f"file://{os.path.abspath(base)}"
    return f"{base}/{what}-{uuid.uuid4().hex}"


#: Spark's setting for dropping the shuffle files of a statement when it ends.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def written(df: DataFrame, what: str) -> DataFrame:
    """The rows, written to the shared store and read again: later reads don't recompute them, and survive lost executors.

    The shuffle files of the steps before are of no use any more, so they go when the table is there.
    """
    spark = df.sparkSession
    path = shared_dir(spark, what)
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        if before is None:
            spark.conf.unset(_CLEANUP)
        else:
            spark.conf.set(_CLEANUP, before)
    table = spark.read.schema(df.schema).parquet(path)
    table.written_to = path
    steps = _STEPS.get()
    if steps is not None:
        steps.tables.append(table)
    return table


def discard(*tables: DataFrame) -> None:
    """Deletes tables that written() made. Only for those that no later step, or the caller's result, reads again."""
    for table in tables:
        spark = table.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(table.written_to)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


class Steps:
    """Tables written inside `with Steps() as steps` are deleted behind it, but for those in steps.keep(), which the result still reads.
    An enclosing Steps deletes these in turn."""

    def __init__(self):
        self.tables: list[DataFrame] = []
        self.kept: list[DataFrame] = []

    def keep(self, *tables: DataFrame) -> None:
        self.kept += tables

    def __enter__(self) -> Steps:
        self.outer = _STEPS.get()
        _STEPS.set(self)
        return self

    def __exit__(self, kind, *_) -> None:
        _STEPS.set(self.outer)
        paths = {t.written_to for t in self.kept}
        if kind is None:
            discard(*(t for t in self.tables if t.written_to not in paths))
        if self.outer is not None:
            self.outer.tables += self.kept


_STEPS: contextvars.ContextVar[Steps | None] = contextvars.ContextVar("steps", default=None)


#: Bytes of Latin letters and digits and of all non-ASCII characters stay, A-Z turn into a-z, all others separate words.
_FOLD = bytes(i + 32 if 65 <= i <= 90 else i if 48 <= i <= 57 or 97 <= i <= 122 or i >= 128 else 32 for i in range(256))


def folded_words(text: str | None) -> list[bytes]:
    """Lower-cased (A-Z only) runs of digits, Latin letters and non-ASCII characters, in UTF-8. Null has none."""
    return text.encode("utf-8", "surrogatepass").translate(_FOLD).split() if text else []


def plain_words(text: str | None) -> list[bytes]:
    """Runs of anything but space and the characters 9 to 13, in UTF-8. Null has none. (Those six are what bytes.split() splits at.)"""
    return text.encode("utf-8", "surrogatepass").split() if text else []


_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every input bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * _M1
    x = x ^ (x >> np.uint64(27))
    x = x * _M2
    return x ^ (x >> np.uint64(31))


_ODD = np.uint64(0x9E3779B97F4A7C15)


def gram_hashes(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of every k consecutive words, from the words' hashes."""
    n = len(h) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = h[:n].copy()
    for j in range(1, k):
        out = out * _ODD + h[j : j + n]
    return mixed(out)


_ODD_INVERSE = np.uint64(pow(int(_ODD), -1, 1 << 64))
_SPACED = np.array([not (i == 32 or 9 <= i <= 13) for i in range(256)])
_POWERS: dict[int, np.ndarray] = {}
#: Bytes that are hashed at a time; a longer word is hashed whole.
HASH_BYTES = 1 << 20


def _powers(n: int, base: np.uint64) -> np.ndarray:
    """base ** i modulo 2 ** 64."""
    have = _POWERS.get(int(base))
    if have is not None and len(have) >= n:
        return have[:n]
    have = np.full(max(n, HASH_BYTES) + 1, base, np.uint64)
    have[0] = 1
    have = np.cumprod(have)
    if n <= 2 * HASH_BYTES:
        _POWERS[int(base)] = have
    return have[:n]


def _hash_piece(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    inside = _SPACED[data].view(np.int8)
    edge = np.flatnonzero(np.diff(inside, prepend=0, append=0))
    begins, ends = edge[::2], edge[1::2]
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * _powers(len(data), _ODD), out=sums[1:])
    return begins, mixed((sums[ends] - sums[begins]) * _powers(len(data), _ODD_INVERSE)[begins] + (ends - begins).astype(np.uint64))


def hashed_words(texts: list[str | None], folded: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of all texts (plain words, or folded ones), one text behind the other, and where each text begins (and the last ends).

    A word's hash is a polynomial of its bytes modulo 2 ** 64, taken from running sums over all bytes, piece by piece.
    """
    return hashed_bytes([(t or "").encode("utf-8", "surrogatepass") for t in texts], folded)[:2]


def span_hashes(h: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
    """Hash of each run of words h[start:stop], from running sums."""
    sums = np.zeros(len(h) + 1, np.uint64)
    np.cumsum((mixed(h) | np.uint64(1)) * _powers(len(h), _ODD), out=sums[1:])
    return mixed((sums[stop] - sums[start]) * _powers(len(h) + 1, _ODD_INVERSE)[start] + (stop - start).astype(np.uint64))


def hashed_bytes(raw: list[bytes], folded: bool = False) -> tuple[np.ndarray, np.ndarray, bytes, np.ndarray]:
    """hashed_words() of texts in UTF-8; also the bytes of all texts, one space behind each, and where each word begins there."""
    whole = b" ".join(raw) + b" "
    if folded:
        whole = whole.translate(_FOLD)
    data = np.frombuffer(whole, np.uint8)
    begins, hashes, at = [np.empty(0, np.int64)], [np.empty(0, np.uint64)], 0
    while at < len(data):
        stop = min(len(data), at + HASH_BYTES)
        if stop < len(data):
            gaps = np.flatnonzero(~_SPACED[data[at:stop]])
            if len(gaps):
                stop = at + int(gaps[-1]) + 1
            else:  # a word without end in this piece
                rest = np.flatnonzero(~_SPACED[data[stop:]])
                stop = stop + int(rest[0]) + 1 if len(rest) else len(data)
        b, h = _hash_piece(data[at:stop])
        begins.append(b + at)
        hashes.append(h)
        at = stop
    first = np.cumsum([0] + [len(x) + 1 for x in raw])
    places = np.concatenate(begins)
    return np.concatenate(hashes), np.searchsorted(places, first), whole, places


def text_slices(it: Iterator[pa.RecordBatch], size: int, column: str = "text") -> Iterator[pa.RecordBatch]:
    """Slices of batches that hold about `size` bytes of a text column; a longer text is a slice of its own."""
    for batch in it:
        lengths = pc.binary_length(batch.column(batch.schema.get_field_index(column))).to_numpy(zero_copy_only=False)
        ends = np.cumsum(np.nan_to_num(lengths).astype(np.int64))
        at = 0
        while at < batch.num_rows:
            stop = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + size, "right")))
            yield batch.slice(at, stop - at)
            at = stop


def crc_bucket(column: str, n: int):
    """crc32 of the column as text, modulo n; null where the column is null."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % n


#: sha256 of no bytes at all, in lower-case hex: a fixed value.
SHA256_OF_NOTHING = "e3b0c44298fc1c149afbf4c8996fb92427ae41e4649b934ca495991b7852b855"
