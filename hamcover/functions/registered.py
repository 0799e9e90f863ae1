"""Functions for SQL and for grouped use: pandas and Arrow batches, never row by row."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, LongType

from hamcover.operators import hashers
from hamcover.plans.hadamard import fwht
from hamcover.plans.params import CoverPlan


def _stacked(a: pd.Series) -> np.ndarray:
    return np.stack(a.to_numpy()).astype(np.int64)


@F.pandas_udf(IntegerType())
def hamming_pd(a: pd.Series, b: pd.Series) -> pd.Series:
    """Distance of codes."""
    if not len(a):
        return pd.Series([], dtype="int32")
    return pd.Series(np.bitwise_count((_stacked(a) ^ _stacked(b)).view(np.uint64)).sum(axis=1).astype("int32"))


@F.pandas_udf(IntegerType())
def hamming_sets_pd(a: pd.Series, b: pd.Series) -> pd.Series:
    """Distance of sparse points."""
    return pd.Series([len(x) + len(y) - 2 * len(np.intersect1d(x, y, assume_unique=True)) for x, y in zip(a, b, strict=True)], dtype="int32")


@F.pandas_udf(IntegerType())
def popcount_pd(a: pd.Series) -> pd.Series:
    return pd.Series(np.bitwise_count(_stacked(a).view(np.uint64)).sum(axis=1).astype("int32")) if len(a) else pd.Series([], dtype="int32")


@F.pandas_udf(ArrayType(LongType()))
def fwht_pd(a: pd.Series) -> pd.Series:
    """Transforms of arrays of one length, a power of two."""
    return pd.Series(list(fwht(_stacked(a).T.copy()).T)) if len(a) else pd.Series([], dtype=object)


@F.pandas_udf(ArrayType(LongType()))
def cover_keys_pd(codes: pd.Series, plans: pd.Series) -> pd.Series:
    """All keys of the first part of a plan, given as JSON."""
    out: list = [None] * len(codes)
    for text in plans.unique():
        plan = CoverPlan.from_json(text)
        rows = np.flatnonzero((plans == text).to_numpy() & codes.notna().to_numpy())
        if len(rows):
            column = pa.array([codes.iloc[i] for i in rows], pa.list_(pa.int64()))
            for i, keys in zip(rows, next(iter(hashers.transform_kernel(plan)(column)))[1].T, strict=True):
                out[i] = keys
    return pd.Series(out)


@F.pandas_udf(ArrayType(LongType()))
def majority_code(codes: pd.Series) -> list:
    """Bitwise majority of a group that fits in memory; a tie is 0. For groups of any size use 64 sums instead."""
    x = _stacked(codes)
    bits = np.unpackbits(np.ascontiguousarray(x).view(np.uint8), axis=1, bitorder="little")
    return np.packbits(2 * bits.sum(axis=0) > len(x), bitorder="little").view(np.int64).tolist()


class BallMasks:
    """Rows of all masks of a width with at most so many ones."""

    def eval(self, width: int, radius: int) -> Iterator[tuple[int]]:
        for m in hashers.flip_masks(width, radius):
            yield (m,)


def register(spark: SparkSession) -> None:
    """hc_hamming, hc_popcount, hc_cover_keys(code, plan) and the table function hc_ball_masks(width, radius)."""
    spark.udf.register("hc_hamming", hamming_pd)
    spark.udf.register("hc_hamming_sets", hamming_sets_pd)
    spark.udf.register("hc_popcount", popcount_pd)
    spark.udf.register("hc_fwht", fwht_pd)
    spark.udf.register("hc_cover_keys", cover_keys_pd)
    spark.udtf.register("hc_ball_masks", F.udtf(BallMasks, returnType="mask bigint"))
