"""From points to buckets: (id, part, v, bucket), one row for each table.

Points are dense (id, code) or sparse (id, ones). The kernels are maps over Arrow batches; labels and seeds
are drawn again where they are needed, from the plan, so nothing else has to be sent.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import replace
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.functions.bits import split, words_of
from hamcover.plans import draws
from hamcover.plans.hadamard import fwht, mask_bits
from hamcover.plans.params import P61, CoverPlan, SamplePlan, SubstringPlan, ball_size

HASHED = "id bigint, part int, v int, bucket bigint"
#: Bytes of one kernel's largest array.
KERNEL_BYTES = 1 << 26
#: Bytes of masks that are broadcast at most: those of tables, substrings or balls, whose number the plan sets and not the data.
MASK_BYTES = 64 << 20


@lru_cache(maxsize=32)
def columns(plan: CoverPlan, part: int, key: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Positions, labels and seeds of a part's columns."""
    return tuple(np.array(x, np.int64) for x in plan.columns(part, key))


def unpacked(codes: pa.Array, d: int) -> np.ndarray:
    """Codes as rows of zeros and ones."""
    words = codes.flatten().to_numpy(zero_copy_only=False)
    rows = np.ascontiguousarray(words, np.int64).view(np.uint8).reshape(len(codes), -1)
    return np.unpackbits(rows, axis=1, bitorder="little", count=d)


def _reduced(x: np.ndarray) -> np.ndarray:
    """Non-negative values modulo 2 ** 61 - 1."""
    x = (x & P61) + (x >> 61)
    return x - P61 * (x >= P61)


def _sums_by_label(weights: np.ndarray, cell: np.ndarray, n: int, prime: int) -> np.ndarray:
    """Sums of weights by cell, exact; modulo the prime where they would not fit. Halves of weights are summed as doubles, exact below 2 ** 53."""
    if prime < 1 << 32:
        return np.bincount(cell, weights, n).astype(np.int64)
    low = np.bincount(cell, weights & ((1 << 31) - 1), n).astype(np.int64)
    high = np.bincount(cell, weights >> 31, n).astype(np.int64)
    high = _reduced(high)
    high = ((high << 31) & P61) | (high >> 30)  # times 2 ** 31
    return _reduced(high + low)


def transform_hash(sketch: np.ndarray, prime: int) -> np.ndarray:
    """Bucket keys of all tables from sketches, labels along the first axis: half of what the whole sum exceeds the transform by.

    The same integers as summing the seeds that each mask keeps; row v - 1 is table v.
    """
    if prime < 1 << 32:
        whole = sketch.sum(axis=0)
        keys = fwht(sketch)[1:]
        np.subtract(whole, keys, out=keys)
        keys >>= 1
        keys %= prime
        return keys
    moved = fwht(sketch, prime)
    keys = moved[0] - moved[1:]
    keys += prime * (keys < 0)
    keys += prime * (keys & 1)
    keys >>= 1
    return keys - prime * (keys >= prime)


def _dense_sketch(bits: np.ndarray, plan: CoverPlan, part: int, key: int = 0) -> np.ndarray:
    where, labels, seeds = columns(plan, part, key)
    order = np.argsort(labels, kind="stable")
    used, starts = np.unique(labels[order], return_index=True)
    size = 1 << plan.bits(part)
    sketch = np.zeros((size, len(bits)), np.int64)
    by_column = np.ascontiguousarray(bits.T)
    if plan.prime < 1 << 32:
        if len(used) == len(labels):
            np.multiply(by_column[where[order]], seeds[order][:, None], out=(out := np.empty((len(order), len(bits)), np.int64)), casting="unsafe")
            sketch[used] = out
        else:
            sketch[used] = np.add.reduceat(by_column[where[order]] * seeds[order][:, None], starts, axis=0)
        return sketch
    low, high = seeds & ((1 << 31) - 1), seeds >> 31
    ones = by_column[where[order]].astype(np.int64)
    low = np.add.reduceat(ones * low[order][:, None], starts, axis=0)
    high = _reduced(np.add.reduceat(ones * high[order][:, None], starts, axis=0))
    sketch[used] = _reduced((((high << 31) & P61) | (high >> 30)) + low)
    return sketch


def _sparse_sketch(ones: pa.Array, plan: CoverPlan, part: int, key: int = 0) -> np.ndarray:
    """Only the positions that are set are visited."""
    where, labels, seeds = columns(plan, part, key)
    n, size = len(ones), 1 << plan.bits(part)
    sizes = np.diff(ones.offsets.to_numpy())
    at = ones.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    row = np.repeat(np.arange(n), sizes)
    total = np.zeros(size * n, np.int64)
    own = len(where) // plan.copies
    for copy in range(plan.copies):
        place = np.full(plan.d, -1, np.int64)
        place[where[:own]] = np.arange(copy * own, (copy + 1) * own)
        column = place[at]
        mine = column >= 0
        add = _sums_by_label(seeds[column[mine]], labels[column[mine]] * n + row[mine], size * n, plan.prime)
        total = total + add if plan.prime < 1 << 32 else _reduced(total + add)
    return total.reshape(size, n)


def _rows(ids: np.ndarray, part: int, keys: np.ndarray, extra: dict[str, pa.Array] | None = None, check: list[np.ndarray] | None = None) -> pa.RecordBatch:
    """keys: a row for each table, a column for each point; check: nothing, or second keys alike."""
    tables, n = keys.shape
    arrays = [pa.array(np.tile(ids, tables)), pa.array(np.full(tables * n, part, np.int32)), pa.array(np.repeat(np.arange(1, tables + 1, dtype=np.int32), n)), pa.array(keys.ravel())]
    names = ["id", "part", "v", "bucket"]
    for second in check or []:
        arrays.append(pa.array(second.ravel()))
        names.append("check")
    for name, values in (extra or {}).items():
        arrays.append(values.take(pa.array(np.tile(np.arange(n), tables))))
        names.append(name)
    return pa.RecordBatch.from_arrays(arrays, names=names)


#: Set positions of sparse points that a kernel visits at once.
KERNEL_ONES = 1 << 20


def slices(batch: pa.RecordBatch, dense_rows: int, sparse_rows: int) -> Iterator[pa.RecordBatch]:
    """A batch of ids and points in slices that a kernel's arrays have room for. Those of sparse points hang on what is set, not on the width."""
    if not is_sparse(batch.column(1)):
        yield from (batch.slice(at, dense_rows) for at in range(0, batch.num_rows, dense_rows))
        return
    ends, at = np.cumsum(np.diff(batch.column(1).offsets.to_numpy())), 0
    while at < batch.num_rows:
        before = ends[at - 1] if at else 0
        rows = int(np.searchsorted(ends, before + KERNEL_ONES, "right")) - at
        rows = min(max(1, rows), sparse_rows)
        yield batch.slice(at, rows)
        at += rows


def _hasher(points: DataFrame, tables: int, kernel: Callable[[pa.RecordBatch], Iterator[tuple[int, np.ndarray]]], carry: bool, layout: str, width: int = 8, paired: bool = False, dense: int = 0) -> DataFrame:
    """Runs a kernel that gives keys part by part. `carry` keeps the code on each row; layout 'array' gives one row for each point and part, with all its keys.
    `dense`: rows that the kernel makes of a dense point, if they are more than the tables."""
    kind = "code array<bigint>" if "code" in points.columns else "ones array<int>"
    name = kind.split()[0]
    rows_at_once = [max(16, KERNEL_BYTES // (width * max(1, most))) for most in (max(tables, dense), tables)]

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in it:
            for batch in slices(whole, *rows_at_once):
                ids = batch.column(0).to_numpy(zero_copy_only=False)
                for part, keys, *check in kernel(batch.column(1)):
                    if layout == "array":
                        flat = np.ascontiguousarray(keys.T).ravel()
                        offsets = np.arange(0, len(flat) + 1, len(keys), dtype=np.int32)
                        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.full(len(ids), part, np.int32)), pa.ListArray.from_arrays(offsets, flat)], names=["id", "part", "buckets"])
                    else:
                        yield _rows(ids, part, keys, {name: batch.column(1)} if carry else None, check)

    schema = "id bigint, part int, buckets array<bigint>" if layout == "array" else HASHED + (", check bigint" if paired else "") + (f", {kind}" if carry else "")
    return points.select(F.col("id").cast("bigint").alias("id"), name).where(F.col(name).isNotNull()).mapInArrow(run, schema)


#: From codes: part and keys of all tables, and second keys if the plan has pairs.
Kernel = Callable[[pa.Array], Iterator[tuple]]


def is_sparse(column: pa.Array) -> bool:
    return pa.types.is_int32(column.type.value_type)


def transform_kernel(plan: CoverPlan) -> Kernel:
    """Keys of all tables of a part from one fast transform per point."""

    def kernel(column: pa.Array) -> Iterator[tuple]:
        sparse = is_sparse(column)
        bits = None if sparse else unpacked(column, plan.d)
        for part in range(plan.parts):
            sketches = (_sparse_sketch(column, plan, part, key) if sparse else _dense_sketch(bits, plan, part, key) for key in range(1 + plan.paired))
            yield part, *(transform_hash(sketch, plan.prime) for sketch in sketches)

    return kernel


def equal_kernel(plan: CoverPlan) -> Kernel:
    """Keys that are equal where the transform's are, to be compared only with one another: twice the sums of the kept seeds, modulo 2 ** 64. No stage of the transform is reduced.
    Unequal masked codes meet as rarely as modulo the prime: their seeds are drawn from as many."""

    def kernel(column: pa.Array) -> Iterator[tuple]:
        bits = np.ascontiguousarray(unpacked(column, plan.d).T)
        for part in range(plan.parts):
            where, labels, seeds = columns(plan, part)
            order = np.argsort(labels, kind="stable")
            used, starts = np.unique(labels[order], return_index=True)
            sketch = np.zeros((1 << plan.bits(part), bits.shape[1]), np.int64)
            sketch[used] = np.add.reduceat(bits[where[order]] * seeds[order][:, None], starts, axis=0)
            whole = sketch.sum(axis=0)
            keys = fwht(sketch)[1:]
            yield part, np.subtract(whole, keys, out=keys)

    return kernel


def transform_cover_hash(points: DataFrame, plan: CoverPlan, carry: bool = False, layout: str = "rows", engine: str = "arrow") -> DataFrame:
    """Bucket rows of the covering family by transforms, in Arrow kernels or (`engine='sql'`) by SQL expressions."""
    if engine == "sql":
        return _sql_cover_hash(points, plan)
    return _hasher(points, max(map(plan.tables, range(plan.parts))), transform_kernel(plan), carry, layout, paired=plan.paired)


def cover_keys_expr(code: Column, plan: CoverPlan, part: int) -> Column:
    """All keys of a part as one array, by SQL expressions; for primes below 2 ** 32."""
    if plan.prime >= 1 << 32 or plan.paired:
        raise ValueError("expressions add without reduction: use a prime below 2 ** 32")
    where, labels, seeds = plan.columns(part)
    size = 1 << plan.bits(part)
    zero = F.lit(0).cast("bigint")
    cells = [zero] * size
    for w, label, seed in zip(where, labels, seeds, strict=True):
        one = F.shiftrightunsigned(code[w // 64], w % 64).bitwiseAND(F.lit(1).cast("bigint"))
        cells[label] = cells[label] + one * F.lit(seed).cast("bigint")
    last = F.lit(size - 1)
    # One stage for each bit: the element whose bit is clear takes the sum, its partner the difference.
    stages = F.array(*(F.lit(1 << b) for b in range(plan.bits(part))))
    moved = F.aggregate(
        stages,
        F.array(*cells),
        lambda t, half: F.transform(F.sequence(F.lit(0), last), lambda i: F.when(i.bitwiseAND(half) == 0, F.get(t, i) + F.get(t, i + half)).otherwise(F.get(t, i - half) - F.get(t, i))),
    )
    # The first element of the transform is the sum of all.
    return F.transform(F.array(moved), lambda t: F.transform(F.slice(t, 2, size - 1), lambda x: F.pmod(F.shiftright(F.get(t, F.lit(0)) - x, 1), F.lit(plan.prime).cast("bigint"))))[0]


def _sql_cover_hash(points: DataFrame, plan: CoverPlan) -> DataFrame:
    found = None
    for part in range(plan.parts):
        rows = points.select("id", F.lit(part).alias("part"), F.posexplode(cover_keys_expr(F.col("code"), plan, part)).alias("pos", "bucket"))
        rows = rows.select("id", "part", (F.col("pos") + 1).alias("v"), "bucket")
        found = rows if found is None else found.union(rows)
    return found


def masked_cover_hash(points: DataFrame, plan: CoverPlan, carry: bool = False, key: str = "linear", layout: str = "rows") -> DataFrame:
    """The plain covering family: a mask for each table, and the same integers as the transform, each by its own sum.

    `key='mask'`: the masked code itself is the bucket, an array of words, by SQL expressions.
    """
    if key == "mask":
        spark, rows = points.sparkSession, []
        for part in range(plan.parts):
            where, labels, _ = plan.columns(part)
            for v, keep in enumerate(mask_bits(labels, plan.bits(part)).tolist(), 1):
                words = [0] * words_of(plan.d)
                for w, k in zip(where, keep, strict=True):
                    words[w // 64] |= k << (w % 64)
                rows.append((part, v, [x - (1 << 64) if x >> 63 else x for x in words]))
        if len(rows) * 8 * (words_of(plan.d) + 2) > MASK_BYTES:
            raise ValueError("too many masks to broadcast: use integer keys")
        masks = spark.createDataFrame(rows, "part int, v int, mask array<bigint>")
        masked = F.array(*(F.col("code")[i].bitwiseAND(F.col("mask")[i]) for i in range(words_of(plan.d))))
        # A row for each point and table is what an index of masks is; the masks are as many as the tables.
        return points.crossJoin(F.broadcast(masks)).select("id", "part", "v", masked.alias("bucket"))

    return _hasher(points, max(map(plan.tables, range(plan.parts))), masked_kernel(plan), carry, layout, paired=plan.paired, dense=plan.d * plan.copies)


def masked_kernel(plan: CoverPlan) -> Kernel:
    """The same keys as the transform's, each summed by itself over what its mask keeps."""
    masks: dict[int, np.ndarray] = {}

    def one(column: pa.Array, bits: np.ndarray | None, part: int, key: int) -> np.ndarray:
        if bits is None:
            return _masked_sparse(column, plan, part, key)
        where, labels, seeds = columns(plan, part, key)
        if part not in masks:
            masks[part] = mask_bits(labels.tolist(), plan.bits(part))
        keep = masks[part]
        ones = np.ascontiguousarray(bits.T)[where].astype(np.int64)
        if plan.prime < 1 << 32:
            return (keep * seeds) @ ones % plan.prime
        low, high = (keep * (seeds & ((1 << 31) - 1))) @ ones, _reduced((keep * (seeds >> 31)) @ ones)
        return _reduced((((high << 31) & P61) | (high >> 30)) + low)

    def kernel(column: pa.Array) -> Iterator[tuple]:
        bits = None if is_sparse(column) else unpacked(column, plan.d)
        for part in range(plan.parts):
            yield part, *(one(column, bits, part, key) for key in range(1 + plan.paired))

    return kernel


def _masked_sparse(ones: pa.Array, plan: CoverPlan, part: int, key: int = 0) -> np.ndarray:
    """Whether a mask keeps a position is told from its label, for what is set only: masks of all positions would grow with tables times width."""
    where, labels, seeds = columns(plan, part, key)
    n, own = len(ones), len(where) // plan.copies
    row = np.repeat(np.arange(n), np.diff(ones.offsets.to_numpy()))
    at = ones.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    out = np.zeros((plan.tables(part), n), np.int64)
    place = np.full(plan.d, -1, np.int64)
    place[where[:own]] = np.arange(own)
    mine = place[at] >= 0
    rows, begins = np.unique(row[mine], return_index=True)
    if not len(rows):
        return out
    every = np.arange(1 << plan.bits(part))
    for copy in range(plan.copies):
        column = place[at[mine]] + copy * own
        label, seed = labels[column], seeds[column]
        low, high = seed & ((1 << 31) - 1), seed >> 31
        for v in range(len(out)):
            kept = (np.bitwise_count(every & (v + 1)) & 1).take(label)
            add = np.add.reduceat(low * kept, begins)
            if plan.prime < 1 << 32:
                out[v, rows] += add
                continue
            more = _reduced(np.add.reduceat(high * kept, begins))
            out[v, rows] = _reduced(out[v, rows] + _reduced((((more << 31) & P61) | (more >> 30)) + add))
    return out % plan.prime


def bit_sampling_hash(points: DataFrame, plan: SamplePlan, carry: bool = False, key: str = "linear", layout: str = "rows") -> DataFrame:
    """Classic tables of sampled bits. The bucket is a linear hash of the bits, or with `key='bits'` up to 63 bits themselves."""
    if key == "bits" and "code" not in points.columns:  # columns of all positions
        return _hasher(points, max(plan.tables, plan.d), sampling_kernel(plan, key), carry, layout)
    return _hasher(points, plan.tables, sampling_kernel(plan, key), carry, layout, dense=plan.d)


@lru_cache(maxsize=4)
def sampled_sets(plan: SamplePlan) -> tuple[np.ndarray, np.ndarray]:
    """Of each eight tables a byte for each position, whose bit t % 8 tells whether table t samples it; and a weight of each position, for all tables."""
    return np.stack([kept for g in range(-(-plan.tables // 8)) for _, kept in _eight(g, [plan])]), position_weights(plan)


def _eight(g: int, plans: list) -> Iterator[tuple[int, np.ndarray]]:
    """Of each sampling plan that has tables from 8 * g, its place and a byte for each position. Plans of one seed and width begin alike, so a table is drawn once for all of them."""
    found = {k: np.zeros(plan.d, np.uint8) for k, plan in enumerate(plans) if isinstance(plan, SamplePlan) and plan.tables > 8 * g}
    alike: dict[tuple, list[int]] = {}
    for k in sorted(found, key=lambda k: plans[k].k):
        alike.setdefault((plans[k].seed, plans[k].d, plans[k].replace), []).append(k)
    for t in range(8 * g, 8 * g + 8):
        for group in alike.values():
            group = [k for k in group if t < plans[k].tables]
            if not group:
                continue
            row, begin = sampled_row(plans[group[-1]], t), 0
            own = np.zeros(plans[group[0]].d, np.uint8)
            for k in group:
                own[row[begin : plans[k].k]] = 1 << (t % 8)
                begin = plans[k].k
                found[k] |= own
    yield from found.items()


def sampled_row(plan: SamplePlan, t: int) -> np.ndarray:
    """Positions of a table, as `plan.positions` has them."""
    return draws.numbers(f"{plan.seed}:s:{t}:", plan.k) % plan.d if plan.replace else draws.order(f"{plan.seed}:s:{t}:", plan.d)[: plan.k]


def sampled_planes(spark: SparkSession, plans: list) -> DataFrame:
    """plan (its place), g, kept: of the sampling plans among these the bytes of each eight tables. Each table is drawn by one task, for all plans, where a task for all points would draw them all again."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for g in batch.column(0).to_pylist():
                for k, kept in _eight(g, plans):
                    yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([g], pa.int32()), pa.array([kept.tobytes()], pa.binary())], names=["plan", "g", "kept"])

    groups = max((-(-plan.tables // 8) for plan in plans if isinstance(plan, SamplePlan)), default=0)
    return spark.range(0, groups, 1, max(1, min(groups, 16 * spark.sparkContext.defaultParallelism))).mapInArrow(run, "plan int, g int, kept binary")


def gathered_planes(rows: DataFrame, d: int) -> np.ndarray:
    """Bytes of `sampled_planes` of one plan, eight tables a row."""
    kept = rows.select("g", "kept").toArrow().sort_by("g")["kept"].to_pylist()
    return np.frombuffer(b"".join(kept), np.uint8).reshape(len(kept), d)


def compact_sets(ones: pa.Array, plan: SamplePlan, rows: DataFrame) -> tuple[pa.Array, SamplePlan, tuple[np.ndarray, np.ndarray]]:
    """Sparse points over the positions that some of them has, renumbered; and for these a plan and sets, from the plan's `sampled_planes`, that give the same keys."""
    used, at = np.unique(ones.flatten().to_numpy(zero_copy_only=False).astype(np.int64), return_inverse=True)
    offsets = np.concatenate([[0], np.cumsum(np.diff(ones.offsets.to_numpy()))]).astype(np.int32)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            kept = [np.frombuffer(x, np.uint8)[used].tobytes() for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(kept, pa.binary())], names=["g", "kept"])

    planes = gathered_planes(rows.select("g", "kept").mapInArrow(run, "g int, kept binary"), len(used))
    return pa.ListArray.from_arrays(offsets, pa.array(at.astype(np.int32))), replace(plan, d=max(1, len(used))), (planes, position_weights(plan)[used])


def drawn_by_tasks(spark: SparkSession, plan: SamplePlan) -> tuple[np.ndarray, np.ndarray] | None:
    """`sampled_sets`, drawn by tasks. None if they are too large to broadcast."""
    if -(-plan.tables // 8) * plan.d + 8 * plan.d > MASK_BYTES:
        return None
    return gathered_planes(sampled_planes(spark, [plan]), plan.d), position_weights(plan)


@lru_cache(maxsize=4)
def position_weights(plan: SamplePlan) -> np.ndarray:
    return 1 + draws.numbers(f"{plan.seed}:bs:", plan.d) % (plan.prime - 1)


def _sampled_sparse(ones: pa.Array, plan: SamplePlan, sets: tuple[np.ndarray, np.ndarray] | None = None) -> np.ndarray:
    """Keys by what is set: equal if the same sampled positions are. A position sampled twice by a table says nothing more, so it counts once."""
    kept, weights = sets or sampled_sets(plan)
    n, sizes = len(ones), np.diff(ones.offsets.to_numpy())
    at = ones.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    keys, some = np.zeros((plan.tables, n), np.int64), np.flatnonzero(sizes)
    if not len(some):
        return keys
    begins, weight = (np.cumsum(sizes) - sizes)[some], weights[at]
    low, high = weight & ((1 << 31) - 1), weight >> 31
    for t in range(plan.tables):
        if t % 8 == 0:
            byte = kept[t // 8].take(at)
        mine = byte >> (t % 8) & 1
        add = np.add.reduceat(low * mine, begins)
        if plan.prime >= 1 << 32:
            more = _reduced(np.add.reduceat(high * mine, begins))
            add = _reduced((((more << 31) & P61) | (more >> 30)) + add)
        keys[t, some] = add
    return keys % plan.prime


def sampling_kernel(plan: SamplePlan, key: str = "linear", sets: tuple[np.ndarray, np.ndarray] | None = None) -> Kernel:
    if key == "bits" and plan.k > 63:
        raise ValueError("at most 63 bits make a key of their own")
    prime, dense = plan.prime, []

    def drawn() -> tuple[np.ndarray, np.ndarray]:
        if not dense:
            dense.append(np.array(plan.positions, np.int64))
            dense.append(np.array([[1 << j for j in range(plan.k)]] * plan.tables if key == "bits" else plan.seeds(), np.int64))
        return tuple(dense)

    def kernel(column: pa.Array) -> Iterator[tuple[int, np.ndarray]]:
        if is_sparse(column) and key != "bits":
            yield 0, _sampled_sparse(column, plan, sets)
            return
        where, weights = drawn()
        by_column = _sparse_columns(column, plan.d) if is_sparse(column) else np.ascontiguousarray(unpacked(column, plan.d).T)
        keys = np.empty((plan.tables, len(column)), np.int64)
        for t in range(plan.tables):
            ones = by_column[where[t]].astype(np.int64)
            if key == "bits" or prime < 1 << 32:
                keys[t] = weights[t] @ ones
                if key != "bits":
                    keys[t] %= prime
            else:
                high = _reduced((weights[t] >> 31) @ ones)
                keys[t] = _reduced((((high << 31) & P61) | (high >> 30)) + (weights[t] & ((1 << 31) - 1)) @ ones)
        yield 0, keys

    return kernel


def kernel_of(method: str, plan: CoverPlan | SamplePlan) -> Kernel:
    return {"transform_cover": transform_kernel, "masked_cover": masked_kernel, "bit_sampling": sampling_kernel}[method](plan)


def fused_hits(points: DataFrame, queries: DataFrame, method: str, plan: CoverPlan | SamplePlan, carry: bool = False) -> DataFrame:
    """Hits (qid, id, part, v) of a small set of queries in one pass over the points: each batch is hashed and looked up in the
    queries' keys, and only hits leave the kernel. No bucket row of a point is ever made, and nothing is shuffled.

    The caller bounds the queries. `carry` adds both codes.
    """
    value = "code" if "code" in points.columns else "ones"
    kind = "array<bigint>" if value == "code" else "array<int>"
    arrow = pa.list_(pa.int64() if value == "code" else pa.int32())
    table = queries.select("qid", value).where(F.col(value).isNotNull()).toArrow().combine_chunks()
    asked = points.sparkSession.sparkContext.broadcast((table["qid"].to_numpy(), table[value].to_pylist()))
    tables = max(map(plan.tables, range(plan.parts))) if isinstance(plan, CoverPlan) else plan.tables
    at_once = [max(64, KERNEL_BYTES // (8 * most)) for most in (max(tables, plan.d), tables)]

    spark = points.sparkSession
    sets = drawn_by_tasks(spark, plan) if method == "bit_sampling" and value == "ones" and len(table) else None
    sets = sets and spark.sparkContext.broadcast(sets)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plain = method == "transform_cover" and value == "code" and plan.prime == P61 and not plan.paired
        kernel = sampling_kernel(plan, sets=sets.value) if sets else equal_kernel(plan) if plain else kernel_of(method, plan)
        qids, values = asked.value
        if not len(qids):
            return
        qcodes = pa.array(values, arrow)
        sorted_keys = {}
        for part, keys, *check in kernel(qcodes):
            order = np.argsort(keys, axis=1, kind="stable")
            sorted_keys[part] = np.take_along_axis(keys, order, 1), order, check
        for whole in it:
            for batch in slices(whole, *at_once):
                ids, codes = batch.column(0).to_numpy(), batch.column(1)
                for part, keys, *check in kernel(codes):
                    known, order, qcheck = sorted_keys[part]
                    for v in range(len(keys)):
                        lo = np.searchsorted(known[v], keys[v], "left")
                        some = np.flatnonzero(known[v][np.minimum(lo, len(qids) - 1)] == keys[v])
                        if not len(some):
                            continue
                        n = np.searchsorted(known[v], keys[v][some], "right") - lo[some]
                        row = np.repeat(some, n)
                        place = np.repeat(lo[some] - (np.cumsum(n) - n), n) + np.arange(n.sum())
                        q = order[v][place]
                        for mine, theirs in zip(check, qcheck, strict=True):
                            same = mine[v][row] == theirs[v][q]
                            row, q = row[same], q[same]
                        arrays = [pa.array(qids[q]), pa.array(ids[row]), pa.array(np.full(len(q), part, np.int32)), pa.array(np.full(len(q), v + 1, np.int32))]
                        names = ["qid", "id", "part", "v"]
                        if carry:
                            arrays += [codes.take(pa.array(row)), qcodes.take(pa.array(q))]
                            names += [value, f"q{value}"]
                        yield pa.RecordBatch.from_arrays(arrays, names=names)

    schema = "qid bigint, id bigint, part int, v int" + (f", {value} {kind}, q{value} {kind}" if carry else "")
    return points.select(F.col("id").cast("bigint").alias("id"), value).where(F.col(value).isNotNull()).mapInArrow(run, schema)


def kept_positions(plan: CoverPlan | SamplePlan) -> list[tuple[int, np.ndarray]]:
    """Of each part its number and the positions that each table keeps, as rows of zeros and ones: two codes share a bucket if they agree there."""
    if isinstance(plan, SamplePlan):
        kept = np.zeros((plan.tables, plan.d), np.uint8)
        kept[np.arange(plan.tables)[:, None], np.array(plan.positions, np.int64)] = 1
        return [(0, kept)]
    found = []
    for part in range(plan.parts):
        where, labels, _ = columns(plan, part)
        kept = np.zeros((plan.tables(part), plan.d), np.uint8)
        masks = mask_bits(labels.tolist(), plan.bits(part)).astype(np.uint8)
        own = len(plan.positions[part])
        for at in range(0, len(where), own):  # copies of the positions, one after the other
            kept[:, where[at : at + own]] |= masks[:, at : at + own]
        found.append((part, kept))
    return found


def _words(bits: np.ndarray) -> np.ndarray:
    """Rows of zeros and ones as words."""
    packed = np.zeros((len(bits), words_of(bits.shape[1]) * 8), np.uint8)
    data = np.packbits(bits, axis=1, bitorder="little")
    packed[:, : data.shape[1]] = data
    return packed.view(np.uint64)


#: Bits of a sum by which `met_rows` looks first, and keys of a block, which stay in a core's cache.
FIRST_BITS, BLOCK_KEYS = 12, 1 << 16


def met_rows(points: DataFrame, queries: DataFrame, plans: list[CoverPlan | SamplePlan]) -> DataFrame:
    """Of dense points the bucket rows that some query meets, for several plans in one pass: plan (its place), id, part, v, bucket, code.

    The rows are those of hashing all points, less accidents of unequal keys, without making the others: a point's kept bits are summed for all tables by one product
    of matrices under small weights, whose sums are exact; a sum that no query has is no row, and the others are told from the codes themselves. The caller bounds queries and plans."""
    spark, d = points.sparkSession, plans[0].d
    table = queries.select("qid", "code").where(F.col("code").isNotNull()).toArrow().combine_chunks()
    asked = spark.sparkContext.broadcast(table["code"].to_pylist())

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not asked.value:
            return
        qcodes = pa.array(asked.value, pa.list_(pa.int64()))
        qbits = unpacked(qcodes, d)
        qwords = _words(qbits)
        weights = np.random.default_rng(d).integers(1, (1 << 24) // d, d).astype(np.float32)  # sums below 2 ** 24
        ready = []
        for k, plan in enumerate(plans):
            buckets = {part: keys for part, keys, *_ in kernel_of("transform_cover" if isinstance(plan, CoverPlan) else "bit_sampling", plan)(qcodes)}
            for part, kept in kept_positions(plan):
                used = np.flatnonzero(kept.any(axis=0))
                weighted = kept[:, used] * weights[used]
                sums = (weighted @ qbits[:, used].T.astype(np.float32)).astype(np.int64)
                first = np.zeros((len(kept), 1 << FIRST_BITS), bool)
                np.put_along_axis(first, sums & ((1 << FIRST_BITS) - 1), True, 1)
                ready.append((k, part, used, weighted, sums, first.ravel(), (np.arange(len(kept)) << FIRST_BITS)[:, None], _words(kept), buckets[part]))
        for whole in it:
            for at in range(0, whole.num_rows, 4096):
                batch = whole.slice(at, 4096)
                ids, codes = batch.column(0).to_numpy(), batch.column(1)
                bits = unpacked(codes, d)
                words, columns_ = _words(bits), np.ascontiguousarray(bits.T).astype(np.float32)
                for k, part, used, weighted, sums, first, begins, masks, buckets in ready:
                    own, step = columns_ if len(used) == d else columns_[used], max(64, BLOCK_KEYS // len(masks))
                    for lo in range(0, len(ids), step):
                        found = (weighted @ own[:, lo : lo + step]).astype(np.int64)
                        n = found.shape[1]
                        places = found & ((1 << FIRST_BITS) - 1)
                        places += begins
                        some = np.flatnonzero(first.take(places, mode="clip"))  # none is out of bounds
                        if not len(some):
                            continue
                        hit, q = np.nonzero(sums[some // n] == found.ravel()[some][:, None])
                        some = some[hit]
                        v, row = some // n, some % n + lo
                        same = ((words[row] ^ qwords[q]) & masks[v] == 0).all(axis=1)
                        some, v, row, q = some[same], v[same], row[same], q[same]
                        some, once = np.unique(some, return_index=True)
                        if len(once):
                            v, row, q = v[once], row[once], q[once]
                            arrays = [np.full(len(v), k, np.int32), ids[row], np.full(len(v), part, np.int32), (v + 1).astype(np.int32), buckets[v, q]]
                            yield pa.RecordBatch.from_arrays([*map(pa.array, arrays), codes.take(pa.array(row))], names=["plan", "id", "part", "v", "bucket", "code"])

    return points.select(F.col("id").cast("bigint").alias("id"), "code").where(F.col("code").isNotNull()).mapInArrow(run, f"plan int, {HASHED}, code array<bigint>")


#: Bytes of which tables keep which positions that one pass over sparse points has at hand.
PASS_BYTES = 128 << 20
#: Positions by which `sparse_met` rules tables out, and queries that it looks at together.
FIRST_ONES, TOGETHER = 48, 5
#: Bits of labels up to which `sparse_met` has the code of each label at hand.
CODE_BITS = 12


def codebook(bits: int) -> np.ndarray:
    """Of each label, as words, the tables whose masks keep it: bit v - 1 for table v. Label 0 is kept by none."""
    labels, v = np.arange(1 << bits), np.arange(1, 1 << bits)
    return np.stack([_words((np.bitwise_count(label & v) & 1).astype(np.uint8)[None])[0] for label in labels])


def label_rows(plan: CoverPlan, part: int) -> list[np.ndarray]:
    """Of each copy the labels of all positions, 0 for those of other parts, which no mask keeps."""
    where, labels, _ = columns(plan, part)
    own, rows = len(where) // plan.copies, []
    for copy in range(plan.copies):
        row = np.zeros(plan.d, np.int32)
        row[where[:own]] = labels[copy * own : (copy + 1) * own]
        rows.append(row)
    return rows


def sparse_passes(plans: list[CoverPlan | SamplePlan], planes: DataFrame | None) -> Iterator[list[tuple]]:
    """Tables of all plans in as many passes as `PASS_BYTES` asks for: of each its plan's place, part, first table, number of tables, and which tables keep a position:
    rows of words, and for each position the rows to join."""
    found, held = [], 0
    for k, plan in enumerate(plans):
        if isinstance(plan, CoverPlan):
            pieces = [(part, 0, plan.tables(part), None) for part in range(plan.parts)]
        else:
            step = max(1, MASK_BYTES // plan.d // 8 * 8)
            groups = -(-plan.tables // 8)
            pieces = [(0, 8 * g, min(plan.tables, 8 * (g + step)) - 8 * g, (g, min(groups, g + step))) for g in range(0, groups, step)]
        for part, first, tables, span in pieces:
            cost = (4 * plan.copies * plan.d if span is None else (span[1] - span[0]) * plan.d)
            if found and held + cost > PASS_BYTES:
                yield found
                found, held = [], 0
            held += cost
            if span is None:
                found.append((k, part, first, tables, plan.bits(part), label_rows(plan, part)))
            else:
                rows = gathered_planes(planes.where((F.col("plan") == k) & (F.col("g") >= span[0]) & (F.col("g") < span[1])), plan.d)
                wide = np.zeros((plan.d, -(-len(rows) // 8) * 8), np.uint8)
                wide[:, : len(rows)] = rows.T
                found.append((k, part, first, tables, wide.view(np.uint64), None))
    if found:
        yield found


def sparse_met(points: DataFrame, queries: DataFrame, plans: list[CoverPlan | SamplePlan], planes: DataFrame | None, counted: bool) -> DataFrame:
    """Of sparse points what meets in some table, for several plans, stored. `counted`: plan (its place), qid, id, n, rows of a pair to be added up; else a row
    plan, id, part, ones, v, qid for the buckets of a point that some query meets: the tables, and of each one of these queries. No keys are made, so there are no accidents of unequal ones.

    A point and a query meet in a table if it keeps none of the positions in which they differ, and those of the point that no query has are among them for all queries.
    So tables that keep such a position are ruled out by words, for all queries, then for few together; and for pairs that have tables left by all positions in which they differ."""
    from hamcover.sources.shared import shared_dir

    spark, d = points.sparkSession, plans[0].d
    table = queries.select("qid", "ones").where(F.col("ones").isNotNull()).toArrow().combine_chunks()
    table = table.take(pa.array(np.argsort([len(x) for x in table["ones"].to_pylist()], kind="stable"))) if len(table) else table  # small ones together
    qids = table["qid"].to_numpy().astype(np.int64)
    asked = [np.array(x, np.int64) for x in table["ones"].to_pylist()]
    schema = "plan int, qid bigint, id bigint, n bigint" if counted else "plan int, id bigint, part int, ones array<int>, v array<int>, qid array<bigint>"
    path = shared_dir(spark, "met")
    if not len(qids):
        return spark.createDataFrame([], schema)
    source = points.select(F.col("id").cast("bigint").alias("id"), "ones").where(F.col("ones").isNotNull())
    for entries in sparse_passes(plans, planes):
        sent = spark.sparkContext.broadcast(entries)

        def run(it: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            spans = [(0, len(asked)), *((lo, min(len(asked), lo + TOGETHER)) for lo in range(0, len(asked), TOGETHER))]
            common = np.zeros((len(spans), d), bool)
            for g, (lo, hi) in enumerate(spans):
                common[g][np.concatenate(asked[lo:hi])] = True
            ready = []
            for k, part, first, tables, kept, labels in sent.value:
                rows = codebook(kept) if labels else kept
                spare = np.full(rows.shape[1], (1 << 64) - 1, np.uint64)  # bits that are no table's
                spare ^= _words(np.concatenate([np.ones(tables, np.uint8), np.zeros(64 * len(spare) - tables, np.uint8)])[None])[0]
                ready.append((k, part, first, tables, rows, labels, spare))
            for whole in it:
                for batch in slices(whole, 1, 4096):
                    yield from _met_of(batch, ready, spans, common, asked, qids, counted)

        rows = source.mapInArrow(run, schema).write.mode("append")
        (rows if counted else rows.partitionBy("plan")).parquet(path)
        sent.destroy()
    return spark.read.schema(schema).parquet(path)


def _kept_words(rows: np.ndarray, labels: list[np.ndarray] | None, at: np.ndarray) -> np.ndarray:
    """Of positions, as words, the tables that keep them."""
    if labels is None:
        return rows.take(at, axis=0)
    found = rows.take(labels[0].take(at), axis=0)
    for more in labels[1:]:
        found |= rows.take(more.take(at), axis=0)
    return found


def _ranked(at: np.ndarray, row: np.ndarray, n: int, most: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Positions of points, given point by point: the first of each in a row, the second in the next, and how many there are; at most so many."""
    alone = np.bincount(row, minlength=n)
    rank = np.arange(len(at)) - np.repeat(np.cumsum(alone) - alone, alone)
    if most is not None:
        mine, alone = rank < most, np.minimum(alone, most)
        at, row, rank = at[mine], row[mine], rank[mine]
    firsts = np.zeros((alone.max(initial=0), n), np.int64)
    firsts[rank, row] = at
    return firsts, alone


def _ruled_out(ruled: np.ndarray, points: np.ndarray, firsts: np.ndarray, alone: np.ndarray, rows: np.ndarray, labels: list[np.ndarray] | None) -> tuple[np.ndarray, np.ndarray]:
    """Points that have tables left, and as words the tables that are ruled out."""
    order = np.argsort(-alone[points], kind="stable")
    points, ruled = points[order], ruled[order]
    have = alone[points]
    for j in range(have.max(initial=0)):
        if not len(have) or have[0] <= j:
            break
        m = int(np.searchsorted(-have, -j, "left"))
        ruled[:m] |= _kept_words(rows, labels, firsts[j, points[:m]])
        if j % 8 == 7:
            left = (ruled != (1 << 64) - 1).any(axis=1)
            points, ruled, have = points[left], ruled[left], have[left]
    left = (ruled != (1 << 64) - 1).any(axis=1)
    return points[left], ruled[left]


def _ruled_by(ruled: np.ndarray, points: np.ndarray, missing: np.ndarray, kept: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """As `_ruled_out`, by positions of one query: which of them a point is missing, and the tables that keep them."""
    lacks = missing[points]
    for j, words in enumerate(kept):
        ruled = ruled | (np.uint64(0) - lacks[:, j].astype(np.uint64))[:, None] & words
        if j % 8 == 7 or j == len(kept) - 1:
            left = (ruled != (1 << 64) - 1).any(axis=1)
            points, ruled, lacks = points[left], ruled[left], lacks[left]
            if not len(points):
                break
    return points, ruled


def _ruled_by_all(ruled: np.ndarray, points: np.ndarray, at: np.ndarray, begins: np.ndarray, sizes: np.ndarray, one: np.ndarray, place: np.ndarray, rows: np.ndarray, labels: list[np.ndarray] | None) -> tuple[np.ndarray, np.ndarray]:
    """As `_ruled_out`, by all positions in which points differ from one query. `place`: of each position its place in the query from 1, or 0."""
    own = sizes[points]
    local = np.repeat(np.arange(len(points)), own)
    mine = at[np.repeat(begins[points] - (np.cumsum(own) - own), own) + np.arange(own.sum())]
    told = place.take(mine)
    common = np.flatnonzero(told)
    lacks = np.ones((len(points), len(one)), bool)
    lacks[local[common], told[common] - 1] = False
    other = np.flatnonzero(told == 0)
    row, j = np.nonzero(lacks)
    row, differ = np.concatenate([local[other], row]), np.concatenate([mine[other], one[j]])
    order = np.argsort(row, kind="stable")
    left, ruled = _ruled_out(ruled, np.arange(len(points)), *_ranked(differ[order], row[order], len(points)), rows, labels)
    return points[left], ruled


def _met_of(batch: pa.RecordBatch, ready: list[tuple], spans: list[tuple[int, int]], common: np.ndarray, asked: list[np.ndarray], qids: np.ndarray, counted: bool) -> Iterator[pa.RecordBatch]:
    ids, n = batch.column(0).to_numpy(), batch.num_rows
    sizes = np.diff(batch.column(1).offsets.to_numpy())
    begins = np.cumsum(sizes) - sizes
    at = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    row = np.repeat(np.arange(n), sizes)
    lone = [_ranked(at[other], row[other], n, FIRST_ONES) for other in (np.flatnonzero(~mine.take(at)) for mine in common)]
    samples = [one[:: max(1, len(one) // FIRST_ONES)][:FIRST_ONES] for one in asked]
    missing, place, byte = [], np.zeros(common.shape[1], np.int32), np.zeros(common.shape[1], np.uint8)
    for one in samples:
        byte[one] = np.arange(1, len(one) + 1)
        told = byte.take(at)
        byte[one] = 0
        some = np.flatnonzero(told != 0)
        lacks = np.ones((n, len(one)), bool)
        lacks[row[some], told[some] - 1] = False
        missing.append(lacks)
    for k, part, first, tables, rows, labels, spare in ready:
        some, left = _ruled_out(np.tile(spare, (n, 1)), np.arange(n), *lone[0], rows, labels)
        pairs = []
        for (lo_q, hi_q), (firsts, alone) in zip(spans[1:], lone[1:], strict=True):
            near, ruled = _ruled_out(left, some, firsts, alone, rows, labels)
            for q in range(lo_q, hi_q) if len(near) else ():
                mine, out = _ruled_by(ruled, near, missing[q], _kept_words(rows, labels, samples[q]))
                one, step = asked[q], max(1, KERNEL_BYTES // (16 * (1 + len(asked[q]))))
                place[one] = np.arange(1, len(one) + 1)
                for lo in range(0, len(mine), step):
                    p, words = _ruled_by_all(out[lo : lo + step], mine[lo : lo + step], at, begins, sizes, one, place, rows, labels)
                    pairs.append((p, np.full(len(p), q), ~words))
                place[one] = 0
        if not pairs:
            continue
        p, q, met = (np.concatenate(x) for x in zip(*pairs, strict=True))
        if counted:
            arrays = [np.full(len(p), k, np.int32), qids[q], ids[p], np.bitwise_count(met).sum(axis=1, dtype=np.int64)]
            yield pa.RecordBatch.from_arrays([*map(pa.array, arrays)], names=["plan", "qid", "id", "n"])
            continue
        if not len(p):
            continue
        order = np.argsort(p, kind="stable")
        p, q, met = p[order], q[order], met[order]
        starts = np.flatnonzero(np.concatenate([[True], p[1:] != p[:-1]]))
        met_by, met_in = [], []
        for lo, hi in zip(starts, np.append(starts[1:], len(p)), strict=True):  # a bucket once, however many queries meet in it
            bits = np.unpackbits(met[lo:hi].view(np.uint8), axis=1, bitorder="little")
            met_in.append(np.flatnonzero(bits.any(axis=0)))
            met_by.append(q[lo + bits[:, met_in[-1]].argmax(axis=0)])
        offsets = np.concatenate([[0], np.cumsum([len(t) for t in met_in])]).astype(np.int32)
        tables_met, by = (first + 1 + np.concatenate(met_in)).astype(np.int32), qids[np.concatenate(met_by)]
        own = p[starts]
        arrays = [pa.array(np.full(len(own), k, np.int32)), pa.array(ids[own]), pa.array(np.full(len(own), part, np.int32)), batch.column(1).take(pa.array(own))]
        arrays += [pa.ListArray.from_arrays(offsets, pa.array(x)) for x in (tables_met, by)]
        yield pa.RecordBatch.from_arrays(arrays, names=["plan", "id", "part", "ones", "v", "qid"])


def _sparse_columns(ones: pa.Array, d: int) -> np.ndarray:
    """Rows of positions by points; for kernels that look at few of many positions."""
    out = np.zeros((d, len(ones)), np.uint8)
    out[ones.flatten().to_numpy(zero_copy_only=False), np.repeat(np.arange(len(ones)), np.diff(ones.offsets.to_numpy()))] = 1
    return out


def substring_hash(points: DataFrame, plan: SubstringPlan, carry: bool = False) -> DataFrame:
    """One row for each substring; the bucket is the substring itself. Expressions only. `carry` keeps the code on each row."""
    own = ["code"] * carry
    parts = F.array(*(F.struct(F.lit(t).alias("part"), s.alias("bucket")) for t, s in enumerate(split(F.col("code"), list(plan.bounds)))))
    return points.select("id", *own, F.explode(parts).alias("s")).select("id", "s.part", F.lit(1).alias("v"), "s.bucket", *own)


def flip_masks(width: int, radius: int) -> list[int]:
    """All integers of `width` bits with at most `radius` ones, as signed 64-bit integers."""
    from itertools import combinations

    masks = [sum(1 << i for i in c) for k in range(radius + 1) for c in combinations(range(width), k)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


#: Probes of one query that are enumerated at most: 16 MB of flip masks.
MOST_PROBES = 2_000_000


def substring_probes(queries: DataFrame, plan: SubstringPlan) -> DataFrame:
    """qid, part, v, bucket of all buckets that a query has to look at: every substring within its radius."""
    if sum(map(plan.probes, range(plan.tables))) > MOST_PROBES:
        raise ValueError("too many probes: use more substrings")
    spark = queries.sparkSession
    rows = [(t, flip_masks(hi - lo, r)) for t, ((lo, hi), r) in enumerate(zip(plan.bounds, plan.radii, strict=True)) if r >= 0]
    flips = spark.createDataFrame(rows, "part int, flips array<bigint>")
    own = substring_hash(queries.withColumnRenamed("qid", "id"), plan).withColumnRenamed("id", "qid")
    probed = own.join(F.broadcast(flips), "part")
    return probed.select("qid", "part", "v", F.explode(F.transform("flips", lambda m: m.bitwiseXOR(F.col("bucket")))).alias("bucket"))


def ball_probes(queries: DataFrame, d: int, r: int) -> DataFrame:
    """qid and every code within r of the query's."""
    if ball_size(d, r) > MOST_PROBES or ball_size(d, r) * 8 * (words_of(d) + 2) > MASK_BYTES:
        raise ValueError(f"{ball_size(d, r)} codes around each query: hash instead")
    from itertools import combinations

    words = words_of(d)
    rows = []
    for k in range(r + 1):
        for c in combinations(range(d), k):
            mask = [0] * words
            for i in c:
                mask[i // 64] |= 1 << (i % 64)
            rows.append(([x - (1 << 64) if x >> 63 else x for x in mask],))
    masks = queries.sparkSession.createDataFrame(rows, "mask array<bigint>")
    code = F.array(*(F.col("code")[i].bitwiseXOR(F.col("mask")[i]) for i in range(words)))
    return queries.join(F.broadcast(masks)).select("qid", code.alias("code"))
