"""Codes as arrays of 64-bit words: bit i is bit i mod 64 of word i div 64. Sparse points are sorted arrays of positions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def words_of(d: int) -> int:
    return -(-d // 64)


def hamming(a: Column | str, b: Column | str, words: int | None = None) -> Column:
    """Distance of codes. Up to eight words it is an unrolled sum, which stays in generated code; else a higher-order function."""
    a, b = _c(a), _c(b)
    if words and words <= 8:
        total = F.bit_count(a[0].bitwiseXOR(b[0]))
        for i in range(1, words):
            total = total + F.bit_count(a[i].bitwiseXOR(b[i]))
        return total.cast("int")
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)


def hamming_leq(a: Column | str, b: Column | str, r: int, words: int) -> Column:
    """distance <= r, word by word: words behind the one that decides are not looked at."""
    a, b = _c(a), _c(b)
    decided = F.lit(True)
    for w in range(words, 0, -1):
        part = hamming(a, b, w) if w <= 8 else hamming(F.slice(a, 1, w), F.slice(b, 1, w))
        decided = F.when(part > r, False).otherwise(decided)
    return decided


def popcount(a: Column | str, words: int | None = None) -> Column:
    a = _c(a)
    if words and words <= 8:
        total = F.bit_count(a[0])
        for i in range(1, words):
            total = total + F.bit_count(a[i])
        return total.cast("int")
    return F.aggregate(a, F.lit(0), lambda s, x: s + F.bit_count(x))


def hamming_sets(a: Column | str, b: Column | str) -> Column:
    """Distance of sparse points: sizes less twice the size of what they share."""
    a, b = _c(a), _c(b)
    return F.size(a) + F.size(b) - 2 * F.size(F.array_intersect(a, b))


def l1(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(_c(a), _c(b), lambda x, y: F.abs(x - y)), F.lit(0), lambda s, x: s + x.cast("int"))


def band(distance: Column | str, r: int, c: float) -> Column:
    """near, c-near or far."""
    d = _c(distance)
    return F.when(d <= r, "near").when(d <= c * r, "c-near").otherwise("far")


def pack_bits(bits: Column | str, d: int) -> Column:
    """An array of d zeros and ones as words. Positions are literals, so this is a flat expression."""
    b = _c(bits)
    words = []
    for w in range(words_of(d)):
        total = F.lit(0).cast("bigint")
        for i in range(w * 64, min(d, w * 64 + 64)):
            total = total.bitwiseOR(F.shiftleft(F.get(b, F.lit(i)).cast("bigint"), i % 64))
        words.append(total)
    return F.array(*words)


def bit(code: Column | str, i: int) -> Column:
    return F.shiftrightunsigned(_c(code)[i // 64], i % 64).bitwiseAND(F.lit(1).cast("bigint")).cast("int")


def unpack_bits(code: Column | str, d: int) -> Column:
    c = _c(code)
    return F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.expr("1") * F.call_function("getbit", F.element_at(c, (i / 64).cast("int") + 1), (i % 64).cast("int")).cast("int"))


def permute(code: Column | str, order: list[int]) -> Column:
    """The code whose bit k is bit order[k]."""
    return pack_bits(F.array(*(bit(code, i) for i in order)), len(order))


def split(code: Column | str, bounds: list[tuple[int, int]]) -> list[Column]:
    """Substrings [lo, hi) as integers; of 64 bits at most."""
    c, out = _c(code), []
    for lo, hi in bounds:
        if hi - lo > 64:
            raise ValueError("substrings of at most 64 bits")
        w, at = lo // 64, lo % 64
        part = F.shiftrightunsigned(c[w], at)
        if (hi - 1) // 64 > w:
            part = part.bitwiseOR(F.shiftleft(c[w + 1], 64 - at))
        if hi - lo < 64:
            part = part.bitwiseAND(F.lit((1 << (hi - lo)) - 1).cast("bigint"))
        out.append(part)
    return out


def replicate(code: Column | str, d: int, t: int) -> Column:
    """Every bit t times. Searches never need it: a plan draws labels for copies instead."""
    return pack_bits(F.flatten(F.array_repeat(unpack_bits(code, d), t)), d * t)


def code_to_ones(code: Column | str, d: int) -> Column:
    bits = unpack_bits(code, d)
    return F.filter(F.transform(bits, lambda x, i: F.when(x == 1, i)), lambda x: x.isNotNull())


def ones_to_code(ones: Column | str, d: int) -> Column:
    o = _c(ones)
    return F.transform(
        F.sequence(F.lit(0), F.lit(words_of(d) - 1)),
        lambda w: F.aggregate(F.filter(o, lambda x: F.floor(x / 64) == w), F.lit(0).cast("bigint"), lambda acc, x: acc.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod(x, F.lit(64)).cast("int")))),
    )
