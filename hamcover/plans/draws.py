"""All randomness: integers from md5 of a readable key, so that any engine can draw them again."""

from __future__ import annotations

import hashlib
import math

import numpy as np

SEED = 7


def digest(key: str) -> str:
    return hashlib.md5(key.encode()).hexdigest()


def number(key: str) -> int:
    """The first 15 hex digits of the key's md5, as an integer."""
    return int(digest(key)[:15], 16)


_SHIFTS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
_SINES = [int(abs(math.sin(i + 1)) * (1 << 32)) & 0xFFFFFFFF for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: Keys that are digested together, so that their arrays stay in a core's cache; and the longest key of one block.
DIGESTED, ONE_BLOCK = 1 << 15, 55


def _digested(prefix: bytes, lo: int, hi: int) -> np.ndarray:
    """md5 of the prefix followed by each number from lo to hi, all of as many digits: four rows of 32-bit words."""
    n, digits = hi - lo, len(str(lo))
    size = len(prefix) + digits
    block = bytearray(prefix + bytes(digits) + b"\x80").ljust(56, b"\0") + (8 * size).to_bytes(8, "little")
    fixed = [int.from_bytes(block[4 * w : 4 * w + 4], "little") for w in range(16)]
    moving: dict[int, np.ndarray] = {}
    left = np.arange(lo, hi, dtype=np.uint32)
    for k in range(digits - 1, -1, -1):
        rest = left // np.uint32(10)
        at = len(prefix) + k
        digit = (left - rest * np.uint32(10) + np.uint32(48)) << np.uint32(8 * (at % 4))
        moving[at // 4] = moving[at // 4] | digit if at // 4 in moving else digit | np.uint32(fixed[at // 4])
        left = rest
    a, b, c, d = (np.full(n, x, np.uint32) for x in _START)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        turn = i // 16
        if turn == 0:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif turn == 1:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
        elif turn == 2:
            np.bitwise_xor(b, c, out=f)
            f ^= d
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
        w = (i, 5 * i + 1, 3 * i + 5, 7 * i)[turn] % 16
        a += f
        if w in moving:
            a += moving[w]
            a += np.uint32(_SINES[i])
        else:
            a += np.uint32((_SINES[i] + fixed[w]) & 0xFFFFFFFF)
        shift = _SHIFTS[turn][i % 4]
        np.left_shift(a, np.uint32(shift), out=g)
        a >>= np.uint32(32 - shift)
        a |= g
        a += b
        a, b, c, d = d, a, b, c
    return np.stack([x + np.uint32(start) for x, start in zip((a, b, c, d), _START, strict=True)])


def digests(prefix: str, n: int) -> tuple[np.ndarray, np.ndarray]:
    """digest(f"{prefix}{i}") of all i below n, as two words each, which are in the order of the hex digits."""
    head = prefix.encode()
    high, low = np.empty(n, np.uint64), np.empty(n, np.uint64)
    lo = 0
    while lo < n:
        hi = min(n, lo + DIGESTED, 10 ** len(str(lo)))
        if len(head) + len(str(lo)) > ONE_BLOCK:
            words = np.frombuffer(b"".join(hashlib.md5(head + b"%d" % i).digest() for i in range(lo, hi)), ">u8").reshape(-1, 2)
            high[lo:hi], low[lo:hi] = words[:, 0], words[:, 1]
        else:
            words = _digested(head, lo, hi).byteswap().astype(np.uint64)
            high[lo:hi], low[lo:hi] = words[0] << np.uint64(32) | words[1], words[2] << np.uint64(32) | words[3]
        lo = hi
    return high, low


def numbers(prefix: str, n: int) -> np.ndarray:
    """number(f"{prefix}{i}") of all i below n."""
    return (digests(prefix, n)[0] >> np.uint64(4)).astype(np.int64)


def order(prefix: str, n: int) -> np.ndarray:
    """The numbers below n by digest(f"{prefix}{i}")."""
    high, low = digests(prefix, n)
    return np.lexsort((low, high))


def seeds(d: int, prime: int, seed: int | str = SEED, part: int = 0, copy: int = 0) -> list[int]:
    return (numbers(f"{seed}:b:{part}:{copy}:", d) % prime).tolist()


def labels_random(d: int, bits: int, seed: int = SEED, part: int = 0, copy: int = 0, skip_zero: bool = False) -> list[int]:
    """A label of `bits` bits for each position. Without zero, labels are spread over the rest."""
    draw = numbers(f"{seed}:m:{part}:{copy}:", d)
    return (1 + draw % ((1 << bits) - 1) if skip_zero else draw % (1 << bits)).tolist()


def labels_permuted(d: int, bits: int, seed: int = SEED, part: int = 0, skip_zero: bool = False) -> list[int]:
    """Labels that all differ: ranks of md5 keys. Only for d up to their number."""
    n = 1 << bits
    if d > n - skip_zero:
        raise ValueError(f"{d} positions need labels that all differ, and {bits} bits give {n - skip_zero}")
    found = np.argsort(order(f"{seed}:m:{part}:", n)).tolist()
    if skip_zero:
        found = [x for x in found if x]
    return found[:d]


def labels_identity(d: int, bits: int) -> list[int]:
    """Position i has label i; for worked examples."""
    if d > 1 << bits:
        raise ValueError("more positions than labels")
    return list(range(d))


def part_positions(d: int, parts: int, seed: int = SEED) -> list[list[int]]:
    """A random order of the positions, cut into parts; the last takes the remainder. One part keeps the order."""
    if not 1 <= parts <= d:
        raise ValueError("parts must be 1 to d")
    every = list(range(d)) if parts == 1 else order(f"{seed}:perm:", d).tolist()
    size = d // parts
    return [every[p * size : (p + 1) * size if p < parts - 1 else d] for p in range(parts)]


def sampled_positions(tables: int, k: int, d: int, seed: int = SEED, replace: bool = True) -> list[list[int]]:
    if replace:
        return [(numbers(f"{seed}:s:{t}:", k) % d).tolist() for t in range(tables)]
    if k > d:
        raise ValueError("more bits than positions")
    return [order(f"{seed}:s:{t}:", d)[:k].tolist() for t in range(tables)]
