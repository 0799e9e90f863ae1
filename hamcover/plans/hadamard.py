"""Hadamard codes, the fast transform, and what can be told of a mask family without any data."""

from __future__ import annotations

from itertools import combinations

import numpy as np


def hadamard_code(v: int, bits: int) -> list[int]:
    """Parities of v AND j for all j of `bits` bits."""
    return [(v & j).bit_count() & 1 for j in range(1 << bits)]


def hadamard_codes(bits: int) -> np.ndarray:
    """All codes, one a row; for tests and small families."""
    j = np.arange(1 << bits, dtype=np.uint64)
    return (np.bitwise_count(j[:, None] & j) & 1).astype(np.int64)


def as_signs(codes: np.ndarray) -> np.ndarray:
    """0 to +1 and 1 to -1: the Hadamard matrix of the codes."""
    return 1 - 2 * codes


def fwht(rows: np.ndarray, prime: int | None = None) -> np.ndarray:
    """Unnormalised Walsh-Hadamard transform along the first axis, whose length is a power of two; in place.

    With a prime, each stage is reduced, for values near 2 ** 61.
    """
    n = len(rows)
    half = 1
    while half < n:
        view = rows.reshape(n // (2 * half), 2, half, *rows.shape[1:])
        a, b = view[:, 0], view[:, 1]
        total = a + b
        np.subtract(a, b, out=b)
        if prime:
            total -= prime * (total >= prime)
            b += prime * (b < 0)
        view[:, 0] = total
        half *= 2
    return rows


def mask_bits(labels: list[int], bits: int) -> np.ndarray:
    """One row for each v from 1: 1 where the mask keeps the position."""
    v = np.arange(1, 1 << bits, dtype=np.uint64)[:, None]
    return (np.bitwise_count(v & np.array(labels, np.uint64)) & 1).astype(np.int64)


def covers(masks: np.ndarray, radius: int) -> bool:
    """True if every difference of at most `radius` positions is missed by some mask. Exhaustive: for small widths."""
    d = masks.shape[1]
    return all((masks[:, list(c)].sum(axis=1) == 0).any() for k in range(min(radius, d) + 1) for c in combinations(range(d), k))


def rank(labels: list[int]) -> int:
    """Rank of labels as vectors over two elements."""
    basis: list[int] = []
    for x in labels:
        for b in basis:
            x = min(x, x ^ b)
        if x:
            basis.append(x)
    return len(basis)


def collision_count(differing: list[int], labels: list[int], bits: int) -> int:
    """Number of tables in which points that differ in these positions share a bucket: exact, for any labels."""
    return (1 << (bits - rank([labels[i] for i in differing]))) - 1


def collision_counts(differing: np.ndarray, labels: list[int], bits: int) -> np.ndarray:
    """collision_count() of many codes of up to 64 positions, given as words whose ones are the differing positions: all are reduced together, position by position."""
    words = differing.view(np.uint64)
    basis = np.zeros((bits, len(words)), np.int64)  # by leading bit
    for i, label in enumerate(labels):
        x = np.where((words >> np.uint64(i)) & np.uint64(1), label, 0)
        for lead in range(bits - 1, -1, -1):
            has = (x >> lead) & 1 == 1
            free = has & (basis[lead] == 0)
            basis[lead] = np.where(free, x, basis[lead])
            x = np.where(free, 0, np.where(has, x ^ basis[lead], x))
    ranks = (basis != 0).sum(axis=0)
    return (1 << (bits - ranks)) - 1
