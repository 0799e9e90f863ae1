"""Plans: from data size, width and radius to tables, parts, primes, sampled bits; and closed-form costs."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass, field, replace
from functools import cached_property

from hamcover.plans import draws

P31, P61 = (1 << 31) - 1, (1 << 61) - 1
#: Tables beyond this are refused: too many rows for any data worth hashing.
MOST_TABLE_BITS = 20


def choose_prime(n: int) -> int:
    """A prime above the square of the data size, as far as 64-bit sums go. Beyond, at about 1.5 billion points, plans have pairs of keys."""
    return P31 if n * n < P31 else P61


@dataclass(frozen=True)
class CoverPlan:
    """A covering family: in each part, 2 ** bits - 1 tables of masks over labels of `bits` bits."""

    d: int
    r: int
    n: int
    c: float = 2.0
    mode: str = "none"
    t: int = 1
    construction: str = "auto"
    skip_zero: bool = False
    prime: int = P31
    seed: int = draws.SEED
    radii: tuple[int, ...] = ()
    labels_override: tuple[int, ...] | None = field(default=None, repr=False)

    @property
    def parts(self) -> int:
        return self.t if self.mode == "partition" else 1

    @property
    def copies(self) -> int:
        return self.t if self.mode == "replicate" else 1

    @cached_property
    def positions(self) -> list[list[int]]:
        return draws.part_positions(self.d, self.parts, self.seed)

    def part_radius(self, part: int) -> int:
        return self.radii[part] if self.radii else self.r * self.copies if self.parts == 1 else self.r // self.parts

    def bits(self, part: int = 0) -> int:
        return self.part_radius(part) + 1

    def tables(self, part: int = 0) -> int:
        return (1 << self.bits(part)) - 1

    @property
    def total_tables(self) -> int:
        return sum(map(self.tables, range(self.parts)))

    def permuted(self, part: int) -> bool:
        """Labels that all differ, where there are enough of them and one copy of each position."""
        fits = len(self.positions[part]) * self.copies <= (1 << self.bits(part)) - self.skip_zero
        if self.construction == "permuted" and not fits:
            raise ValueError("permuted labels need a width of at most 2 ** (radius + 1)")
        return self.construction == "permuted" or self.construction == "auto" and fits

    @property
    def paired(self) -> bool:
        """Two keys under seeds of their own: where one prime isn't above the square of the data size, both together are."""
        return self.n * self.n > P61

    def columns(self, part: int, key: int = 0) -> tuple[list[int], list[int], list[int]]:
        """Of each hashed position (copies one after the other): where it is in the code, its label, its seed for the first or second key."""
        where, labels, seeds = [], [], []
        own = self.positions[part]
        n = len(own)
        if self.labels_override is not None:
            every = list(self.labels_override)
        elif self.permuted(part):
            every = draws.labels_permuted(n * self.copies, self.bits(part), self.seed, part, self.skip_zero)
        else:
            every = [x for copy in range(self.copies) for x in draws.labels_random(n, self.bits(part), self.seed, part, copy, self.skip_zero)]
        for copy in range(self.copies):
            where += own
            labels += every[copy * n : (copy + 1) * n]
            seeds += draws.seeds(n, self.prime, f"{self.seed}:{key}" if key else self.seed, part, copy)
        return where, labels, seeds

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "positions"}  # drawn again where they are needed

    def sized(self, n: int) -> CoverPlan:
        """The same masks, with keys for n points."""
        return replace(self, n=n, prime=choose_prime(n))

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @staticmethod
    def from_json(text: str) -> CoverPlan:
        got = json.loads(text)
        got["radii"] = tuple(got["radii"])
        if got["labels_override"] is not None:
            got["labels_override"] = tuple(got["labels_override"])
        return CoverPlan(**got)


#: Parts by radius of the published practice: fixed values. Each is (greatest radius, parts).
POLICIES = {
    "low": ((9, 1), (None, 2)),
    "ratings": ((7, 1), (13, 2), (None, 3)),
    "words": ((9, 1), (19, 2), (None, 3)),
}


def plan_cover(d: int, n: int, r: int, c: float = 2.0, mode: str = "auto", t: int | None = None, policy: str | None = None, radii: str = "equal", prime: int | None = None, **more) -> CoverPlan:
    """Replicate small radii, cut large ones into parts, leave the rest: so that c * r comes near log2 of the data size.

    `policy` takes the parts from a table instead. `radii='general'` gives parts uneven radii whose sum plus parts is
    one more than the radius, the least that still covers.
    """
    if r < 0 or d < 1:
        raise ValueError("radius from 0, width from 1")
    if c < 1:
        raise ValueError("c is a ratio of at least 1")
    size = math.log2(n) if n > 1 else 0.0
    if policy:
        t = next(parts for top, parts in POLICIES[policy] if top is None or r <= top)
        mode = "partition" if t > 1 else "none"
    elif mode == "auto":
        if size <= 0 or r == 0 or c * r == size:
            mode, t = "none", 1
        elif c * r < size:
            mode, t = "replicate", t or int(size // (c * r))
        else:
            mode, t = "partition", t or math.ceil(c * r / size)
        if t == 1:
            mode = "none"
    elif mode == "none":
        t = 1
    elif t is None:
        t = max(1, int(size // (c * r)) if mode == "replicate" else math.ceil(c * r / size))
    if mode == "partition" and t > d:
        raise ValueError("more parts than positions")
    uneven: tuple[int, ...] = ()
    if radii == "general" and mode == "partition":
        spare = r + 1 - t
        if spare < 0:
            raise ValueError("more parts than the radius has room for")
        uneven = tuple(spare // t + (p < spare % t) for p in range(t))
    plan = CoverPlan(d, r, n, c, mode, t, prime=prime or choose_prime(n), radii=uneven, **more)
    if max(map(plan.bits, range(plan.parts))) > MOST_TABLE_BITS + 1:
        raise ValueError(f"2 ** {max(map(plan.bits, range(plan.parts)))} tables: use more parts, or scan")
    return plan


@dataclass(frozen=True)
class SamplePlan:
    d: int
    k: int
    tables: int
    prime: int = P31
    seed: int = draws.SEED
    replace: bool = True

    @cached_property
    def positions(self) -> list[list[int]]:
        return draws.sampled_positions(self.tables, self.k, self.d, self.seed, self.replace)

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "positions"}  # drawn again where they are needed

    def sized(self, n: int) -> SamplePlan:
        """The same positions, with keys for n points."""
        return replace(self, prime=choose_prime(n))

    def seeds(self) -> list[list[int]]:
        return [(draws.numbers(f"{self.seed}:bs:{t}:", self.k) % self.prime).tolist() for t in range(self.tables)]


def plan_bit_sampling(d: int, n: int, r: int, delta: float = 0.1, tables: int | None = None, k: int | None = None, mode: str = "delta", c: float = 2.0, k_rounding: str = "ceil", replace: bool = True, prime: int | None = None, seed: int = draws.SEED) -> SamplePlan:
    """k from the chance to miss a point at distance r in all tables; `mode='theory'` sets both from c instead.

    Rounding up is the published rule; rounding down keeps the promised chance at distance exactly r.
    """
    if not 0 < delta < 1:
        raise ValueError("a miss chance within 0 and 1; for 0 use a covering family")
    if mode == "theory":
        far = 1 - min(c * r, d - 1) / d
        k = k or max(1, math.ceil(math.log2(max(n, 2)) / math.log2(1 / far)))
        tables = tables or max(1, math.ceil(max(n, 2) ** rho(d, r, c)))
    if tables is None:
        tables = plan_cover(d, n, r, mode="none").total_tables
    if k is None:
        if r == 0:
            k = d
        else:
            x = math.log(1 - delta ** (1 / tables)) / math.log(1 - min(r, d - 1) / d)
            k = max(1, math.ceil(x) if k_rounding == "ceil" else math.floor(x))
    if tables < 1 or k < 1:
        raise ValueError("at least one table of one bit")
    return SamplePlan(d, k, tables, prime or choose_prime(n), seed, replace)


@dataclass(frozen=True)
class SubstringPlan:
    d: int
    bounds: tuple[tuple[int, int], ...]
    radii: tuple[int, ...]

    @property
    def tables(self) -> int:
        return len(self.bounds)

    def probes(self, table: int) -> int:
        lo, hi = self.bounds[table]
        return sum(math.comb(hi - lo, i) for i in range(self.radii[table] + 1)) if self.radii[table] >= 0 else 0


def plan_multi_index(d: int, n: int, r: int, T: int | None = None, radii: str = "equal") -> SubstringPlan:
    """T substrings of equal width, the last with the remainder; each probed within the share of the radius.

    `radii='general'` lowers the radius of substrings by one behind the remainder: still complete, with fewer probes.
    """
    T = min(d, max(1, T or math.ceil(d / math.log2(max(n, 2)))))
    size = d // T
    bounds = tuple((i * size, (i + 1) * size if i < T - 1 else d) for i in range(T))
    each = [r // T] * T
    if radii == "general":
        each = [r // T if i <= r - T * (r // T) else r // T - 1 for i in range(T)]
    return SubstringPlan(d, bounds, tuple(each))


# Closed forms.


def rho(d: int, r: float, c: float) -> float:
    """Exponent of the searches by sampled bits: about 1 / c."""
    near, far = probabilities(d, r, c)
    return math.log(near) / math.log(far)


def probabilities(d: int, r: float, c: float) -> tuple[float, float]:
    """Chances that one sampled bit agrees at distance r and at distance c * r."""
    return 1 - r / d, max(1 - c * r / d, 1e-12)


def expected_collisions(plan: CoverPlan, distance: float) -> float:
    """Upper bound of the mean number of shared buckets of a pair at a distance, by mode of the plan."""
    if plan.mode == "replicate":
        return 2.0 ** (plan.bits() - plan.copies * distance)
    if plan.mode == "partition":
        t = plan.parts
        return sum(2.0 ** plan.bits(p) for p in range(t)) / t * t * (1 - 1 / (2 * t)) ** distance
    if plan.skip_zero:
        size = 1 << plan.bits()
        return size * (0.5 - 1 / size) ** distance
    return 2.0 ** (plan.bits() - distance)


def expected_far(n: int, r: int, c: float) -> tuple[float, float]:
    """Bounds of collisions with far points over all tables: covering family, and classic sampling."""
    return n * 2.0**r / 2.0 ** (c * r), n ** (1 / c)


def hash_cost(method: str, d: int, L: int, k: int = 0) -> float:
    """Operations of hashing one point into L tables."""
    return {"transform_cover": d + L * math.log2(max(L, 2)), "masked_cover": d * L, "bit_sampling": k * L, "multi_index": d, "linear_scan": 0}[method]


def theory_cost(n: int, c: float) -> tuple[float, float]:
    """Query time and space, as powers of the data size, of an early-stopping search."""
    return n ** (1 / c), n ** (1 + 1 / c)


def min_family_size(r: int) -> float:
    """Least size of any covering family of width 2 ** (r + 1): above 2 ** r."""
    return math.comb(1 << (r + 1), r) / math.comb(1 << r, r)


#: Bound of the factor that equal parts cost in the exponent: a fixed value of the analysis.
PARTITION_PENALTY = math.log(4)


def ball_size(d: int, r: int) -> int:
    return sum(math.comb(d, i) for i in range(min(r, d) + 1))
