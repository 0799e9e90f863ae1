import math
import random

import numpy as np
import pytest

from hamcover.plans import draws
from hamcover.plans.hadamard import as_signs, collision_count, covers, fwht, hadamard_code, hadamard_codes, mask_bits, rank
from hamcover.plans.params import (
    CoverPlan,
    SubstringPlan,
    ball_size,
    choose_prime,
    expected_collisions,
    min_family_size,
    plan_bit_sampling,
    plan_cover,
    plan_multi_index,
    rho,
)


def bits_of(text):
    return np.array([int(c) for c in text])


def test_example_four_bits():
    labels = [0b011, 0b100, 0b101, 0b001]
    masks = mask_bits(labels, 3)
    assert ["".join(map(str, m)) for m in masks] == ["1011", "1000", "0011", "0110", "1101", "1110", "0101"]
    x, q = bits_of("0011"), bits_of("1010")
    met = [(v, "".join(map(str, x & m))) for v, m in enumerate(masks, 1) if ((x & m) == (q & m)).all()]
    assert met == [(4, "0010")]


def test_example_eight_bits():
    masks = mask_bits(draws.labels_identity(8, 3), 3)
    x, y, q = map(bits_of, ("00110011", "00110001", "00111010"))
    assert (x != q).sum() == 2 and (y != q).sum() == 3
    assert [(v, "".join(map(str, x & m))) for v, m in enumerate(masks, 1) if ((x & m) == (q & m)).all()] == [(3, "00100010")]
    assert not [v for v, m in enumerate(masks, 1) if ((y & m) == (q & m)).all()]


def test_code_matrix():
    codes = hadamard_codes(3)
    assert codes.tolist() == [hadamard_code(v, 3) for v in range(8)]
    signs = as_signs(codes)
    assert (signs @ signs.T == 8 * np.eye(8)).all()
    x = np.arange(8)
    assert fwht(x[:, None].copy())[:, 0].tolist() == (signs @ x).tolist()


def test_transform_is_its_own_inverse():
    x = np.random.default_rng(0).integers(0, 1000, (64, 5))
    assert (fwht(fwht(x.copy())) == 64 * x).all()


@pytest.mark.parametrize("d,r", [(4, 1), (6, 2), (8, 3), (10, 2), (12, 3), (9, 4)])
@pytest.mark.parametrize("seed", range(3))
def test_every_label_map_covers(d, r, seed):
    assert covers(mask_bits(draws.labels_random(d, r + 1, seed), r + 1), r)
    assert covers(mask_bits([1] * d, r + 1), r)
    if d <= 1 << (r + 1):
        assert covers(mask_bits(draws.labels_permuted(d, r + 1, seed), r + 1), r)


def test_collisions_are_told_by_rank():
    rng = random.Random(1)
    for _ in range(200):
        d, r = rng.randint(4, 40), rng.randint(1, 5)
        labels = draws.labels_random(d, r + 1, rng.randint(0, 99))
        z = [i for i in range(d) if rng.random() < 0.2]
        shared = (mask_bits(labels, r + 1)[:, z].sum(axis=1) == 0).sum()
        assert shared == collision_count(z, labels, r + 1)
        if len(z) <= r:
            assert shared >= 1
    assert rank([1, 2, 3]) == 2


def test_expectation_bound():
    d, r, distance, runs = 64, 4, 6, 400
    got = [collision_count(list(range(distance)), draws.labels_random(d, r + 1, seed), r + 1) for seed in range(runs)]
    bound = expected_collisions(CoverPlan(d, r, 1000), distance)
    assert np.mean(got) <= bound + 3 * np.std(got) / math.sqrt(runs)


def test_replication_and_parts_keep_covering():
    rng = random.Random(2)
    for mode, t, r in (("replicate", 2, 2), ("partition", 2, 5), ("partition", 3, 7)):
        plan = plan_cover(24, 1000, r, mode=mode, t=t)
        families = [(where, mask_bits(labels, plan.bits(p))) for p in range(plan.parts) for where, labels, _ in [plan.columns(p)]]
        for _ in range(200):
            z = np.zeros(24, int)
            z[rng.sample(range(24), r)] = 1
            assert any((z[w] @ m.T == 0).any() for w, m in families)


def test_uneven_parts():
    plan = plan_cover(64, 1000, 10, mode="partition", t=3, radii="general")
    assert sum(r + 1 for r in plan.radii) == 11
    assert plan.total_tables < plan_cover(64, 1000, 10, mode="partition", t=3).total_tables + 1


def test_published_table_counts():
    for mode, r, t, tables in [("replicate", 2, 4, 511), ("replicate", 3, 3, 1023), ("replicate", 4, 2, 511), ("replicate", 5, 2, 2047), ("partition", 10, 2, 126), ("partition", 12, 2, 254), ("partition", 14, 2, 510), ("partition", 16, 2, 1022)]:
        assert plan_cover(128, 65_536, r, mode=mode, t=t).total_tables == tables
    assert plan_cover(128, 2**24, 6, 4.0).mode == "none" and plan_cover(128, 2**24, 6, 4.0).total_tables == 127
    assert plan_multi_index(128, 65_536, 3).tables == 8
    assert plan_multi_index(128, 50_000, 6).tables <= 10


def test_chooser():
    assert plan_cover(128, 2**16, 2).mode == "replicate" and plan_cover(128, 2**16, 2).t == 4
    assert plan_cover(128, 2**16, 10).mode == "partition" and plan_cover(128, 2**16, 10).t == 2
    assert plan_cover(64, 1, 3).mode == "none" and plan_cover(64, 1000, 0).mode == "none"
    assert [plan_cover(512, 1000, r, policy="words").parts for r in (9, 10, 19, 20, 29)] == [1, 2, 2, 3, 3]
    assert [plan_cover(2000, 1000, r, policy="ratings").parts for r in (7, 8, 13)] == [1, 2, 2]
    with pytest.raises(ValueError):
        plan_cover(128, 1000, 40, mode="none")
    with pytest.raises(ValueError):
        plan_cover(8, 1000, 3, mode="partition", t=9)
    assert CoverPlan.from_json(plan_cover(64, 1000, 6).to_json()) == plan_cover(64, 1000, 6)


def test_sampled_bits():
    ks = lambda d, r, L: [plan_bit_sampling(d, 1000, r, x, tables=L).k for x in (0.1, 0.01)]
    assert ks(128, 6, 127) == [84, 70] and ks(128, 2, 511) == [344, 300] and ks(128, 3, 1023) == [258, 228]
    assert ks(128, 4, 511) == [171, 149] and ks(128, 5, 2047) == [171, 154]
    assert [plan_bit_sampling(128, 1000, r, 0.1, tables=L).k for r, L in ((10, 126), (12, 254), (14, 510), (16, 1022))] == [50, 48, 47, 46]
    plan = plan_bit_sampling(64, 1000, 9, 0.1, tables=1023, k_rounding="floor")
    assert 1 - (1 - (1 - 9 / 64) ** plan.k) ** 1023 >= 0.9
    with pytest.raises(ValueError):
        plan_bit_sampling(64, 1000, 6, 0.0)
    assert 0.4 < rho(128, 6, 2.0) < 0.55
    theory = plan_bit_sampling(128, 10_000, 6, mode="theory", c=2.0)
    assert theory.k > 1 and theory.tables >= 1
    assert len(set(plan_bit_sampling(64, 1000, 6, tables=3, k=20, replace=False).positions[0])) == 20


def test_substrings():
    plan = plan_multi_index(64, 1000, 8)
    assert plan.tables == 7 and plan.bounds[-1] == (54, 64)
    assert plan_multi_index(64, 1000, 8, radii="general").radii == (1, 1, 0, 0, 0, 0, 0)
    assert SubstringPlan(64, ((0, 32),), (2,)).probes(0) == 529
    assert ball_size(128, 6) > 5 * 10**9


def test_primes_and_bounds():
    assert choose_prime(46_340) == 2**31 - 1 and choose_prime(46_342) == 2**61 - 1
    assert all(min_family_size(r) >= 2**r for r in range(1, 5))


def test_labels():
    assert sorted(draws.labels_permuted(16, 4)) == list(range(16))
    assert 0 not in draws.labels_permuted(15, 4, skip_zero=True) and 0 not in draws.labels_random(200, 3, skip_zero=True)
    with pytest.raises(ValueError):
        draws.labels_permuted(16, 4, skip_zero=True)
    parts = draws.part_positions(10, 3)
    assert sorted(sum(parts, [])) == list(range(10)) and [len(p) for p in parts] == [3, 3, 4]
    assert draws.number("a") == int("0cc175b9c0f1b6a831c399e269772661"[:15], 16)
