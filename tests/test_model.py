"""The worked example, and properties of blocks, fits and scores on seeded random collections."""

import math
import random

import numpy as np
import pytest

from quillon.functions import scores as S
from quillon.operators import blocks as B
from quillon.operators import sizes as Z
from quillon.operators.maxent import MaxEntModel, shift


def bits(text):
    return sum(1 << "abcdefgh".index(c) for c in text)


SETS = [bits("abc"), bits("cd"), bits("def")]


def test_running_example():
    model = MaxEntModel(8, SETS, [0.5, 0.4, 0.8]).fit(1e-12, 5000)
    assert model.mult == pytest.approx([28.533792, 0.118528, 85.477273], rel=1e-6)
    assert 1 / model.total() / 256 == pytest.approx(3.023924e-4, rel=1e-6)
    assert model.query(bits("agh")) == pytest.approx(0.185310, abs=1e-6)
    assert model.log_likelihood(1) == pytest.approx(-5.370695, abs=1e-6)


def test_block_sizes_of_the_example():
    found = B.closed_blocks(SETS)
    cumulative = B.cumulative(found, B.independent_mass([0.5] * 8))
    assert sorted(round(v[0] * 256) for v in cumulative.values()) == [4, 16, 16, 32, 32, 64, 256]
    quick, few = B.quick_sizes(SETS, found, cumulative)
    assert sorted(round(v[0] * 256) for v in quick.values()) == [4, 12, 12, 16, 16, 36, 160]
    assert few < B.quadratic_sizes(found, cumulative)[1]


def test_quick_equals_quadratic_equals_enumeration():
    rng = random.Random(5)
    for _ in range(60):
        sets = rng.sample([x for x in range(512) if x.bit_count() > 1], rng.randint(1, 5))
        found = B.closed_blocks(sets)
        cumulative = B.cumulative(found, B.independent_mass([0.5] * 9))
        quick, slow = B.quick_sizes(sets, found, cumulative)[0], B.quadratic_sizes(found, cumulative)[0]
        for b in found:
            rows = sum(B.signature(r, sets) == b for r in range(512))
            assert quick[b][0] * 512 == pytest.approx(rows) == pytest.approx(slow[b][0] * 512)


@pytest.mark.parametrize("rows", [False, True])
def test_fit_meets_constraints_and_has_product_form(rows):
    rng = random.Random(3)
    for _ in range(6):
        m = 6
        p = [rng.random() for _ in range(1 << m)]
        total = sum(p)
        f = lambda x: sum(v for k, v in enumerate(p) if k & x == x) / total  # noqa: E731,B023
        sets = rng.sample([x for x in range(1 << m) if x.bit_count() > 1], 3)
        by_size = [sum(v for k, v in enumerate(p) if k.bit_count() == j) / total for j in range(m + 1)]
        model = MaxEntModel(m, sets, [f(x) for x in sets], [f(1 << i) for i in range(m)], by_size if rows else None).fit()
        q = [model.row_probability(k) for k in range(1 << m)]
        assert sum(q) == pytest.approx(1)
        assert [model.query(x) for x in sets] == pytest.approx([f(x) for x in sets], abs=1e-7)
        assert model.query(21) == pytest.approx(sum(v for k, v in enumerate(q) if k & 21 == 21))
        assert model.log_likelihood(1) == pytest.approx(sum(v / total * math.log2(w) for v, w in zip(p, q)), abs=1e-6)
        if rows:
            assert model.size_probabilities() == pytest.approx(by_size, abs=1e-7)


def test_row_sizes():
    assert Z.size_distribution([0.5, 0.25, 0.1]) == pytest.approx([0.3375, 0.4875, 0.1625, 0.0125])
    big = Z.size_distribution([0.95] + [0.3] * 59)
    assert np.abs(Z.without(big, 0.95) - Z.size_distribution([0.3] * 59)).max() < 1e-12
    assert Z.updated(big, 0.95, 0.2) == pytest.approx(Z.size_distribution([0.2] + [0.3] * 59), abs=1e-12)


def test_scores():
    assert S.kl2_value(0.5, 0.125) == pytest.approx(0.5963225, abs=1e-7)
    assert S.kl2_value(0.18, 0.19) == pytest.approx(0.00047519, abs=1e-8)
    assert S.kl2_value(0.7, 0.19) == pytest.approx(0.8870610, abs=1e-7)
    assert S.set_bits(6000, 50, True) == pytest.approx(14.99344, abs=1e-4)
    assert S.binomial_two_tailed(10, 20, 0.3) == pytest.approx(0.0834450, abs=1e-6)
    assert S.mdl(-10, 0, 0, 100, 5) - S.bic(-10, 0, 100) == pytest.approx(1)
    assert shift(1.0, 2, 0.1) == pytest.approx(0.925)


def test_branch_bound_holds():
    rng = random.Random(1)
    for _ in range(300):
        low, high = sorted((rng.random(), rng.random()))
        e_low, e_high = sorted((rng.random(), rng.random()))
        fr, est = rng.uniform(low, high), rng.uniform(e_low, e_high)
        assert S.kl2_value(fr, est) <= S.branch_bound(high, e_high, low, e_low) + 1e-12


def test_groups_and_cap():
    assert B.groups([3, 12, 6, 48]) == [[0, 1, 2], [3]]
    assert B.admissible(SETS, bits("gh"), 2) and not B.admissible(SETS, bits("ad"), 5)
