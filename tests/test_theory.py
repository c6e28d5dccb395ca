"""Algebra without data: encodings, the privacy ratio, moments, variances."""

import itertools
import math

import numpy as np
import pytest

from privfreq.measures import theory
from privfreq.operators import reports
from privfreq.operators.sketch import countmin_shape
from privfreq.params import SMALL, ZIPF, Params
from privfreq.plans import kernels


def test_encodings_differ_in_one_place():
    assert reports.encode(2, 6) == [-1, -1, 1, -1, -1, -1]
    assert reports.encode(None, 6) == [-1] * 6


def test_parameters():
    assert ZIPF.g == 56 and ZIPF.but(g_rule="exp").g == 55
    assert countmin_shape(0.1, 0.01) == (28, 5)
    with pytest.raises(ValueError):
        Params(eps=0)


@pytest.mark.parametrize("eps", [1.0, 4.0])
def test_privacy_ratio_by_enumeration(eps):
    p = SMALL.but(eps=eps, m=4)

    def chance(out, vector):
        return math.prod(p.q if o != v else 1 - p.q for o, v in zip(out, vector))

    dummy, a, b = reports.encode(None, 4), reports.encode(0, 4), reports.encode(3, 4)
    outs = list(itertools.product((-1, 1), repeat=4))
    assert max(chance(o, dummy) / chance(o, a) for o in outs) == pytest.approx(math.exp(eps / 2))
    assert max(chance(o, a) / chance(o, b) for o in outs) == pytest.approx(math.exp(eps))


def test_moments_of_one_bit():
    """A debiased cell: 1 at the own item, 0 for a dummy; second moment from the flip chances, summed exactly."""
    p = SMALL
    for sent, mean in ((1, 1.0), (-1, 0.0)):
        values = [(p.q, -sent), (1 - p.q, sent)]
        first = sum(w * (p.c * bit + 1) / 2 for w, bit in values)
        second = sum(w * ((p.c * bit + 1) / 2) ** 2 for w, bit in values)
        assert first == pytest.approx(mean, abs=1e-12)
        assert second == pytest.approx((p.c**2 - 1) / 4 + mean)


def test_light_variance_matches_simulation():
    p = Params(eps=2.0, m=8, k=3)
    expected = theory.exact_light_variance([5, 7, 3], 20, 5, p)
    assert expected == pytest.approx(35.07, abs=0.01)
    rng = np.random.default_rng(3)
    trials, total = 20_000, np.zeros(20_000)
    where = rng.integers(0, p.m, (trials, p.k, 3))
    for item, n in enumerate((5, 7, 3, 20)):
        for _ in range(n):
            j = rng.integers(0, p.k, trials)
            probe = where[np.arange(trials), j, 0]
            plus = (where[np.arange(trials), j, item] == probe) if item < 3 else np.zeros(trials, bool)
            plus ^= rng.random(trials) < p.q
            total += (p.c * np.where(plus, 1, -1) + 1) / 2
    corrected = p.m / (p.m - 1) * (total - 15 / p.m)
    assert corrected.mean() == pytest.approx(5, abs=5 * math.sqrt(35.07 / trials) * p.m / (p.m - 1))
    assert total.var() == pytest.approx(expected, rel=0.06)


def test_butterfly_is_the_parity_matrix():
    x = np.arange(8)
    matrix = np.array([[(-1) ** bin(a & b).count("1") for b in range(8)] for a in range(8)])
    assert (kernels.butterfly(x) == matrix @ x).all()


def test_counter_flips_rate_and_repeatability():
    seeds = np.arange(1, 4001, dtype=np.uint64)
    flips = kernels.counter_flips(seeds, 64, 0.119)
    assert abs(flips.mean() - 0.119) < 5 * math.sqrt(0.119 * 0.881 / flips.size)
    assert (kernels.counter_flips(seeds[100:200], 64, 0.119) == flips[100:200]).all()
    assert abs(np.corrcoef(flips[:, 0], flips[:, 1])[0, 1]) < 0.08


@pytest.mark.parametrize("q,m", [(0.119, 64), (0.018, 1024), (0.45, 16)])
def test_gap_flips_are_independent_coins(q, m):
    seeds = np.arange(1, 6001, dtype=np.uint64)
    row, place = kernels.gap_flips(seeds, m, q)
    flips = np.zeros((6000, m), bool)
    flips[row, place] = True
    assert flips.sum() == len(row)
    assert abs(flips.mean() - q) < 5 * math.sqrt(q * (1 - q) / flips.size)
    assert (abs(flips.mean(0) - q) < 6 * math.sqrt(q * (1 - q) / 6000)).all()
    assert abs(np.corrcoef(flips[:, 0], flips[:, 1])[0, 1]) < 0.08 and abs(flips.sum(1).var() / (m * q * (1 - q)) - 1) < 0.1
    again = kernels.gap_flips(seeds[100:200], m, q)
    other = np.zeros((100, m), bool)
    other[again] = True
    assert (other == flips[100:200]).all()


def test_report_sizes():
    assert theory.report_bytes(ZIPF, "onehot") == 129 and theory.report_bytes(ZIPF, "pooled_lh") == 2
