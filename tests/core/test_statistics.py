"""Laws of the estimators over fixed seeds, and the misprints that the survey settles."""

import math

import numpy as np
import pytest

from evsketch.functions.gumbel import EULER_GAMMA, VARIANCE, geometric_bias
from evsketch.operators.accuracy import bits_for, space_table
from evsketch.operators.baselines import loglog_alpha
from evsketch.workloads import measures

SF = "/root/testdata/sf0.001"


def draws(n, k, runs, seed):
    """Registers of ``runs`` full sketches of n items: Gumbel at ln n."""
    return np.random.default_rng(seed).gumbel(math.log(n), 1, (runs, k))


def test_full_geometric_bias_scale_and_coverage():
    n, k = 10_000, 64
    z = np.exp(draws(n, k, 4000, 1).mean(1) - EULER_GAMMA)
    assert z.mean() / n == pytest.approx(geometric_bias(k), abs=0.01)
    assert geometric_bias(k) == pytest.approx(1 + math.pi**2 / (12 * k), abs=0.001)
    assert math.sqrt(k) * z.std() / n == pytest.approx(math.sqrt(VARIANCE), rel=0.06)
    assert (np.abs(z - n) / n <= math.pi / math.sqrt(k)).mean() >= 5 / 6


def test_harmonic_scale_and_debias():
    n, k = 10_000, 64
    z = k / np.exp(-draws(n, k, 4000, 2)).sum(1)
    assert z.mean() / n == pytest.approx(k / (k - 1), abs=0.01)
    assert math.sqrt(k) * z.std() / n == pytest.approx(1, rel=0.06)


def test_shift_rounding_variance_is_one_twelfth():
    rng = np.random.default_rng(3)
    x, c = rng.gumbel(0, 1, 2_000_000), rng.random(2_000_000)
    y = np.floor(x + c) - c
    assert y.mean() == pytest.approx(EULER_GAMMA - 0.5, abs=0.005)
    assert y.var() == pytest.approx(VARIANCE + 1 / 12, abs=0.01)
    assert abs(y.var() - (VARIANCE + 0.25)) > 0.1
    assert np.exp(-y).mean() / np.exp(-x).mean() == pytest.approx(math.e - 1, rel=0.01)


def test_lower_tail_and_inverse_product_by_enumeration():
    def splits(n, k):
        if k == 1:
            yield (n,)
            return
        for i in range(n + 1):
            for rest in splits(n - i, k - 1):
                yield (i, *rest)

    for n, k in ((4, 3), (6, 4), (9, 2)):
        total = sum(math.factorial(n) / math.prod(map(math.factorial, s)) * k**-n * math.prod(1 / (i + 1) for i in s) for s in splits(n, k))
        assert total <= (k / n) ** k + 1e-12


def test_loglog_constants():
    assert loglog_alpha(64) == pytest.approx(0.39178, abs=1e-5)
    assert loglog_alpha(1024) == pytest.approx(0.39669, abs=1e-5)


def test_space_orders():
    bits = dict(space_table(0.05, 0.01, 1e9, 2.0**32))
    assert bits["shift_rounded_registers"] < bits["rounded_registers"] < bits["real_registers"] < bits["bitmap"]
    assert bits_for(-4, 45) == 6


@pytest.fixture(scope="module")
def compared(spark):
    return {r.method: r for r in measures.a_method_compare(spark, SF).collect()}


def test_who_wins_at_equal_k(compared):
    assert compared["averaged_harmonic"].norm_std < compared["averaged_geometric"].norm_std
    assert compared["full_harmonic"].norm_std < compared["full_geometric"].norm_std
    assert compared["full_geometric"].coverage >= 5 / 6 and compared["averaged_geometric"].coverage >= 2 / 3
    assert compared["averaged_shifted"].norm_std == pytest.approx(1.3146, rel=0.35)


def test_error_falls_with_k_and_n(spark):
    by = {(r.method, r.k): r for r in measures.a_error_sweep_k(spark, SF).collect()}
    std = [by["harmonic", k].norm_std / math.sqrt(k) for k in (16, 64, 256)]
    assert std[0] > std[1] > std[2]
    assert by["geometric", 1024].bias > by["geometric", 64].bias  # out of regime at n = 1,500
    below = {r.below: r for r in measures.a_error_sweep_n(spark, SF).collect()}
    assert below[64].bias > below[512].bias > below[15000].bias
