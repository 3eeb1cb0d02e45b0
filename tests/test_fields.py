import math

import pytest

from fieldtally.functions import calibrate
from fieldtally.functions.algebra import binary_field, check_uniform, field_of_order, find_irreducible, is_prime, monoid
from fieldtally.plans import primes
from fieldtally.plans.sketch_plan import SketchPlan

#: Published constants (fixed values): order, mean, variance, factor / m, relative error * sqrt(m).
PUBLISHED = [(2, -0.1100, 5.588, 1.079, 1.638), (3, 0.5487, 4.321, 0.6836, 1.441), (4, 0.7903, 4.002, 0.5782, 1.387), (5, 0.9173, 3.861, 0.5295, 1.362), (7, 1.049, 3.732, 0.4833, 1.339), (8, 1.088, 3.697, 0.4704, 1.333), (9, 1.118, 3.671, 0.4607, 1.328), (256, 1.326, 3.512, 0.3989, 1.299), (2**32, 1.333, 3.507, 0.3969, 1.298), (math.inf, 1.333, 3.507, 0.3969, 1.298)]


@pytest.mark.parametrize(("order", "mean", "variance", "factor", "error"), PUBLISHED)
def test_constants(order, mean, variance, factor, error):
    m, v = calibrate.log_moments(order)
    assert abs(m - mean) < 6e-4 and abs(v - variance) < 6e-4
    assert abs(2**-m - factor) < 3e-4 and abs(calibrate.error_constant(order) - error) < 1e-3
    assert calibrate.error_constant(order) < calibrate.UNIVERSAL_BOUND


def test_limit_is_closed_form():
    assert abs(calibrate.error_constant(math.inf) - math.sqrt(math.log(2) ** 2 / 12 + math.pi**2 / 6)) < 1e-4
    assert abs(calibrate.base2_moment(0.0, 0.5) - 1) < 1e-6


def test_finite_approaches_asymptotic():
    for q in (2, 3, 256):
        assert abs(calibrate.finite_factor(4096, q) / calibrate.asymptotic_factor(4096, q) - 1) < 2e-3
    m = calibrate.rows_for(0.1, 101)
    assert calibrate.variance_ratio(m, 101) <= 0.01 / 3 < calibrate.variance_ratio(m - 1, 101)


@pytest.mark.parametrize("q", [2, 3, 4, 5, 7, 8, 9])
def test_multiples_and_shifts_of_a_uniform_value_are_uniform(q):
    assert check_uniform(field_of_order(q))


@pytest.mark.parametrize("q", [0, 1, 6, 10, 12])
def test_orders_that_are_no_fields(q):
    with pytest.raises(ValueError):
        field_of_order(q)


def test_irreducible_polynomials():
    assert [find_irreducible(2, k) for k in (2, 3, 4, 8, 16)] == [0x7, 0xB, 0x13, 0x11B, 0x1002B]
    assert binary_field(32).order == 2**32


def test_primality():
    sieved = set(primes.primes_up_to(5000).tolist())
    assert all(is_prime(n) == (n in sieved) for n in range(5001))
    assert is_prime(2**61 - 1) and not is_prime(3215031751) and not is_prime((2**31 - 1) * (2**19 - 1)) and not is_prime(2**62)
    assert primes.above_max(2**31) == 2147483659 and primes.first_primes(2, 10**12) == [1000000000039, 1000000000061]
    assert field_of_order(2**31 - 1).k == 1 and field_of_order(3**7).p == 3


def test_drawn_from_a_range():
    low, high = primes.wide_range(1000, 0.05)
    drawn = [primes.draw_between(low, high, seed) for seed in range(200)]
    assert all(low <= p <= high and is_prime(p) for p in drawn) and max(drawn) > high * 0.9
    assert primes.count_between(low, high) == 534_597


def test_monoids():
    assert monoid("integer", for_sketch=True).signed
    with pytest.raises(ValueError):
        monoid("boolean", for_sketch=True)


def test_prime_pools():
    assert primes.above_max(344) == 347
    assert len(primes.pool_by_max(344, 0.1)) == math.ceil(10 * math.log2(344) / 0.1)
    assert min(primes.pool_by_mean(53.7, 0.1)) == 59 and primes.pool_by_max(1, 0.1) == [2]
    assert primes.draw([2, 3, 5], 7) == primes.draw([2, 3, 5], 7)


def test_plans():
    with pytest.raises(ValueError):
        SketchPlan(2, field_of_order(2))
    assert SketchPlan(64, field_of_order(2)).fingerprint != SketchPlan(64, field_of_order(3)).fingerprint
    assert SketchPlan(64, field_of_order(101)).memory_bits == 64 * 48 * 7


@pytest.mark.parametrize("eps, size", [(0.15, 25_466), (0.05, 534_597)])
def test_the_wide_pool_is_the_whole_range(eps, size):
    pool, d = primes.pool_wide(1000, eps), math.log2(1000) / eps
    assert len(pool) == size and d <= pool[0] < 2 * d and d**3 * 0.99 < pool[-1] <= d**3
    assert primes.pool_wide(1, 0.5) == [2, 3, 5, 7]
