"""Normalising constants and error laws, by numerical integration on the driver.

Positions are centred so that a row expects one live element in the cell of position 0.  A
cell at position z is then non-zero with probability r * (1 - exp(-2^-z)), r = 1 - 1/order,
and the highest non-zero position, with a uniform offset, has density ``shape_density``.
``base2_moment(t)`` is the integral of 2^(t z) under it.  Nothing here starts a job.
"""

from __future__ import annotations

import functools
import math

import numpy as np

_LOW, _HIGH, _STEP, _TERMS = -40.0, 80.0, 0.002, 130


def survival(order: float) -> float:
    """1 - 1/order; 1 in the limit of large fields."""
    return 1.0 if math.isinf(order) else 1.0 - 1.0 / order


@functools.lru_cache(maxsize=64)
def _grid(r: float) -> tuple[np.ndarray, np.ndarray]:
    z = np.arange(_LOW, _HIGH + _STEP / 2, _STEP)
    log_above = np.zeros_like(z)
    for j in range(1, _TERMS):
        with np.errstate(divide="ignore"):
            log_above += np.log1p(r * np.expm1(-np.exp2(-(z + j))))
    return z, r * -np.expm1(-np.exp2(-z)) * np.exp(log_above)


def shape_density(z: float, r: float) -> float:
    grid, density = _grid(r)
    return float(np.interp(z, grid, density))


@functools.lru_cache(maxsize=1024)
def base2_moment(t: float, r: float) -> float:
    """Finite for t < 1 only."""
    if t >= 1:
        raise ValueError("the moment is finite only below 1")
    z, density = _grid(r)
    body = float(np.trapezoid(np.exp2(t * z) * density, dx=_STEP))
    return body + r * 2.0 ** (-(1 - t) * _HIGH) / ((1 - t) * math.log(2))


@functools.lru_cache(maxsize=128)
def log_moments(order: float) -> tuple[float, float]:
    """(mean, variance) of the centred highest position: the large-m constants."""
    z, density = _grid(survival(order))
    mean = float(np.trapezoid(z * density, dx=_STEP))
    return mean, float(np.trapezoid((z - mean) ** 2 * density, dx=_STEP))


def finite_factor(m: int, order: float) -> float:
    """The unbiased estimator's factor for m rows; m of 3 at least, for a finite variance."""
    if m < 3:
        raise ValueError("m must be 3 at least")
    return base2_moment(1 / m, survival(order)) ** -m * m


def variance_ratio(m: int, order: float) -> float:
    """Variance of the estimate over the square of the truth, for m rows."""
    r = survival(order)
    return base2_moment(1 / m, r) ** (-2 * m) * base2_moment(2 / m, r) ** m - 1


def asymptotic_factor(m: int, order: float) -> float:
    return 2 ** -log_moments(order)[0] * m


def error_constant(order: float) -> float:
    """Relative standard error times the square root of m, for large m."""
    return math.log(2) * math.sqrt(log_moments(order)[1])


#: Above every field's error constant.
UNIVERSAL_BOUND = math.sqrt(79)


def cell_nonzero_probability(support: float, level: int, offset: float, m: int, order: float) -> float:
    return -math.expm1(-support * 2.0 ** (-level - offset) / m) * survival(order)


def rows_for(eps: float, order: float, fail: float = 1 / 3) -> int:
    """The fewest rows for relative error eps at that failure probability, by Chebyshev's inequality."""
    target, low, high = eps * eps * fail, 3, 4
    while variance_ratio(high, order) > target:
        low, high = high, high * 2
    while low < high:
        middle = (low + high) // 2
        low, high = (low, middle) if variance_ratio(middle, order) <= target else (middle + 1, high)
    return low
