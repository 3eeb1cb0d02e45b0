"""Prime pools for counting integers modulo a random prime.  All on the driver, from bounds known before the stream."""

from __future__ import annotations

import math
import random

import numpy as np

from ..functions.algebra import is_prime


def primes_up_to(n: int) -> np.ndarray:
    sieve = np.ones(max(n + 1, 2), bool)
    sieve[:2] = False
    for i in range(2, int(n**0.5) + 1):
        if sieve[i]:
            sieve[i * i :: i] = False
    return np.flatnonzero(sieve)


#: Up to here primes are sieved, beyond it candidates are tested one by one.
SIEVED = 1 << 22


def first_primes(count: int, least: float = 2) -> list[int]:
    """The ``count`` smallest primes of ``least`` or more.  No memory but the list's, however large ``least``."""
    if least < SIEVED:
        limit = max(32, int(least * 1.2 + count * 20))
        while limit < 4 * SIEVED:
            found = primes_up_to(limit)
            found = found[found >= least]
            if len(found) >= count:
                return found[:count].tolist()
            limit *= 2
    out, n = [], max(3, math.ceil(least)) | 1
    if least <= 2:
        out.append(2)
    while len(out) < count:
        if is_prime(n):
            out.append(n)
        n += 2
    return out[:count]


def above_max(linf: int) -> int:
    """The smallest prime above the largest frequency: counting modulo it loses nothing."""
    return first_primes(1, linf + 1)[0]


def pool_by_max(linf: float, eps: float) -> list[int]:
    """The 10 log2(linf) / eps smallest primes: all but a tenth of them lose at most eps of the support."""
    if linf < 2:
        return [2]
    return first_primes(math.ceil(10 * math.log2(linf) / eps))


def pool_by_mean(mean: float, eps: float) -> list[int]:
    """10 / eps primes of at least the mean non-zero frequency, with the same guarantee."""
    return first_primes(math.ceil(10 / eps), max(2.0, mean))


def pool_by_power_mean(power_mean: float, eps: float) -> list[int]:
    """As by the mean, with a power mean of exponent below one in its place, which is smaller."""
    return pool_by_mean(power_mean, eps)


def wide_range(linf: float, eps: float) -> tuple[int, int]:
    """The range of the earlier estimator's primes: from D to D^3, D = log2(linf) / eps."""
    d = max(2.0, math.log2(max(2.0, linf)) / eps)
    return math.ceil(d), int(d**3)


def pool_wide(linf: float, eps: float) -> list[int]:
    """All primes of that range."""
    low, high = wide_range(linf, eps)
    found = primes_up_to(high)
    return found[found >= low].tolist()


def draw_between(low: int, high: int, seed: int) -> int:
    """A uniform prime of a range that has one, without listing them: numbers are drawn until one is prime."""
    source = random.Random(f"between/{seed}")
    while not is_prime(n := source.randint(low, high)):
        pass
    return n


def count_between(low: int, high: int) -> int:
    """How many primes lie in a range: counted up to 2^27, else by the logarithmic integral."""
    if high < 1 << 27:
        found = primes_up_to(high)
        return int((found >= low).sum())
    x = np.exp(np.linspace(math.log(max(low, 2)), math.log(high), 20_001))
    return int(np.trapezoid(1 / np.log(x), x))


def discounted(pool, bound: float, eps: float) -> list[int]:
    """Any pool for half the error, from a bound that holds without the top eps/2 share of the entries."""
    return pool(bound, eps / 2)


def draw(pool: list[int], seed: int) -> int:
    """A uniform prime of the pool; the seed must not depend on the data."""
    return random.Random(f"draw/{seed}").choice(pool)
